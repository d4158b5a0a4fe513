"""The two relational solvers and the graph baselines, as sweeps of one linear step.

Every method moves a vector to (constant part + weighted sum over linked vectors - weighted totals of whole groups),
divided by a constant or scaled to length 1. Constant parts, link coefficients, denominators and the groups that each
node is pushed by are worked out once. Non-links never exist as rows: the sum over them is the group's total minus
the linked sum, which is folded into the link coefficients. Nodes in the same groups with the same weights share a
signature, so the push is made for each signature, not for each node.

A sweep runs by one of three kernels with equal results. 'broadcast' sends the vectors to all tasks, each of which
holds a part of the links in sorted arrays; it is used while the vectors take up to BROADCAST_BYTES. 'hubs' is for more
nodes, if each link has an end among a few nodes of many links, as columns of few values have: a sweep sends the vectors
of those to all tasks and gets back sums for them, and no other vector moves or is kept between sweeps. 'shuffle' joins
links to vectors and sums with partial aggregation, for any graph at any size.
"""

from __future__ import annotations

import warnings
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tablevec.functions.vectors import vec_add, vec_scale, vec_sub, vec_sum, vec_unit, vec_zero
from tablevec.operators.lexicon import column_centroids
from tablevec.operators.weights import Params, derive_weights, group_repulsion, relation_counts, warn_if_unsafe
from tablevec.plans.stages import Stages

BROADCAST_BYTES = 64 << 20
#: A hub has at least HUB_DEGREE links; there are at most HUBS of them, with HUB_LINKS links among themselves, and RULES
#: rows of pushes. What has more goes by the 'shuffle' kernel.
HUB_DEGREE, HUBS, HUB_LINKS, RULES = 256, 4096, 2_000_000, 50_000
#: Nodes packed in one row, rows in one file (Spark reads a file's rows as one batch), and most bytes of sums that come
#: from all tasks to the driver at once.
CHUNK, FILE_ROWS, SUM_BYTES = 1024, 16, 64 << 20


@dataclass
class Problem:
    """What the solvers need: base (node_id, category, value, vec, is_oov), mirrored links (rel, rel_inv, src, dst)."""

    base: DataFrame
    links: DataFrame
    dims: int
    include_oov: bool = True
    centroids: DataFrame | None = None

    def column_means(self) -> DataFrame:
        if self.centroids is None:
            self.centroids = column_centroids(self.base, self.dims, self.include_oov)
        return self.centroids


@dataclass
class Step:
    """nodes (node_id, const, den, sig), coefs (src, dst, coef), push (sig, rel, rel_inv, coef), targets (rel, rel_inv, dst)."""

    nodes: DataFrame
    coefs: DataFrame
    push: DataFrame | None
    targets: DataFrame | None
    unit: bool
    dims: int
    strict: bool = False
    stuck: bool = False  # whether any denominator is 0: such nodes keep their vectors
    made: Stages | None = None  # tables that only the step reads


@dataclass
class Fit:
    """The fitted vectors (node_id, vec), each sweep's number and relative step, and the least denominator."""

    vectors: DataFrame
    history: list[dict] = field(default_factory=list)
    least_denominator: float | None = None


def check_denominators(least: float | None, strict: bool) -> None:
    """A denominator of 0 has no update, and one below 0 turns it round: an error in strict mode, else a warning."""
    if least is not None and least <= 0:
        if strict:
            raise ValueError(f"the sweeps may diverge: least denominator {least:.3g}")
        warnings.warn(f"the sweeps may diverge: least denominator {least:.3g}", stacklevel=2)


def _signature() -> Column:
    """Of a node's weights: nodes whose groups and repulsions are equal share one; a node is in few groups."""
    return F.xxhash64(F.array_sort(F.collect_list(F.struct("rel", "rel_inv", "rep_w")))).alias("sig")


def _constants(p: Problem, params: Params, each: DataFrame) -> DataFrame:
    """(node_id, category, k, const) and the columns of `each`: base pull plus column pull."""
    rows = p.base.join(each.withColumnRenamed("src", "node_id"), "node_id", "left").na.fill(0, ["k"])
    const = vec_add(vec_scale("vec", F.lit(float(params.base))), vec_scale("centroid", F.lit(float(params.column)) / (F.col("k") + 1)))
    return rows.join(F.broadcast(p.column_means()), "category").withColumn("const", const)


def _push(w: DataFrame, each: DataFrame, coef: Column) -> DataFrame:
    return w.join(each.select("src", "sig"), "src").select("sig", "rel", "rel_inv", coef.alias("coef")).distinct()


def objective_weights(p: Problem, params: Params, mc: str, made: Stages) -> DataFrame:
    """The weights, written once: links, constants, pushes and the look at convexity all read them."""
    return made.keep(derive_weights(p.links, params, "objective", mc=mc))


def objective_step(p: Problem, params: Params, mc: str = "distinct", weights: DataFrame | None = None, made: Stages | None = None) -> Step:
    made = made or Stages(p.base.sparkSession, "weights")
    w = weights if weights is not None else objective_weights(p, params, mc, made)
    own = w.select("rel", "rel_inv", "src", F.col("link_w").alias("own"), F.col("rep_w").alias("rep"))
    mirror = w.select("rel", (~F.col("rel_inv")).alias("rel_inv"), F.col("src").alias("dst"), F.col("link_w").alias("back"))
    joined = p.links.join(own, ["rel", "rel_inv", "src"]).join(mirror, ["rel", "rel_inv", "dst"])
    pull = F.col("own") + F.col("back")
    coefs = made.keep(joined.groupBy("src", "dst").agg(F.sum(pull + 2 * F.col("rep")).alias("coef"), F.sum(pull).alias("pull")))
    pulls = coefs.groupBy("src").agg(F.sum("pull").alias("pull")).withColumnRenamed("src", "node_id")
    away = F.sum(2 * F.col("rep_w") * (F.col("n_dst") - F.col("out_degree"))).alias("away")
    each = made.keep(w.groupBy("src").agg(F.max("k").alias("k"), away, _signature()))
    rows = _constants(p, params, each).join(pulls, "node_id", "left")
    den = F.lit(float(params.base)) + F.lit(float(params.column)) / (F.col("k") + 1) + F.coalesce("pull", F.lit(0.0)) - F.coalesce("away", F.lit(0.0))
    nodes = rows.select("node_id", "category", "const", den.alias("den"), "sig")
    targets = p.links.select("rel", "rel_inv", "dst").distinct()
    return Step(nodes, coefs.select("src", "dst", "coef"), _push(w, each, 2 * F.col("rep_w")), targets, False, p.dims, made=made)


def series_step(p: Problem, params: Params, repulsion: str = "centroid") -> Step:
    made = Stages(p.base.sparkSession, "weights")
    w = made.keep(derive_weights(p.links, params, "series", repulsion))
    coefs = p.links.join(w.select("rel", "rel_inv", "src", "link_w"), ["rel", "rel_inv", "src"]).groupBy("src", "dst").agg(F.sum("link_w").alias("coef"))
    each = made.keep(w.groupBy("src").agg(F.max("k").alias("k"), _signature()))
    nodes = _constants(p, params, each).select("node_id", "category", "const", F.lit(1.0).alias("den"), "sig")
    targets = p.links.select("rel", "rel_inv", "dst").distinct()
    return Step(nodes, coefs, _push(w, each, F.col("rep_w")), targets, True, p.dims, made=made)


def graph_step(p: Problem, update: str = "simplified", category_edges: DataFrame | None = None) -> Step:
    """The classic graph method: undirected distinct links, neighbour weight 1 / degree, base weight 1."""
    made = Stages(p.base.sparkSession, "weights")
    pairs = p.links.select("src", "dst")
    if category_edges is not None:
        pairs = pairs.union(category_edges)
    pairs = made.keep(pairs.where(F.col("src") != F.col("dst")).distinct())
    degree = pairs.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    beta = degree.select("src", (F.lit(1.0) / F.col("deg")).alias("beta"))
    if update == "exact":
        other = beta.select(F.col("src").alias("dst"), F.col("beta").alias("theirs"))
        coefs = pairs.join(beta, "src").join(other, "dst").select("src", "dst", (F.col("beta") + F.col("theirs")).alias("coef"))
    else:
        coefs = pairs.join(beta, "src").select("src", "dst", F.col("beta").alias("coef"))
    den = coefs.groupBy("src").agg((F.lit(1.0) + F.sum("coef")).alias("den")).withColumnRenamed("src", "node_id")
    rows = p.base.join(den, "node_id", "left").select("node_id", "category", F.col("vec").alias("const"), F.coalesce("den", F.lit(1.0)).alias("den"), F.lit(None).cast("long").alias("sig"))
    return Step(rows, coefs, None, None, False, p.dims, made=made)


def _pushed(step: Step, x: DataFrame) -> DataFrame | None:
    """(sig, away): the weighted totals of a signature's groups; as many rows as there are signatures."""
    if step.push is None:
        return None
    totals = step.targets.join(x.select(F.col("node_id").alias("dst"), "vec"), "dst").groupBy("rel", "rel_inv").agg(vec_sum("vec", step.dims).alias("total"))
    return step.push.join(F.broadcast(totals), ["rel", "rel_inv"]).groupBy("sig").agg(vec_sum("total", step.dims, F.col("coef")).alias("away"))


def sweep(step: Step, x: DataFrame, only: str | None = None) -> DataFrame:
    """One pass over all nodes, or those of one category: (node_id, vec)."""
    nodes = step.nodes if only is None else step.nodes.where(F.col("category") == only)
    coefs = step.coefs if only is None else step.coefs.join(nodes.select(F.col("node_id").alias("src")), "src", "left_semi")
    pull = coefs.join(x.select(F.col("node_id").alias("dst"), "vec"), "dst").groupBy("src").agg(vec_sum("vec", step.dims, F.col("coef")).alias("pull"))
    rows = nodes.join(pull.withColumnRenamed("src", "node_id"), "node_id", "left")
    moved = vec_add("const", F.coalesce("pull", vec_zero(step.dims)))
    away = _pushed(step, x)
    if away is not None:
        rows = rows.join(away, "sig", "left")  # as many rows as signatures: Spark broadcasts them if they are few
        moved = vec_sub(moved, F.coalesce("away", vec_zero(step.dims)))
    rows = rows.select("node_id", "den", moved.alias("moved"))
    if step.unit:
        return rows.select("node_id", vec_unit("moved").alias("vec"))
    if not step.stuck:
        return rows.select("node_id", vec_scale("moved", F.lit(1.0) / F.col("den")).alias("vec"))
    new = F.when(F.col("den") != 0, vec_scale("moved", F.lit(1.0) / F.nullif("den", F.lit(0.0))))
    return rows.join(x.select("node_id", F.col("vec").alias("old")), "node_id").select("node_id", F.coalesce(new, "old").alias("vec"))


def _moved(x: DataFrame, y: DataFrame) -> float:
    """Length of the change over length of the old vectors."""
    both = x.select("node_id", F.col("vec").alias("a")).join(y.select("node_id", F.col("vec").alias("b")), "node_id")
    square = lambda v: F.aggregate(v, F.lit(0.0), lambda s, e: s + e * e)
    d, o = both.agg(F.sum(square(vec_sub("a", "b"))), F.sum(square(F.col("a")))).first()
    return float(np.sqrt((d or 0.0) / o)) if o else 0.0


def _shuffle(step: Step, start: DataFrame, iters: int, tol: float, blocks: list[str] | None) -> Fit:
    stages = Stages(start.sparkSession, "sweeps")
    kept = lambda df: None if df is None else stages.keep(df)
    step = replace(step, nodes=kept(step.nodes), coefs=kept(step.coefs), push=kept(step.push), targets=kept(step.targets))
    if step.made is not None:
        step.made.clear()
    least, zeros = step.nodes.agg(F.min("den"), F.coalesce(F.sum((F.col("den") == 0).cast("int")), F.lit(0))).first()
    check_denominators(least, step.strict)
    step = replace(step, stuck=zeros > 0)
    x, out = stages.keep(start.select("node_id", "vec")), Fit(start, least_denominator=least)
    for k in range(iters):
        old, last = x, stages.made
        for block in blocks or [None]:
            new = sweep(step, x, block)
            x = stages.keep(new if block is None else x.join(new.select("node_id"), "node_id", "left_anti").unionByName(new))
        change = _moved(old, x) if tol or k == iters - 1 else None
        out.history.append({"sweep": k + 1, "rel_step": change})
        if k:
            stages.drop(last)
        if tol and change is not None and change < tol:
            break
    out.vectors = x
    return out


def _packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All links of a task, sorted by source, as three byte strings."""
    parts = [(b.column("src").to_numpy(), b.column("dst").to_numpy(), b.column("coef").to_numpy()) for b in batches]
    if not parts:
        return
    src, dst, coef = (np.concatenate(c) for c in zip(*parts))
    order = np.argsort(src, kind="stable")
    yield pa.RecordBatch.from_arrays([pa.array([v[order].astype(t).tobytes()], pa.binary()) for v, t in ((src, "<i8"), (dst, "<i8"), (coef, "<f8"))], names=["src", "dst", "coef"])


def _runs(s: np.ndarray, size: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """Of sorted numbers: where each run of equal ones starts, then the end; and the runs that start blocks of about `size`."""
    first = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])) if len(s) else np.zeros(0, dtype=np.int64)
    cuts = np.unique(np.append(np.searchsorted(first, np.arange(0, len(s), size)), len(first)))
    return np.append(first, len(s)), cuts


def _summed(runs: tuple[np.ndarray, np.ndarray], t: np.ndarray, c: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For each run the sum of c * v[t], in blocks that stay in the cache."""
    bounds, cuts = runs
    total = np.empty((len(bounds) - 1, v.shape[1]))
    for a, b in zip(cuts[:-1], cuts[1:]):
        low, high = bounds[a], bounds[b]
        part = v.take(t[low:high], axis=0)
        part *= c[low:high, None]
        np.add.reduceat(part, bounds[a:b] - low, axis=0, out=total[a:b])
    return total


def _broadcast(step: Step, start: DataFrame, iters: int, tol: float, blocks: list[str] | None) -> Fit:
    """Sweeps with the vectors on the driver and in every task; links stay in their tasks."""
    spark, d = start.sparkSession, step.dims
    first = start.select("node_id", F.col("vec").alias("first"))
    table = step.nodes.select("node_id", "category", "den", "sig", "const").join(first, "node_id", "left")
    table = table.withColumn("first", F.coalesce("first", vec_zero(d))).toArrow().sort_by("node_id")
    ids = table.column("node_id").to_numpy()
    place = {int(n): i for i, n in enumerate(ids)} if len(ids) and ids[-1] != len(ids) - 1 else None
    at = (lambda v: v) if place is None else (lambda v: np.array([place[int(n)] for n in v], dtype=np.int64))

    def rows_of(column: pa.ChunkedArray) -> np.ndarray:
        return np.array(column.combine_chunks().flatten().to_numpy(zero_copy_only=False), dtype=float).reshape(-1, d)

    const, den = rows_of(table.column("const")), table.column("den").to_numpy().astype(float)
    least = float(den.min()) if len(den) else None
    check_denominators(least, step.strict)
    x = rows_of(table.column("first"))
    sig = table.column("sig").to_pylist()
    push = None
    if step.push is not None:
        rules = step.push.toPandas()
        groups = {g: i for i, g in enumerate(sorted(set(zip(rules["rel"], rules["rel_inv"]))))}
        sigs = {s: i for i, s in enumerate(sorted(set(rules["sig"])))}
        push = np.zeros((len(sigs) + 1, len(groups)))
        for r in rules.itertuples():
            push[sigs[r.sig], groups[r.rel, r.rel_inv]] = r.coef
        mine = np.array([sigs.get(s, len(sigs)) for s in sig], dtype=np.int64)
        members = step.targets.toPandas().sort_values(["rel", "rel_inv"])
        target = at(members["dst"].to_numpy(np.int64))
        group = np.array([groups[g] for g in zip(members["rel"], members["rel_inv"])], dtype=np.int64)
        group_runs, ones = _runs(group), np.ones(len(group))
    links = Stages(spark, "links")
    packed = links.keep(step.coefs.repartition(max(1, spark.sparkContext.defaultParallelism), "src").mapInArrow(_packed, "src binary, dst binary, coef binary"))
    size = packed.agg(F.coalesce(F.sum(F.length("src")), F.lit(0))).first()[0] * 3
    rows = packed.collect() if size <= BROADCAST_BYTES else None  # small links stay beside the vectors
    local = [tuple(np.frombuffer(r[c], dtype=t) for c, t in (("src", "<i8"), ("dst", "<i8"), ("coef", "<f8"))) for r in rows] if rows is not None else None
    if local is not None:
        local = [(at(s)[_runs(s)[0][:-1]], _runs(s), at(t), c) for s, t, c in local if len(s)]

    def pulls(v: np.ndarray) -> np.ndarray:
        out = np.zeros_like(v)
        if local is not None:
            for where, runs, t, c in local:
                out[where] = _summed(runs, t, c, v)
            return out
        shared = spark.sparkContext.broadcast((v, place))

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            now, index = shared.value
            for b in batches:
                for r in b.to_pylist():
                    s, t, c = (np.frombuffer(r[n], dtype=k) for n, k in (("src", "<i8"), ("dst", "<i8"), ("coef", "<f8")))
                    runs = _runs(s)
                    where, total = s[runs[0][:-1]], _summed(runs, t if index is None else np.array([index[int(n)] for n in t]), c, now)
                    yield pa.RecordBatch.from_arrays([pa.array([where.astype("<i8").tobytes()]), pa.array([total.tobytes()])], names=["src", "pull"])

        for r in packed.mapInArrow(work, "src binary, pull binary").collect():
            out[at(np.frombuffer(r["src"], dtype="<i8"))] += np.frombuffer(r["pull"], dtype="<f8").reshape(-1, d)
        shared.unpersist()
        return out

    categories = np.array(table.column("category").to_pylist(), dtype=object)
    history = []
    for k in range(iters):
        old = x
        for block in blocks or [None]:
            moved = const + pulls(x)
            if push is not None:
                totals = np.zeros((push.shape[1], d))
                totals[group[group_runs[0][:-1]]] = _summed(group_runs, target, ones, x)
                moved -= (push @ totals)[mine]
            if step.unit:
                n = np.sqrt((moved * moved).sum(axis=1, keepdims=True))
                moved = np.divide(moved, n, out=np.zeros_like(moved), where=n > 0)
            else:
                moved = np.divide(moved, den[:, None], out=x.copy(), where=den[:, None] != 0)
            x = moved if block is None else np.where((categories == block)[:, None], moved, x)
        base = float((old * old).sum())
        history.append({"sweep": k + 1, "rel_step": float(np.sqrt(((x - old) ** 2).sum() / base)) if base else 0.0})
        if tol and history[-1]["rel_step"] < tol:
            break
    links.clear()
    if step.made is not None:
        step.made.clear()
    done = pa.table({"node_id": pa.array(ids), "vec": pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * d), pa.array(x.ravel()))})
    return Fit(spark.createDataFrame(done) if len(ids) else start.select("node_id", "vec"), history, least)


_PACKED = {"ids": "<i8", "den": "<f8", "rule": "<i4", "const": "<f8", "first": "<f8", "out_at": "<i4", "out_hub": "<i4", "out_coef": "<f8", "in_at": "<i4", "in_hub": "<i4", "in_coef": "<f8", "mem_at": "<i4", "mem_group": "<i4"}


def _vectors(column: pa.ChunkedArray, d: int) -> np.ndarray:
    return np.array(column.combine_chunks().flatten().to_numpy(zero_copy_only=False), dtype=float).reshape(-1, d)


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[dict[str, np.ndarray]]:
    for b in batches:
        columns = [(n, b.column(n)) for n in b.schema.names]
        for i in range(b.num_rows):
            yield {n: np.frombuffer(c[i].as_buffer(), dtype=_PACKED[n]) for n, c in columns}


def _chunk_moved(r: dict[str, np.ndarray], hub: np.ndarray, away: np.ndarray, unit: bool) -> np.ndarray:
    """A chunk's vectors after a sweep that found these vectors of the hubs and pushes of the rules."""
    x = r["const"].reshape(-1, hub.shape[1]).copy()
    if len(r["out_at"]):
        runs = _runs(r["out_at"])
        x[r["out_at"][runs[0][:-1]]] += _summed(runs, r["out_hub"], r["out_coef"], hub)
    x -= away[r["rule"]]
    if not unit:
        return x / r["den"][:, None]
    n = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, n, out=np.zeros_like(x), where=n > 0)


def _chunk_sums(r: dict[str, np.ndarray], x: np.ndarray, pull: np.ndarray, total: np.ndarray) -> None:
    """Adds what a chunk's vectors pull the hubs by, and their part in the totals of the groups."""
    if len(r["in_hub"]):
        runs = _runs(r["in_hub"])
        pull[r["in_hub"][runs[0][:-1]]] += _summed(runs, r["in_at"], r["in_coef"], x)
    if len(r["mem_group"]):
        runs = _runs(r["mem_group"])
        total[r["mem_group"][runs[0][:-1]]] += _summed(runs, r["mem_at"], np.ones(len(r["mem_at"])), x)


def _added(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows = [np.frombuffer(v.as_buffer(), dtype="<f8") for b in batches for v in b.column("sums")]
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array([np.sum(rows, axis=0).tobytes()], pa.binary())], names=["sums"])


def _hubs(step: Step, start: DataFrame, iters: int, tol: float, blocks: list[str] | None) -> Fit:
    """Sweeps with only the hubs' vectors on the driver; graphs that need more go to the joins.

    A node that is no hub is linked with hubs alone, so its next vector follows from theirs and the pushes. The tables
    of such nodes and their links are packed once; each sweep is one pass over them that returns sums for the hubs.
    """
    spark, d, stages = start.sparkSession, step.dims, Stages(start.sparkSession, "hubs")
    kept = lambda df: None if df is None else stages.keep(df)
    step = replace(step, nodes=kept(step.nodes), coefs=kept(step.coefs), push=kept(step.push), targets=kept(step.targets))
    if step.made is not None:
        step.made.clear()
        step = replace(step, made=None)
    joins = lambda: _shuffle(replace(step, made=stages), start, iters, tol, blocks)
    least, zeros = step.nodes.agg(F.min("den"), F.coalesce(F.sum((F.col("den") == 0).cast("int")), F.lit(0))).first()
    if blocks or zeros or not iters or (step.push is not None and step.push.count() > RULES):
        return joins()
    top = step.coefs.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= HUB_DEGREE).orderBy(F.desc("n"), "dst").limit(HUBS)
    hubs = sorted(r["dst"] for r in top.collect())

    def marked() -> tuple[DataFrame, Callable[[DataFrame, str, str], DataFrame]]:
        table = F.broadcast(spark.createDataFrame([(h, i) for i, h in enumerate(hubs)], "hub long, at int"))
        of = lambda df, node, at: df.join(table.select(F.col("hub").alias(node), F.col("at").alias(at)), node, "left")
        return of(of(step.coefs, "src", "_s"), "dst", "_d"), of

    loose = marked()[0].where("_s is null and _d is null").select(F.explode(F.array("src", "dst")).alias("node")).distinct().limit(HUBS + 1).collect()
    if len(hubs) + len(loose) > HUBS:
        return joins()
    hubs = sorted(hubs + [r["node"] for r in loose])  # with links among small columns, no link is left without a hub
    links, of = marked()
    if links.where("_s is not null and _d is not null").count() > HUB_LINKS:
        return joins()
    check_denominators(least, step.strict)

    rules = step.push.toPandas() if step.push is not None else None
    groups = {g: i for i, g in enumerate(sorted(set(zip(rules["rel"], rules["rel_inv"]))))} if rules is not None else {}
    sigs = {s: i for i, s in enumerate(sorted(set(rules["sig"])))} if rules is not None else {}
    push = np.zeros((len(sigs) + 1, len(groups)))
    for r in rules.itertuples() if rules is not None else ():
        push[sigs[r.sig], groups[r.rel, r.rel_inv]] = r.coef
    rule = lambda found: np.array([sigs.get(s, len(sigs)) for s in found], dtype=np.int32)

    first = start.select("node_id", F.col("vec").alias("first"))
    nodes = of(step.nodes.join(first, "node_id", "left").withColumn("first", F.coalesce("first", vec_zero(d))), "node_id", "_at")
    mine = nodes.where("_at is not null").select("_at", "den", "sig", "const", "first").toArrow().sort_by("_at")
    den, own_rule, const, hub = mine.column("den").to_numpy(), rule(mine.column("sig").to_pylist()), _vectors(mine.column("const"), d), _vectors(mine.column("first"), d)
    among = links.where("_s is not null and _d is not null").select("_s", "_d", "coef").toArrow().sort_by("_s")
    s, t, c = (among.column(n).to_numpy() for n in ("_s", "_d", "coef"))
    among_runs = _runs(s)
    chunk = lambda node: F.floor(F.col(node) / CHUNK).cast("long").alias("chunk")
    ends = [links.where("_s is null").select(chunk("src"), F.lit(0).alias("kind"), F.col("src").alias("node"), F.col("_d").alias("at"), "coef"), links.where("_d is null").select(chunk("dst"), F.lit(1).alias("kind"), F.col("dst").alias("node"), F.col("_s").alias("at"), "coef")]
    group, member = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    if groups:
        numbers = F.broadcast(spark.createDataFrame([(*g, i) for g, i in groups.items()], "rel string, rel_inv boolean, at int"))
        targets = of(step.targets.join(numbers, ["rel", "rel_inv"]), "dst", "_d")
        ends.append(targets.where("_d is null").select(chunk("dst"), F.lit(2).alias("kind"), F.col("dst").alias("node"), "at", F.lit(1.0).alias("coef")))
        held = targets.where("_d is not null").select("at", "_d").toArrow().sort_by("at")
        group, member = held.column("at").to_numpy(), held.column("_d").to_numpy()
    group_runs = _runs(group)

    def pack(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("node_id")
        ids, out = left.column("node_id").to_numpy(), {}
        if not len(ids):
            return pa.table({n: pa.array([], pa.binary()) for n in _PACKED})
        out |= {"ids": ids, "den": left.column("den").to_numpy(), "rule": rule(left.column("sig").to_pylist()), "const": _vectors(left.column("const"), d), "first": _vectors(left.column("first"), d)}
        kind, at, other, coef = right.column("kind").to_numpy(), np.searchsorted(ids, right.column("node").to_numpy()), right.column("at").to_numpy(), right.column("coef").to_numpy()
        for k, names, by in ((0, ("out_at", "out_hub", "out_coef"), at), (1, ("in_at", "in_hub", "in_coef"), other), (2, ("mem_at", "mem_group", None), other)):
            rows = np.flatnonzero(kind == k)
            rows = rows[np.argsort(by[rows], kind="stable")]
            out |= {n: v[rows] for n, v in zip(names, (at, other, coef)) if n}
        return pa.table({n: pa.array([np.ascontiguousarray(out[n]).astype(t).tobytes()], pa.binary()) for n, t in _PACKED.items()})

    left = nodes.where("_at is null").select(chunk("node_id"), "node_id", "den", "sig", "const", "first")
    right = reduce(DataFrame.unionByName, ends)
    packed = stages.keep(left.groupBy("chunk").cogroup(right.groupBy("chunk")).applyInArrow(pack, ", ".join(f"{n} binary" for n in _PACKED)), compression="uncompressed", maxRecordsPerFile=str(FILE_ROWS))
    n_hubs, n_groups, unit = len(hubs), len(groups), step.unit

    def told(*values):
        return spark.sparkContext.broadcast(values)

    def summed(now: tuple | None, before: tuple | None, look: bool) -> tuple[np.ndarray, np.ndarray, float, float]:
        """Sums of the vectors after a sweep, those at the start if there was none; with `look` also how far they moved."""
        shared = told(now, before)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums = np.zeros((n_hubs + n_groups) * d + 2)
            pull, total = sums[: n_hubs * d].reshape(-1, d), sums[n_hubs * d : -2].reshape(-1, d)
            now, before = shared.value
            for r in _unpacked(batches):
                x = r["first"].reshape(-1, d) if now is None else _chunk_moved(r, *now, unit)
                _chunk_sums(r, x, pull, total)
                if look:
                    old = r["first"].reshape(-1, d) if before is None else _chunk_moved(r, *before, unit)
                    sums[-2:] += ((x - old) ** 2).sum(), (old * old).sum()
            yield pa.RecordBatch.from_arrays([pa.array([sums.tobytes()], pa.binary())], names=["sums"])

        read = packed if now is None or (look and before is None) else packed.drop("first")
        parts = read.mapInArrow(work, "sums binary")
        if ((n_hubs + n_groups) * d + 2) * 8 * parts.rdd.getNumPartitions() > SUM_BYTES:
            parts = parts.repartition(8).mapInArrow(_added, "sums binary")
        sums = np.sum([np.frombuffer(r["sums"], dtype="<f8") for r in parts.collect()] or [np.zeros((n_hubs + n_groups) * d + 2)], axis=0)
        shared.unpersist()
        return sums[: n_hubs * d].reshape(-1, d), sums[n_hubs * d : -2].reshape(-1, d), float(sums[-2]), float(sums[-1])

    history, before, now = [], None, None
    pull, total, _, _ = summed(None, None, False)
    for k in range(iters):
        if n_hubs:
            total = total.copy()
            total[group[group_runs[0][:-1]]] += _summed(group_runs, member, np.ones(len(member)), hub)
            pull = pull.copy()
            pull[s[among_runs[0][:-1]]] += _summed(among_runs, t, c, hub)
        away = push @ total
        before, now = now, (hub, away)
        moved = const + pull - away[own_rule]
        n = np.sqrt((moved * moved).sum(axis=1, keepdims=True)) if unit else den[:, None]
        moved = np.divide(moved, n, out=np.zeros_like(moved), where=n != 0)
        change, last = None, k == iters - 1
        if tol or not last:
            pull, total, gap, base = summed(now, before, bool(tol))
        else:
            _, _, gap, base = summed(now, before, True)
        if tol or last:
            base += float((hub * hub).sum())
            change = float(np.sqrt((gap + float(((moved - hub) ** 2).sum())) / base)) if base else 0.0
        hub = moved
        history.append({"sweep": k + 1, "rel_step": change})
        if tol and change < tol:
            break
    shared = told(*now)

    def written(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for r in _unpacked(batches):
            x = _chunk_moved(r, *shared.value, unit)
            yield pa.RecordBatch.from_arrays([pa.array(r["ids"]), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * d), pa.array(x.ravel()))], names=["node_id", "vec"])

    done = packed.drop("first").mapInArrow(written, "node_id long, vec array<double>")
    if n_hubs:
        done = done.unionByName(spark.createDataFrame([(h, v) for h, v in zip(hubs, hub.tolist())], "node_id long, vec array<double>"))
    out = Stages(spark, "sweeps").keep(done)
    stages.clear()
    return Fit(out, history, least)



def run(step: Step, start: DataFrame, iters: int, kernel: str | None = None, tol: float = 0.0, blocks: list[str] | None = None) -> Fit:
    if kernel is None:
        kernel = "broadcast" if start.count() * step.dims * 8 <= BROADCAST_BYTES else "hubs"
    return {"broadcast": _broadcast, "hubs": _hubs, "shuffle": _shuffle}[kernel](step, start, iters, tol, blocks)


def fit_objective(p: Problem, params: Params = Params(), iters: int = 10, update: str = "jacobi", nonlinks: str = "shortcut", kernel: str | None = None, tol: float = 0.0, mc: str = "distinct", start: DataFrame | None = None) -> Fit:
    """Minimises the loss. 'jacobi' moves all nodes at once; 'block_seidel' one column after the other.

    `start` gives other first vectors, for warm starts. nonlinks='bruteforce' lists all non-links, for checks only.
    Weights that may make the loss not convex, and denominators that are not above 0, are errors in strict mode and
    warnings else; a node whose denominator is 0 keeps its vector.
    """
    made = Stages(p.base.sparkSession, "weights")
    w = objective_weights(p, params, mc, made)
    warn_if_unsafe(p.base, p.links, params, w if mc == "distinct" else None)
    step = replace(objective_step(p, params, mc, w, made), strict=params.strict)
    if nonlinks == "bruteforce":
        step = _listed(p, step, params, mc)
    blocks = sorted(r["category"] for r in p.base.select("category").distinct().collect()) if update == "block_seidel" else None
    return run(step, start or p.base, iters, kernel, tol, blocks)


def _listed(p: Problem, step: Step, params: Params, mc: str) -> Step:
    """The objective's step with every non-link as a negative coefficient and no group totals."""
    ends = p.links.select("rel", "rel_inv", "src").distinct().join(p.links.select("rel", "rel_inv", "dst").distinct(), ["rel", "rel_inv"])
    away = ends.join(p.links, ["rel", "rel_inv", "src", "dst"], "left_anti").join(group_repulsion(p.links, params, mc).select("rel", "rel_inv", "repel"), ["rel", "rel_inv"])
    w = derive_weights(p.links, params, "objective", mc=mc)
    back = w.select("rel", (~F.col("rel_inv")).alias("rel_inv"), F.col("src").alias("dst"), F.col("link_w").alias("back"))
    near = p.links.join(w.select("rel", "rel_inv", "src", "link_w"), ["rel", "rel_inv", "src"]).join(back, ["rel", "rel_inv", "dst"]).select("src", "dst", (F.col("link_w") + F.col("back")).alias("coef"))
    coefs = near.union(away.select("src", "dst", (-2 * F.col("repel")).alias("coef"))).groupBy("src", "dst").agg(F.sum("coef").alias("coef"))
    return replace(step, coefs=coefs, push=None, targets=None)


def fit_series(p: Problem, params: Params = Params(1, 0, 3, 1), iters: int = 10, repulsion: str = "centroid", totals: str = "shared", kernel: str | None = None, tol: float = 0.0, start: DataFrame | None = None) -> Fit:
    """The recursion of unit vectors. repulsion='outdegree' divides by the node's links; totals='per_node' works
    every node's total out by itself, for checks only."""
    step = series_step(p, params, repulsion)
    if totals == "per_node":
        w = derive_weights(p.links, params, "series", repulsion)
        each = w.select("rel", "rel_inv", "src", "rep_w").join(p.links.select("rel", "rel_inv", "dst").distinct(), ["rel", "rel_inv"]).select("src", "dst", (-F.col("rep_w")).alias("coef"))
        step = Step(step.nodes, step.coefs.union(each).groupBy("src", "dst").agg(F.sum("coef").alias("coef")), None, None, True, step.dims)
    return run(step, start or p.base, iters, kernel, tol)


def fit_graph_baseline(p: Problem, iters: int = 20, update: str = "simplified", kernel: str | None = None, category_edges: DataFrame | None = None) -> Fit:
    return run(graph_step(p, update, category_edges), p.base, iters, kernel)


def base_vectors(p: Problem) -> DataFrame:
    return p.base.select("node_id", "vec")


def objective_loss(p: Problem, x: DataFrame, params: Params, mc: str = "distinct") -> DataFrame:
    """One row: base_loss, column_loss, link_loss, nonlink_loss, total. Non-links enter by sums over whole groups."""
    square = lambda v: F.aggregate(v, F.lit(0.0), lambda s, e: s + e * e)
    k = relation_counts(p.links).withColumnRenamed("src", "node_id")
    own = p.base.select("node_id", "category", F.col("vec").alias("b")).join(x, "node_id").join(k, "node_id", "left").na.fill(0, ["k"]).join(F.broadcast(p.column_means()), "category")
    first = own.agg(F.coalesce(F.sum(params.base * square(vec_sub("vec", "b"))), F.lit(0.0)).alias("base_loss"), F.coalesce(F.sum(F.lit(float(params.column)) / (F.col("k") + 1) * square(vec_sub("vec", "centroid"))), F.lit(0.0)).alias("column_loss"))
    w = derive_weights(p.links, params, "objective", mc=mc)
    ends = p.links.join(w.select("rel", "rel_inv", "src", "link_w", "rep_w"), ["rel", "rel_inv", "src"]).join(x.select(F.col("node_id").alias("src"), F.col("vec").alias("a")), "src").join(x.select(F.col("node_id").alias("dst"), F.col("vec").alias("c")), "dst")
    gap = square(vec_sub("a", "c"))
    linked = ends.agg(F.coalesce(F.sum(F.col("link_w") * gap), F.lit(0.0)).alias("link_loss"), F.coalesce(F.sum(F.col("rep_w") * gap), F.lit(0.0)).alias("_inside"))

    def side(column: str, tag: str) -> DataFrame:
        members = p.links.select("rel", "rel_inv", F.col(column).alias("node_id")).distinct().join(x, "node_id")
        return members.groupBy("rel", "rel_inv").agg(F.count(F.lit(1)).alias(f"n{tag}"), F.sum(square(F.col("vec"))).alias(f"q{tag}"), vec_sum("vec", p.dims).alias(f"s{tag}"))

    whole = side("src", "a").join(side("dst", "b"), ["rel", "rel_inv"]).join(group_repulsion(p.links, params, mc).select("rel", "rel_inv", "repel"), ["rel", "rel_inv"])
    dot = F.aggregate(F.zip_with("sa", "sb", lambda u, v: u * v), F.lit(0.0), lambda s, e: s + e)
    apart = whole.agg(F.coalesce(F.sum(F.col("repel") * (F.col("nb") * F.col("qa") + F.col("na") * F.col("qb") - 2 * dot)), F.lit(0.0)).alias("_all"))
    rows = first.crossJoin(linked).crossJoin(apart)  # three single rows
    away = F.col("_all") - F.col("_inside")
    return rows.select("base_loss", "column_loss", "link_loss", away.alias("nonlink_loss"), (F.col("base_loss") + F.col("column_loss") + F.col("link_loss") - away).alias("total"))


def graph_loss(p: Problem, x: DataFrame) -> DataFrame:
    """One row: base_loss, neighbour_loss, total of the classic graph method."""
    square = lambda v: F.aggregate(v, F.lit(0.0), lambda s, e: s + e * e)
    pairs = p.links.select("src", "dst").where(F.col("src") != F.col("dst")).distinct()
    beta = pairs.groupBy("src").agg((F.lit(1.0) / F.count(F.lit(1))).alias("beta"))
    near = pairs.join(beta, "src").join(x.select(F.col("node_id").alias("src"), F.col("vec").alias("a")), "src").join(x.select(F.col("node_id").alias("dst"), F.col("vec").alias("c")), "dst")
    second = near.agg(F.coalesce(F.sum(F.col("beta") * square(vec_sub("a", "c"))), F.lit(0.0)).alias("neighbour_loss"))
    first = p.base.select("node_id", F.col("vec").alias("b")).join(x, "node_id").agg(F.coalesce(F.sum(square(vec_sub("vec", "b"))), F.lit(0.0)).alias("base_loss"))
    return first.crossJoin(second).select("base_loss", "neighbour_loss", (F.col("base_loss") + F.col("neighbour_loss")).alias("total"))
