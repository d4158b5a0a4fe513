"""Exact top-k search by inner product with cover trees over queries and data.

Both sides are indexed by a cover tree: a node is a data point and a radius that covers all points below it, and its
children are points far from each other. For a pair of nodes, the product of the centres plus what the two radii can
add bounds every product between them; the pair is pruned if that is less than the worst k-th score of the queries
below the query node.

The top level of the tree over all data is a bounded set of pivots. Rows go to the cell of their nearest pivot, a cell
is dealt into blocks, and each block gets a tree of its own in one task. Queries are dealt by their own nearest pivot, so
that those of a part visit few cells. A query visits only the cells whose bound reaches the k-th score that it has among
a bounded sample, which is a lower bound of its true k-th score.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tablevec.llm.common import Scratch, map_arrow, record_batch, table

SCALE = 1024
PIVOTS, SAMPLE = 64, 4096
#: Rows in a block of data, and queries in a block of queries: what one task holds.
BLOCK, QUERY_BLOCK = 16_384, 4096
#: Pairs of a cell and a part of the queries that are broadcast, 8 bytes each; more are joined.
MOST_VISITS = 500_000
#: Points in a leaf of the tree over data, and over queries; children of a node at most.
LEAF, QUERY_LEAF, FANOUT = 512, 32, 64


def _distances(points: np.ndarray, center: np.ndarray) -> np.ndarray:
    d = points - center
    return np.sqrt(np.einsum("ij,ij->i", d, d))


def spread(points: np.ndarray, most: int, stop: float = 0.0) -> tuple[list[int], np.ndarray, np.ndarray]:
    """Points far from each other, at most so many, until all lie within `stop`: their indices, each point's nearest
    of them, and its distance. The first is the point nearest the mean; equal points never count twice."""
    first = int(_distances(points, points.mean(axis=0)).argmin())
    chosen, near = [first], _distances(points, points[first])
    owner = np.zeros(len(points), dtype=np.int64)
    while len(chosen) < most and near.max() > stop:
        new = int(near.argmax())
        d = _distances(points, points[new])
        closer = d < near
        owner[closer], near[closer] = len(chosen), d[closer]
        chosen.append(new)
    return chosen, owner, near


class CoverTree:
    """Nodes in arrays: centre, radius, range of points (in `order`) and range of children; leaves have no children."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        n = len(points)
        self.order = np.arange(n)
        center, radius, span, kids = [], [], [], []

        def add(start: int, end: int, c: int, r: float) -> None:
            center.append(c)
            radius.append(r)
            span.append((start, end))
            kids.append((0, 0))

        if n:
            first = int(_distances(points, points.mean(axis=0)).argmin())
            add(0, n, first, float(_distances(points, points[first]).max()))
        at = 0
        while at < len(center):
            start, end = span[at]
            if end - start > leaf and radius[at] > 0:
                mine = self.order[start:end].copy()
                chosen, owner, near = spread(points[mine], max(2, min(FANOUT, 16 * len(mine) // leaf)), radius[at] / 2)
                if len(chosen) > 1:
                    self.order[start:end] = mine[np.argsort(owner, kind="stable")]
                    sizes, low = np.bincount(owner, minlength=len(chosen)), start
                    reach = np.zeros(len(chosen))
                    np.maximum.at(reach, owner, near)
                    kids[at] = (len(center), len(center) + len(chosen))
                    for j, c in enumerate(chosen):
                        add(low, low + int(sizes[j]), int(mine[c]), float(reach[j]))
                        low += int(sizes[j])
            at += 1
        self.points = points[self.order]
        self.centers = points[center] if n else points[:0]
        self.radius, self.span, self.kids = np.array(radius), span, kids
        self.norms = np.sqrt(np.einsum("ij,ij->i", self.centers, self.centers))


class Best:
    """The k best of each query so far: higher score first, then smaller id."""

    def __init__(self, n: int, k: int):
        self.k, self.scores, self.ids = k, np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)

    def offer(self, query: int, scores: np.ndarray, ids: np.ndarray) -> None:
        s, i = np.concatenate([self.scores[query], scores]), np.concatenate([self.ids[query], ids])
        top = np.lexsort((i, -s))[: self.k]
        self.scores[query], self.ids[query] = s[top], i[top]


def dual_search(queries: np.ndarray, query_ids: np.ndarray, data: np.ndarray, data_ids: np.ndarray, k: int, least: np.ndarray | None = None) -> tuple[Best, int]:
    """The k best data points of each query, without those of its own id, and how many products were computed.

    `least` holds scores that the answers must reach; what is below may be missing.
    """
    best, work = Best(len(queries), k), 0
    if not len(queries) or not len(data):
        return best, work
    qt, dt = CoverTree(queries, QUERY_LEAF), CoverTree(data)
    floor = np.full(len(queries), -np.inf) if least is None else least.astype(float)
    ids = data_ids[dt.order]
    kid_bounds = dt.kids

    def bounds(q: int, nodes: np.ndarray) -> np.ndarray:
        b = dt.centers[nodes] @ qt.centers[q] + qt.radius[q] * dt.norms[nodes] + dt.radius[nodes] * (qt.norms[q] + qt.radius[q])
        return b + 1e-9 * (1 + np.abs(b))

    def worst(members: np.ndarray) -> float:
        return float(np.maximum(best.scores[members, -1], floor[members]).min())

    def finish(q: int, nodes: np.ndarray) -> None:
        nonlocal work
        members = qt.order[slice(*qt.span[q])]
        own, own_ids = queries[members], query_ids[members]
        heap = [(-b, int(n)) for b, n in zip(bounds(q, nodes), nodes)]
        heapq.heapify(heap)
        limit = worst(members)
        while heap:
            b, node = heapq.heappop(heap)
            if -b < limit:
                break
            low, high = kid_bounds[node]
            if high:
                under = np.arange(low, high)
                for x, n in zip(bounds(q, under), under):
                    if x >= limit:
                        heapq.heappush(heap, (-x, int(n)))
                continue
            start, end = dt.span[node]
            scores = own @ dt.points[start:end].T
            work += scores.size
            some = ids[start:end]
            good = (scores >= np.maximum(best.scores[members, -1], floor[members])[:, None]) & (own_ids[:, None] != some[None, :])
            for j in np.flatnonzero(good.any(axis=1)):
                best.offer(int(members[j]), scores[j, good[j]], some[good[j]])
            limit = worst(members)

    todo = [(0, np.array([0]))]
    while todo:
        q, nodes = todo.pop()
        members = qt.order[slice(*qt.span[q])]
        nodes = nodes[bounds(q, nodes) >= worst(members)]
        low, high = qt.kids[q]
        if not high:
            finish(q, nodes)
            continue
        opened = [np.arange(*kid_bounds[n]) if kid_bounds[n][1] else np.array([n]) for n in nodes]
        nodes = np.concatenate(opened) if opened else nodes
        todo += [(child, nodes) for child in range(low, high)]
    return best, work


def usable(vector: str) -> Column:
    """Whether a vector is there and has only finite components."""
    x = F.col(vector)
    return x.isNotNull() & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    """floor(SCALE * x) of all rows; shorter vectors end in zeros."""
    out = np.zeros((len(column), width))
    sizes = np.diff(column.offsets.to_numpy())
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    rows = np.repeat(np.arange(len(column)), sizes)
    out[rows, np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = np.floor(SCALE * flat)
    return out


def _celled(batches: Iterator[pa.RecordBatch], pivots: np.ndarray, width: int) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("vec_id", pa.int64()), ("cell", pa.int32()), ("far", pa.float64()), ("v", pa.binary())])
    for batch in batches:
        v = _matrix(batch.column(1), width)
        d = (v * v).sum(axis=1)[:, None] - 2 * v @ pivots.T + (pivots * pivots).sum(axis=1)[None, :]
        cell = d.argmin(axis=1)
        far = np.sqrt(np.maximum(d[np.arange(len(v)), cell], 0)) * (1 + 1e-9) + 1e-6
        yield record_batch(schema, [batch.column(0), cell.astype(np.int32), far, [r.tobytes() for r in v]])


def _routed(batches: Iterator[pa.RecordBatch], sample: np.ndarray, sample_ids: np.ndarray, pivots: np.ndarray, radius: np.ndarray, filled: np.ndarray, k: int) -> Iterator[pa.RecordBatch]:
    """Each query once for every filled cell that it has to visit."""
    schema = pa.schema([("query_id", pa.int64()), ("cell", pa.int32()), ("part", pa.int32()), ("least", pa.float64()), ("v", pa.binary())])
    for whole in batches:
        for start in range(0, whole.num_rows, 512):
            batch = whole.slice(start, 512)
            ids, packed, part = batch.column(0).to_numpy(), batch.column(1), batch.column(2)
            v = np.array([np.frombuffer(b, dtype="<f8") for b in packed.to_pylist()])
            s = np.where(ids[:, None] == sample_ids[None, :], -np.inf, v @ sample.T)
            s = np.concatenate([s, np.full((len(v), k), -np.inf)], axis=1)
            least = -np.partition(-s, k - 1, axis=1)[:, k - 1]
            bound = v @ pivots.T + np.sqrt((v * v).sum(axis=1))[:, None] * radius[None, :]
            q, cell = np.nonzero((bound >= least[:, None]) & filled[None, :])
            yield record_batch(schema, [ids[q], cell.astype(np.int32), part.take(pa.array(q)), least[q], packed.take(pa.array(q))])


def query_parts(sizes: dict[int, int], most: int) -> list[tuple[int, int, int]]:
    """(cell, first part, parts): cells of few queries share a part of at most `most`; larger cells have their own."""
    out, part, used = [], 0, 0
    for cell, n in sorted(sizes.items()):
        if used and used + n > most:
            part, used = part + 1, 0
        parts = -(-n // most)
        out.append((cell, part, parts))
        part, used = (part, used + n) if parts == 1 else (part + parts, 0)
    return out


def _searched(queries: pa.Table, data: pa.Table, k: int) -> pa.Table:
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])
    q_ids, d_ids = queries.column("query_id").to_numpy(), data.column("vec_id").to_numpy()
    unpack = lambda t: np.array([np.frombuffer(b, dtype="<f8") for b in t.column("v").to_pylist()])
    if not len(q_ids) or not len(d_ids):
        return schema.empty_table()
    best, _ = dual_search(unpack(queries), q_ids, unpack(data), d_ids, k, queries.column("least").to_numpy())
    row, column = np.nonzero(np.isfinite(best.scores))
    return pa.table([q_ids[row], best.ids[row, column], best.scores[row, column].astype(np.int64)], schema=schema)


def search(vectors: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """query_id, rank, vec_id, score: the k highest integer products of floor(1024 * x) for each query.

    Both take (vec_id, embedding). Candidates are all rows but those of the query's own vec_id; equal scores go by the
    smaller vec_id; fewer than k rows give fewer answers. Vectors that are null or hold null or non-finite components,
    and rows with a null vec_id, take no part. Shorter vectors count as ending in zeros. Queries that share a vec_id
    count once, with the smallest vector. Other columns are ignored.
    """
    spark: SparkSession = vectors.sparkSession
    good = lambda df: df.where(F.col("vec_id").isNotNull() & usable("embedding")).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    data, asked = good(vectors), good(queries).groupBy("vec_id").agg(F.min("embedding").alias("embedding"))
    n, width = data.agg(F.count(F.lit(1)), F.max(F.size("embedding"))).first()
    n_asked, wide = asked.agg(F.count(F.lit(1)), F.max(F.size("embedding"))).first()
    if not n or not n_asked:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    width, scale = max(width, wide), 1 << 30
    taken = data.where(F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(scale)) < min(scale, scale * SAMPLE // n)).limit(2 * SAMPLE).toPandas().sort_values("vec_id")
    if taken.empty:
        taken = data.limit(SAMPLE).toPandas()
    sample = np.zeros((len(taken), width))
    for i, v in enumerate(taken["embedding"]):
        sample[i, : len(v)] = np.floor(SCALE * np.asarray(v, dtype=np.float64))
    sample_ids = taken["vec_id"].to_numpy(np.int64)
    pivots = sample[spread(sample, PIVOTS)[0]]
    celled = lambda df: map_arrow(df, lambda b: _celled(b, pivots, width), "vec_id long, cell int, far double, v binary")
    placed = Scratch(spark, "search").keep(celled(data), "cells")
    radius, sizes = np.zeros(len(pivots)), np.zeros(len(pivots), dtype=np.int64)
    for r in placed.groupBy("cell").agg(F.max("far").alias("far"), F.count(F.lit(1)).alias("n")).collect():  # at most PIVOTS rows
        radius[r["cell"]], sizes[r["cell"]] = r["far"], r["n"]
    blocks = -(-sizes // BLOCK)
    queries_in = celled(asked).select("vec_id", "cell", "v")
    dealt_to = query_parts({r["cell"]: r["count"] for r in queries_in.groupBy("cell").count().collect()}, QUERY_BLOCK)  # at most PIVOTS rows
    parts = F.broadcast(spark.createDataFrame(dealt_to, "cell int, _first int, _parts int"))
    routed_in = queries_in.join(parts, "cell").select("vec_id", "v", (F.col("_first") + F.pmod(F.xxhash64("vec_id"), F.col("_parts"))).cast("int").alias("part"))
    routed = map_arrow(routed_in, lambda b: _routed(b, sample, sample_ids, pivots, radius, blocks > 0, k), "query_id long, cell int, part int, least double, v binary")
    per_cell = F.broadcast(spark.createDataFrame([(c, int(b)) for c, b in enumerate(blocks) if b], "cell int, _blocks int"))
    queries_out = routed.join(per_cell, "cell").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    visits = routed.select("cell", "part").distinct()  # a cell's rows go to the parts whose queries visit it, and to no other
    if len(blocks) * (dealt_to[-1][1] + dealt_to[-1][2]) <= MOST_VISITS:
        visits = F.broadcast(visits)
    dealt = placed.join(per_cell, "cell").select("vec_id", "cell", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.col("_blocks")).cast("int").alias("block"), "v").join(visits, "cell")
    keys = ["cell", "block", "part"]
    queries_out, dealt = (df.select(*(F.col(c).alias(c) for c in df.columns)) for df in (queries_out, dealt))  # names of their own
    found = queries_out.groupBy(*keys).cogroup(dealt.groupBy(*keys)).applyInArrow(lambda q, d: _searched(q, d, k), "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op2_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return search(vectors, vectors.where(F.col("vec_id") % 100 == 0), 10)


OP2_SQL = """
WITH v AS (
    SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS DOUBLE)) AS e FROM embeddings
    WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), pairs AS (
    SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.e, c.e) AS BIGINT) AS score
    FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 100 = 0
), ranked AS (
    SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM pairs
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 10
"""
