"""Skip-gram with drawn negatives for more vertices than one process holds: vectors and pairs lie in blocks.

Vertices are dealt to blocks by number. A turn trains each block's vectors with one block of contexts, in as many tasks as
there are blocks, none of which meets another's vectors; after as many turns as blocks every pair of a round was seen once.
A task holds two blocks and the pairs between them, the driver nothing but the names of vertices without a number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tablevec.plans.stages import Stages

#: Most vertices of a block and least blocks (a turn has as many tasks), most vertices without a number, parts that walks
#: are dealt to.
BLOCK, BLOCKS, NAMES, PARTS = 160_000, 6, 10_000, 64
#: Pairs of a step, contexts drawn for it, their weight beside a pair, and the rate of a row's first step.
STEP, DRAWN, NEGATIVE, RATE = 1024, 32, 5.0, 0.1


def numbering(vertices: DataFrame) -> tuple[int, list[str]] | None:
    """How many vertices are the numbers 0, 1, 2, ... as text, and the names of all others; None if it is not so."""
    numeric = F.col("vertex").rlike(r"^(0|[1-9]\d{0,17})$")
    n, most = vertices.where(numeric).agg(F.countDistinct("vertex"), F.coalesce(F.max(F.col("vertex").cast("long")) + 1, F.lit(0))).first()
    names = [r["vertex"] for r in vertices.where(~numeric).select("vertex").distinct().limit(NAMES + 1).collect()]
    return (n, sorted(names)) if n == most and len(names) <= NAMES else None


def pairs_of(flat: np.ndarray, sizes: np.ndarray, window: int, rng: np.random.Generator) -> np.ndarray:
    """(center, context) of paths laid end to end; each center looks 1 to `window` places to both sides, drawn evenly."""
    owner, reach, out = np.repeat(np.arange(len(sizes)), sizes), rng.integers(1, window + 1, len(flat)), [np.zeros((0, 2), flat.dtype)]
    for k in range(1, min(window, len(flat) - 1) + 1):
        same = owner[:-k] == owner[k:]
        for center, context in ((slice(None, -k), slice(k, None)), (slice(k, None), slice(None, -k))):
            near = same & (reach[center] >= k)
            out.append(np.stack([flat[center][near], flat[context][near]], axis=1))
    return np.concatenate(out)


def _paired(batches: Iterator[pa.RecordBatch], n: int, names: list[str], blocks: int, window: int, seed: int) -> Iterator[pa.RecordBatch]:
    """Pairs of places in blocks, packed by the blocks of center and context."""
    part, known = TaskContext.get().partitionId(), pa.array(names, pa.string())
    for number, batch in enumerate(batches):
        paths = batch.column(0)
        text, sizes = paths.flatten(), pc.list_value_length(paths).to_numpy(zero_copy_only=False)
        at = pc.index_in(text, value_set=known)
        flat = pc.if_else(at.is_valid(), pc.add(at.cast(pa.int64()), n).cast(pa.string()), text).cast(pa.int64()).to_numpy()
        pairs = pairs_of(flat, sizes, window, np.random.default_rng([seed, part, number]))
        bucket = (pairs[:, 0] % blocks) * blocks + pairs[:, 1] % blocks
        order = np.argsort(bucket, kind="stable")
        pairs, ends = (pairs[order] // blocks).astype("<i4"), np.cumsum(np.bincount(bucket, minlength=blocks * blocks))
        for b, (low, high) in enumerate(zip(np.append(0, ends[:-1]), ends)):
            if high > low:
                row = [(b % blocks - b // blocks) % blocks], [b // blocks], [part], [number], [pairs[low:high].tobytes()]
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(row, (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary()))], names=["turn", "block", "part", "number", "pairs"])


def _moved(table: np.ndarray, at: np.ndarray, by: np.ndarray, rate: float) -> None:
    """Adds sums of gradients to rows, each at a rate that falls with the squares it has had (its last number)."""
    order = np.argsort(at, kind="stable")
    rows = at[order]
    first = np.flatnonzero(np.append(True, rows[1:] != rows[:-1]))
    total, rows = np.add.reduceat(by.take(order, axis=0), first, axis=0), rows[first]
    now = table.take(rows, axis=0)
    now[:, -1] += np.einsum("ij,ij->i", total, total) / total.shape[1]
    now[:, :-1] += total * (rate / np.sqrt(now[:, -1:] + 1e-12))
    table[rows] = now


def train(mine: np.ndarray, theirs: np.ndarray, pairs: np.ndarray, rng: np.random.Generator, rate: float = RATE) -> None:
    """One look at each pair. Half of the drawn contexts are contexts of the step, so frequent ones are drawn more."""
    pairs, kind = pairs[rng.permutation(len(pairs))], mine.dtype.type
    for low in range(0, len(pairs), STEP):
        c, o = pairs[low : low + STEP].T
        drawn = np.concatenate([rng.choice(o, DRAWN // 2), rng.integers(0, len(theirs), DRAWN - DRAWN // 2)])
        u, w, others = (t.take(at, axis=0)[:, :-1] for t, at in ((mine, c), (theirs, o), (theirs, drawn)))
        near = 1 / (1 + np.exp(np.clip(np.einsum("ij,ij->i", u, w), -30, 30)))[:, None]
        away = kind(-NEGATIVE / DRAWN) / (1 + np.exp(np.clip(-(u @ others.T), -30, 30)))
        _moved(mine, c, near * w + away @ others, rate)
        _moved(theirs, np.append(o, drawn), np.concatenate([near * u, away.T @ u]), rate)


def fit_skipgram(paths: DataFrame, n: int, names: list[str], window: int, dim: int, seed: int, rounds: int) -> DataFrame:
    """(node_id, vec) of the numbered vertices, from (walk_id, path) and what `numbering` gives."""
    spark, stages = paths.sparkSession, Stages(paths.sparkSession, "skipgram")
    total = n + len(names)
    blocks = max(BLOCKS, -(-total // BLOCK))
    dealt = paths.repartition(PARTS, "walk_id").sortWithinPartitions("walk_id").select("path")
    found = dealt.mapInArrow(lambda b: _paired(b, n, names, blocks, window, seed), "turn int, block int, part int, number int, pairs binary")
    found.write.partitionBy("turn").parquet(f"{stages.root}/pairs")
    pairs = spark.read.schema("block int, part int, number int, pairs binary, turn int").parquet(f"{stages.root}/pairs")

    def started(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column(0).to_pylist():
                side, block = divmod(k, blocks)
                table = np.zeros((len(range(block, total, blocks)), dim + 1), "<f4")
                if not side:  # contexts start at zero
                    table[:, :-1] = (np.random.default_rng([seed, block]).random((len(table), dim)) - 0.5) / dim
                yield pa.RecordBatch.from_arrays([pa.array([side], pa.int32()), pa.array([block], pa.int32()), pa.array([table.tobytes()], pa.binary())], names=["side", "block", "body"])

    shape = "side int, block int, body binary"
    now, last = stages.keep(spark.range(0, 2 * blocks, 1, 2 * blocks).mapInArrow(started, shape)), stages.made

    def trained(turn: int):
        def work(left: pa.Table, right: pa.Table) -> pa.Table:
            held = {r["side"]: (r["block"], np.frombuffer(r["body"], "<f4").reshape(-1, dim + 1).copy()) for r in right.to_pylist()}
            left = left.sort_by([("part", "ascending"), ("number", "ascending")])
            read = [np.frombuffer(v.as_buffer(), "<i4") for v in left.column("pairs")]
            if read:
                train(held[0][1], held[1][1], np.concatenate(read).reshape(-1, 2), np.random.default_rng([seed, turn, held[0][0]]))
            return pa.table({"side": pa.array(list(held), pa.int32()), "block": pa.array([b for b, _ in held.values()], pa.int32()), "body": pa.array([t.tobytes() for _, t in held.values()], pa.binary())})

        return work

    for turn in range(rounds * blocks):
        by = turn % blocks
        meet = F.when(F.col("side") == 0, F.col("block")).otherwise(F.pmod(F.col("block") - F.lit(by), F.lit(blocks))).alias("_meet")
        mine = pairs.where(F.col("turn") == by).select("block", "part", "number", "pairs").groupBy("block")
        now = stages.keep(mine.cogroup(now.select("side", "block", "body", meet).groupBy("_meet")).applyInArrow(trained(turn), shape), compression="uncompressed")
        stages.drop(last)
        last = stages.made

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, body in zip(batch.column(0).to_pylist(), batch.column(1)):
                table = np.frombuffer(body.as_buffer(), "<f4").reshape(-1, dim + 1)[:, :-1]
                ids = np.arange(len(table), dtype=np.int64) * blocks + block
                ids = ids[ids < n]
                for low in range(0, len(ids), 8192):
                    some = table[low : min(low + 8192, len(ids))].astype(float)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[low : low + 8192]), pa.ListArray.from_arrays(pa.array(np.arange(len(some) + 1, dtype=np.int32) * dim), pa.array(some.ravel()))], names=["node_id", "vec"])

    done = stages.keep(now.where("side = 0").select("block", "body").mapInArrow(read, "node_id long, vec array<double>"))
    stages.drop(last)
    stages._delete(f"{stages.root}/pairs")
    return done
