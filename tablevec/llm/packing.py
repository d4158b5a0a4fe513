"""Best-fit packing of token sequences by large-item matching, planned on the histogram of lengths.

How full the sequences get depends on the lengths alone, and lengths run from 1 to the capacity. So documents are
tokenized and cut where their rows lie, only the count of each length goes to the driver (at most `capacity` rows,
whatever the input), the plan is made there for runs of equal sequences at once, and each piece finds its place from
its rank among the pieces of its length.
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator
from functools import partial

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from tablevec.llm.common import Scratch, map_arrow, record_batch, slices, table
from tablevec.llm.subwords import coder

CAPACITY, END_ID = 4096, 1
#: Pieces of one length that are ranked by one task.
RANKED_TOGETHER = 200_000
_PIECES = pa.schema([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64())])


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _cut(batches: Iterator[pa.RecordBatch], tokenizer: str, capacity: int, with_ids: bool) -> Iterator[pa.RecordBatch]:
    code, end = coder(tokenizer), np.array([END_ID], dtype="<u4").tobytes()
    schema = _PIECES.append(pa.field("ids", pa.binary())) if with_ids else _PIECES
    for whole in batches:
        for batch in slices(whole, 1, 16 << 20):
            rows: list[list] = [[] for _ in schema]
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = code.ids(text or "") + end
                for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    values = [doc_id, piece, at // 4, len(part) // 4, zlib.crc32(part)]
                    for column, value in zip(rows, [*values, part]):
                        column.append(value)
            yield record_batch(schema, rows)


def cut_documents(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """The pieces of all documents: doc_id, piece, start, length, ids_crc32 and, if wanted, the ids as bytes.

    A document is its ids and an end id; a null or empty text is the end id alone. Only documents longer than the
    capacity are cut, into full pieces and a rest. Rows with a null doc_id and repeated rows are packed like others.
    """
    kind = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids
    work = partial(_cut, tokenizer=tokenizer or default_tokenizer(), capacity=capacity, with_ids=with_ids)
    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), work, kind)


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, list[tuple[int, int]]]]:
    """Sequences as (how many alike, [(length, how many of it in each)]) for the counts of the lengths.

    Pieces above a third of the capacity go first, at most two to a sequence: the longest left is matched with the
    longest that fits beside it. The others, longest first, go to the sequence with the least gap that still holds
    them. Runs of alike sequences are handled at once, so the work follows the number of lengths, not of pieces.
    """
    left = {n: c for n, c in counts.items() if c > 0}
    if any(n < 1 or n > capacity for n in left):
        raise ValueError("lengths must lie between 1 and the capacity")
    large = sorted(n for n in left if 3 * n > capacity)
    bins: dict[int, list[list]] = {}  # by gap: [how many alike, contents]
    gaps: list[int] = []

    def put(gap: int, many: int, contents: list[tuple[int, int]]) -> None:
        if gap not in bins:
            bins[gap] = []
            bisect.insort(gaps, gap)
        bins[gap].append([many, contents])

    while large:
        first = large[-1]
        fits = bisect.bisect_right(large, capacity - first) - 1
        if fits < 0:
            put(capacity - first, left.pop(large.pop()), [(first, 1)])
            continue
        second = large[fits]
        many = left[first] // 2 if first == second else min(left[first], left[second])
        if first == second and many == 0:  # a single one is left of this length; try the next shorter partner
            if fits == 0:
                put(capacity - first, left.pop(large.pop()), [(first, 1)])
                continue
            second, many = large[fits - 1], 1
        put(capacity - first - second, many, [(first, 2)] if first == second else [(first, 1), (second, 1)])
        for n in (first, second):
            left[n] -= many
        for n in {first, second}:
            if not left[n]:
                del left[n]
                large.remove(n)
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        todo = left[n]
        while todo:
            at = bisect.bisect_left(gaps, n)
            if at == len(gaps):
                each = capacity // n
                full, rest = divmod(todo, each)
                if full:
                    put(capacity - each * n, full, [(n, each)])
                if rest:
                    put(capacity - rest * n, 1, [(n, rest)])
                break
            gap = gaps[at]
            many, contents = bins[gap].pop()
            if not bins[gap]:
                del bins[gap]
                gaps.pop(at)
            each = min(gap // n, todo)
            filled = min(many, todo // each)
            put(gap - each * n, filled, [*contents, (n, each)])
            if many > filled:
                put(gap, many - filled, contents)
            todo -= filled * each
    return [(many, contents) for gap in gaps for many, contents in bins[gap]]


def place_table(plan: list[tuple[int, list[tuple[int, int]]]]) -> pd.DataFrame:
    """For each run of ranks of a length: first rank, how many in each sequence, first sequence, offset in it."""
    rows, used, sequence = [], {}, 0
    for many, contents in plan:
        offset = 0
        for length, each in contents:
            rank = used.get(length, 0)
            rows.append((length, rank, each, sequence, offset))
            used[length] = rank + many * each
            offset += length * each
        sequence += many
    return pd.DataFrame(rows, columns=["length", "rank", "each", "sequence", "offset"]).sort_values(["length", "rank"])


def _place(batches: Iterator[pa.RecordBatch], places: dict[str, np.ndarray], n_cols: int) -> Iterator[pa.RecordBatch]:
    keys = places["length"] * (1 << 40) + places["rank"]
    for batch in batches:
        length, rank = batch.column("length").to_numpy(), batch.column("_rank").to_numpy()
        at = np.searchsorted(keys, length * (1 << 40) + rank, side="right") - 1
        turn = rank - places["rank"][at]
        each = places["each"][at]
        columns = [batch.column(i) for i in range(n_cols)]
        fields = [batch.schema.field(i) for i in range(n_cols)]
        columns += [pa.array(places["sequence"][at] + turn // each, pa.int64()), pa.array(places["offset"][at] + turn % each * length, pa.int64())]
        yield pa.RecordBatch.from_arrays(columns, schema=pa.schema([*fields, pa.field("sequence_id", pa.int64()), pa.field("offset", pa.int64())]))


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds sequence_id and offset to pieces (doc_id, piece, length, ...), which must be a table that reads alike twice.

    Ranks within a length are counted in salted parts of about RANKED_TOGETHER pieces, so a length that a third of
    all pieces share is dealt over many tasks. Repeated (doc_id, piece) rows each get a place of their own.
    """
    spark = pieces.sparkSession
    histogram = pieces.groupBy("length").count()
    counts = {r["length"]: r["count"] for r in histogram.collect()}  # at most `capacity` rows
    places = place_table(plan_bins(counts, capacity))
    schema = T.StructType([*pieces.schema.fields, T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    if not counts:
        return spark.createDataFrame([], schema)
    parts = spark.createDataFrame([(n, 1 + c // RANKED_TOGETHER) for n, c in counts.items()], "length long, _parts long")
    salted = pieces.join(F.broadcast(parts), "length").withColumn("_salt", F.pmod(F.xxhash64("doc_id", "piece"), F.col("_parts")))
    before = Window.partitionBy("length").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = salted.groupBy("length", "_salt").agg(F.count(F.lit(1)).alias("_n")).select("length", "_salt", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_first"))
    if sum(1 + c // RANKED_TOGETHER for c in counts.values()) <= 200_000:
        starts = F.broadcast(starts)
    order = Window.partitionBy("length", "_salt").orderBy("doc_id", "piece")
    ranked = salted.join(starts, ["length", "_salt"]).withColumn("_rank", F.row_number().over(order) - 1 + F.col("_first"))
    kept = [f.name for f in pieces.schema.fields]
    arrays = {c: places[c].to_numpy("int64") for c in places.columns}
    return ranked.select(*kept, F.col("_rank").cast("long").alias("_rank")).mapInArrow(partial(_place, places=arrays, n_cols=len(kept)), schema)


def pack_documents(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Packs documents (doc_id, text; other columns are ignored) into sequences of at most `capacity` tokens."""
    spark: SparkSession = docs.sparkSession
    pieces = Scratch(spark, "packing").keep(cut_documents(docs, tokenizer, capacity, with_ids), "pieces")
    return pack(pieces, capacity)


def sequences(packed: DataFrame) -> DataFrame:
    """The filled sequences: sequence_id, ids as bytes and how many tokens; `packed` must hold the ids.

    A sequence holds at most `capacity` pieces, so no group is unbounded.
    """
    inside = F.array_sort(F.collect_list(F.struct("offset", "ids", "length")))
    got = packed.groupBy("sequence_id").agg(inside.alias("_in"))
    return got.select("sequence_id", F.expr("aggregate(_in, cast('' as binary), (a, x) -> concat(a, x.ids))").alias("ids"), F.expr("aggregate(_in, 0L, (a, x) -> a + x.length)").alias("n_tokens"))


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents")).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
