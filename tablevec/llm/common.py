"""What the training-data operators share: inputs, Arrow batches and tables written between steps."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F



def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the given data set, read by Spark so that any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bucket(key: str, modulus: int) -> Column:
    """crc32 of the key as text, modulo; a null key counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def byte_words(text: bytes | None) -> list[bytes]:
    """The words `[^\\x20\\x09-\\x0D]+` of a text in UTF-8, with A to Z in lower case; bytes know ASCII only."""
    return text.lower().split() if text else []


def give_back() -> None:
    """Returns memory that this worker has freed to the system: idle workers stay alive between tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def map_arrow(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """mapInArrow whose workers give memory back after each task."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fn(batches)
        gc.collect()
        give_back()

    return df.mapInArrow(work, schema)


def record_batch(schema: pa.Schema, columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


def slices(batch: pa.RecordBatch, column: int, most: int) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts in one column have about `most` bytes, one row at least."""
    if not batch.num_rows:
        return
    lengths = np.nan_to_num(np.asarray(pc.binary_length(batch.column(column)).to_numpy(zero_copy_only=False), dtype="float64")).astype("int64")
    start, ends = 0, np.cumsum(lengths)
    while start < batch.num_rows:
        before = ends[start - 1] if start else 0
        end = max(start + 1, int(np.searchsorted(ends, before + most, side="right")))
        yield batch.slice(start, end - start)
        start = end


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, named by spark.checkpoint.dir.

    Where none is named, a local one of the driver's if it runs all tasks itself, as in tests; on a cluster an error,
    since each executor would write to its own disk.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    made = getattr(spark, "_own_shared_folder", None)
    if made is None:
        made = spark._own_shared_folder = tempfile.mkdtemp(prefix="tablevec-shared-")
    return made


class Scratch:
    """Tables written between the steps of an operator, which cuts their lineage and survives lost executors.

    Every table is Parquet in a folder of its own below the shared folder; `drop` deletes one that no later
    step reads, and `drop_since` all tables of scratches made since a mark, once what reads them is written.
    """

    _made: list[Scratch] = []

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root = spark, f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        self._made.append(self)

    @classmethod
    def mark(cls) -> int:
        return len(cls._made)

    @classmethod
    def drop_since(cls, mark: int) -> None:
        for scratch in cls._made[mark:]:
            scratch.drop("")
        del cls._made[mark:]

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        jvm, context = self.spark._jvm, self.spark.sparkContext
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}" if name else self.root)
            path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


def text_bytes(column: str = "text") -> Column:
    """A text as UTF-8 bytes; null stays null."""
    return F.col(column).cast("string").cast("binary").alias(column)


def filter_rows(docs: DataFrame, decide: Callable[[list[str | None]], object], most: int = 2 << 20) -> DataFrame:
    """The rows whose text gets a true verdict, with all their columns, where they lie; `decide` sees lists of texts."""
    at = docs.columns.index("text")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole, at, most):
                yield batch.filter(pa.array(np.asarray(decide(batch.column(at).to_pylist()), dtype=bool)))

    return map_arrow(docs, work, docs.schema)


def id_bitmap(ids: DataFrame, most_bits: int = 26) -> np.ndarray:
    """A bitmap of the hashes of the distinct column `id`, of a bounded size whatever the number of ids.

    Ids outside it are surely not among them; an exact join must follow for the others.
    """
    bits = 1 << min(most_bits, max(12, int(16 * ids.count()).bit_length()))
    slot = f"pmod(xxhash64(id), {bits})"
    words = ids.select(F.expr(f"{slot} >> 6").alias("w"), F.expr(f"shiftleft(1L, cast({slot} & 63 as int))").alias("bit")).groupBy("w").agg(F.bit_or("bit").alias("bits"))
    bitmap, got = np.zeros(bits >> 6, dtype=np.uint64), words.toPandas()
    bitmap[got["w"].to_numpy(np.int64)] = got["bits"].to_numpy(np.int64).view(np.uint64)
    return bitmap


def id_slot(column: str) -> Column:
    """The hash of an id that in_bitmap reads, below 2 ** 40."""
    return F.pmod(F.xxhash64(column), F.lit(1 << 40))


def in_bitmap(bitmap: np.ndarray, slots: np.ndarray) -> np.ndarray:
    at = slots % (64 * len(bitmap))
    return ((bitmap[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1)).astype(bool)


def fresh_name(taken: list[str], name: str) -> str:
    """A column name that is not among those taken, which Spark compares without case."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name += "_"
    return name


def without_ids(docs: DataFrame, key: str, ids: DataFrame) -> DataFrame:
    """The rows of `docs` whose key is not among the distinct ids (column `id`); null keys stay.

    Rows whose key is outside a bitmap of the ids stay where they lie; only the others are shuffled to be compared.
    Other columns may have any names; repeated rows stay repeated or go together.
    """
    shared, columns = docs.sparkSession.sparkContext.broadcast(id_bitmap(ids)), docs.columns
    gone = fresh_name(columns, "_gone")

    def part(want: bool) -> DataFrame:
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                slots = batch.column(batch.num_columns - 1)
                hit = in_bitmap(shared.value, slots.fill_null(0).to_numpy()) & ~slots.is_null().to_numpy(zero_copy_only=False)
                yield batch.select(range(batch.num_columns - 1)).filter(pa.array(hit == want))

        slot = F.when(F.col(f"`{key}`").isNotNull(), id_slot(f"`{key}`")).alias(fresh_name(columns, "_slot"))
        return docs.select(*(F.col(f"`{c}`") for c in columns), slot).mapInArrow(work, docs.schema)

    return part(False).union(part(True).join(ids.select(F.col("id").alias(gone)), F.col(f"`{key}`") == F.col(f"`{gone}`"), "left_anti"))
