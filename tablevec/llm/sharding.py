"""Placement of rows on shards by a permutation-filled lookup table.

Every shard has a preference order over the slots of a table of prime size: an offset and a step, both hashed from
its name. The shards take turns, each claiming its next free preferred slot, until the table is full. So shards get
equal numbers of slots, give or take one turn, and when a shard leaves or joins few other slots change hands. A row's
slot is a hash of its key; the table has a fixed number of rows, whatever the input, and is broadcast.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import table

SLOTS = 65_537
MOST_SLOTS = 1 << 22
SHARDS = tuple(f"shard-{i:03d}" for i in range(128))


def _is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def lookup_table(shards: Sequence[str], slots: int = SLOTS) -> np.ndarray:
    """The index of the shard that owns each slot. The order of `shards` sets the order of the turns."""
    if not shards or len(set(shards)) != len(shards):
        raise ValueError("shards need names that differ")
    if not _is_prime(slots) or not len(shards) < slots <= MOST_SLOTS:
        raise ValueError(f"the number of slots must be a prime above the number of shards, {MOST_SLOTS} at most")
    digests = [hashlib.sha256(s.encode()).digest() for s in shards]
    offsets = [int.from_bytes(d[:8], "big") % slots for d in digests]
    steps = [int.from_bytes(d[8:16], "big") % (slots - 1) + 1 for d in digests]
    owner = np.full(slots, -1, dtype=np.int32)
    at, left = list(offsets), slots
    while True:
        for i, step in enumerate(steps):
            slot = at[i]
            while owner[slot] >= 0:
                slot = (slot + step) % slots
            owner[slot], at[i] = i, (slot + step) % slots
            left -= 1
            if not left:
                return owner


def place(df: DataFrame, key: str, shards: Sequence[str] = SHARDS, slots: int = SLOTS, slot_as: str = "slot", shard_as: str = "shard") -> DataFrame:
    """Adds each row's slot and shard, by the text of `key`; columns of these names are replaced.

    Equal keys share a shard, so a null key, which counts as empty text, is placed with all other nulls. Key by a
    column without hot values (doc_id, not source): then no shard gets more than its share. Nothing is shuffled.
    """
    spark, owner = df.sparkSession, lookup_table(shards, slots)
    names = spark.createDataFrame([(int(s), shards[o]) for s, o in enumerate(owner)], f"`{slot_as}` int, `{shard_as}` string")
    kept = [c for c in df.columns if c not in (slot_as, shard_as)]
    hashed = F.pmod(F.xxhash64(F.coalesce(F.col(f"`{key}`").cast("string"), F.lit(""))), F.lit(slots)).cast("int")
    return df.select(*(F.col(f"`{c}`") for c in kept), hashed.alias(slot_as)).join(F.broadcast(names), slot_as).select(*(F.col(f"`{c}`") for c in kept), slot_as, shard_as)


def write_shards(placed: DataFrame, path: str, shard: str = "shard") -> None:
    """Writes one folder of Parquet files for each shard; each task writes the rows it has, so nothing is gathered."""
    placed.write.partitionBy(shard).parquet(path)


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return place(table(spark, sf_dir, "documents").select("doc_id"), "doc_id")
