"""Benchmark passages inside documents, by q-gram filtering and banded alignment.

Case and runs of white space are folded. A passage of m characters that occurs with at most e edits shares at least
(m + 1 - q) - q * e of its q-grams with the text, all within m + e characters and on diagonals (text minus passage
position) that differ by at most e. So positions of benchmark q-grams are found first; windows that hold enough of
them are kept; in those, q-grams are counted for each passage in overlapping bands of diagonals; and each band that
meets the bound is aligned. No occurrence within the edit budget is lost.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import filter_rows, map_arrow, record_batch, slices, table

Q = 9
#: Edits allowed for each character of a passage, fewer where the bound would not be positive.
EDIT_SHARE = 0.09
#: Benchmark characters that are searched for at once; a larger benchmark takes several passes over the documents.
MOST_CHARACTERS = 8_000_000
_SLOTS = 1 << 21
_BASE = np.uint32(0x01000193)
_OUT = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("start", pa.int64()), ("end", pa.int64()), ("edits", pa.int32())])


@lru_cache(1)
def _folding() -> np.ndarray:
    """Each code point's lower case if that is one character, and a space for white space."""
    out = np.arange(0x110000, dtype=np.uint32)
    for c in range(0x110000):
        low = chr(c).lower()
        if len(low) == 1:
            out[c] = ord(low)
        if chr(c).isspace():
            out[c] = 32
    return out


def fold(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Folded code points, and the place of each in the text."""
    codes = _folding()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    space = codes == 32
    kept = np.flatnonzero(~(space[1:] & space[:-1])) + 1 if len(codes) else np.zeros(0, np.int64)
    at = np.concatenate([[0], kept]) if len(codes) else kept
    return codes[at], at


def grams(codes: np.ndarray, q: int = Q) -> np.ndarray:
    """Rolling hashes of all runs of q codes, by doubling."""
    if len(codes) < q:
        return np.zeros(0, np.uint32)
    power, run, size = _BASE, codes.astype(np.uint32), 1
    total, have = None, 0
    while True:
        if q & size:
            if total is None:
                total, have = run, size
            else:
                n = len(codes) - have - size + 1
                total = run[:n] * _pow(have) + total[size : size + n]
                have += size
        if 2 * size > q:
            break
        run = run[:-size] * power + run[size:]
        size *= 2
        power = _pow(size)
    return total[: len(codes) - q + 1]


def _pow(n: int) -> np.uint32:
    return np.uint32(pow(int(_BASE), n, 1 << 32))


def _slot(hashes: np.ndarray) -> np.ndarray:
    return (hashes * np.uint32(0x9E3779B1)) >> np.uint32(11)


def edit_budget(m: int) -> int:
    """The edits allowed in a passage: a share of its length, as long as the bound on shared q-grams is positive."""
    return max(0, min(int(EDIT_SHARE * m), (m - Q) // Q))


def shared_bound(m: int) -> int:
    return m + 1 - Q - Q * edit_budget(m)


def align(passage: np.ndarray, text: np.ndarray, most: int) -> tuple[int, int, int] | None:
    """The fewest edits that turn the passage into a part of the text: (edits, start, end); none if more than `most`.

    The band holds all diagonals from the text's start to what is left of it after the passage, and `most` more.
    """
    m, n = len(passage), len(text)
    low, high = -most, max(n - m, 0) + most
    width = high - low + 1
    diagonals = np.arange(low, high + 1)
    padded = np.full(m + width + 1, -1, dtype=np.int64)
    padded[most : most + n] = text[: len(padded) - most]
    unit = 1 << 32
    far = np.int64(m + n + 9) * unit
    origin = diagonals.astype(np.int64) - low
    value = np.where((diagonals >= 0) & (diagonals <= n), origin, far)
    slope = np.arange(width, dtype=np.int64) * unit
    for i in range(m):
        kept = value + np.where(padded[i : i + width] == passage[i], 0, unit)
        kept[:-1] = np.minimum(kept[:-1], value[1:] + unit)
        column = diagonals + i + 1
        kept[(column < 0) | (column > n)] = far
        value = np.minimum.accumulate(kept - slope) + slope
        value[(column < 0) | (column > n)] = far
        if value.min() >= (most + 1) * unit:
            return None
    best = int(value.min())
    edits, start = divmod(best, unit)
    end = int(diagonals[int(value.argmin())]) + m
    return (edits, start + low, end) if edits <= most else None


@dataclass(frozen=True)
class _Class:
    """Passages of like lengths: a window that holds any of them, and how many hits it has at least."""

    window: int
    least: int
    hashes: np.ndarray
    item: np.ndarray
    position: np.ndarray


class Index:
    def __init__(self, items: list[tuple[int, str]]):
        folded = [(k, fold(t.strip())[0]) for k, t in items if t and t.strip()]
        self.ids = [k for k, _ in folded]
        self.codes = [c for _, c in folded]
        self.budget = np.array([edit_budget(len(c)) for c in self.codes], dtype=np.int64)
        self.bound = np.array([shared_bound(len(c)) for c in self.codes], dtype=np.int64)
        self.short = [i for i, c in enumerate(self.codes) if len(c) < Q]
        self.flags = np.zeros(_SLOTS, dtype=np.uint16)
        self.classes: list[_Class] = []
        sizes: dict[int, list[int]] = {}
        for i, c in enumerate(self.codes):
            if len(c) >= Q:
                sizes.setdefault(min(15, int(2 * np.log2(len(c))) - 6), []).append(i)
        for mine in sizes.values():
            found = [grams(self.codes[i]) for i in mine]
            hashes = np.concatenate(found)
            item = np.repeat(mine, [len(g) for g in found])
            position = np.concatenate([np.arange(len(g)) for g in found])
            order = np.argsort(hashes, kind="stable")
            self.flags[_slot(hashes)] |= np.uint16(1 << len(self.classes))
            window = max(len(self.codes[i]) + int(self.budget[i]) for i in mine)
            self.classes.append(_Class(window, int(self.bound[mine].min()), hashes[order], item[order], position[order]))

    def find(self, texts: list[str | None]) -> list[list[tuple[int, int, int, int]]]:
        """For each text, (item_id, start, end, edits) of each passage in it: the best place, the first of equals."""
        parts = [fold(t or "") for t in texts]
        sizes = [len(c) + 1 for c, _ in parts]
        ends = np.cumsum(sizes)
        whole = np.zeros(int(ends[-1]) if sizes else 0, dtype=np.uint32)
        for (c, _), end in zip(parts, ends):
            whole[end - 1 - len(c) : end - 1] = c
        best: list[dict[int, tuple[int, int, int]]] = [{} for _ in texts]

        def offer(k: int, item: int, edits: int, start: int, end: int) -> None:
            if item not in best[k] or (edits, start) < best[k][item][:2]:
                best[k][item] = (edits, start, end)

        hashes = grams(whole)
        flags = self.flags[_slot(hashes)]
        hit = np.flatnonzero(flags)
        flags = flags[hit]
        for j, c in enumerate(self.classes):
            at = hit[(flags >> np.uint16(j)) & np.uint16(1) > 0]
            if len(at) < c.least:
                continue
            dense = np.flatnonzero(at[c.least - 1 :] - at[: len(at) - c.least + 1] <= c.window - Q)
            if not len(dense):
                continue
            edge = np.zeros(len(at) + 1, dtype=np.int64)
            np.add.at(edge, dense, 1)
            np.add.at(edge, dense + c.least, -1)
            at = at[np.cumsum(edge[:-1]) > 0]
            low, high = np.searchsorted(c.hashes, hashes[at], "left"), np.searchsorted(c.hashes, hashes[at], "right")
            many = high - low
            text_at = np.repeat(at, many)
            entry = np.repeat(low, many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
            item, diagonal = c.item[entry], text_at - c.position[entry]
            step = self.budget[item] + 1
            cell = diagonal // step
            shift = int(cell.min()) if len(cell) else 0
            span = int(cell.max()) - shift + 2 if len(cell) else 1
            keys, counts = np.unique(item.astype(np.int64) * span + (cell - shift), return_counts=True)
            follows = np.zeros(len(keys), dtype=np.int64)
            if len(keys) > 1:
                follows[:-1] = np.where(keys[1:] == keys[:-1] + 1, counts[1:], 0)
            before = np.zeros(len(keys), dtype=np.int64)
            before[1:] = np.where(keys[1:] == keys[:-1] + 1, counts[:-1], 0) if len(keys) > 1 else 0
            for key in keys[(counts + np.maximum(follows, before)) >= self.bound[keys // span]]:
                i, first = int(key // span), int(key % span) + shift
                self._verify(i, first * (int(self.budget[i]) + 1), parts, ends, whole, offer)
        for i in self.short:
            for k, (codes, _) in enumerate(parts):
                place = _exact(codes, self.codes[i])
                if place >= 0:
                    offer(k, i, 0, place, place + len(self.codes[i]))
        out = []
        for k, found in enumerate(best):
            place = parts[k][1]
            out.append([(self.ids[i], int(place[a]), int(place[b - 1]) + 1, e) for i, (e, a, b) in sorted(found.items())])
        return out

    def _verify(self, i: int, diagonal: int, parts: list, ends: np.ndarray, whole: np.ndarray, offer) -> None:
        """Aligns passage i on the diagonals of a cell, the cells beside it, and a budget more, inside one text."""
        e, codes = int(self.budget[i]), self.codes[i]
        low, high = diagonal - (e + 1) - e, diagonal + 2 * (e + 1) + e + len(codes)
        middle = diagonal + len(codes) // 2
        for k in {int(np.searchsorted(ends, min(max(p, 0), int(ends[-1]) - 1), side="right")) for p in (diagonal, middle, diagonal + len(codes) - 1)}:
            begin, end = int(ends[k]) - 1 - len(parts[k][0]), int(ends[k]) - 1
            a, b = max(low, begin), min(high, end)
            if b - a < len(codes) - e:
                continue
            part = whole[a:b]
            place = _exact(part, codes)
            got = (0, place, place + len(codes)) if place >= 0 else align(codes, part, e)
            if got and got[2] > got[1]:
                offer(k, i, got[0], got[1] + a - begin, got[2] + a - begin)


def _exact(codes: np.ndarray, passage: np.ndarray) -> int:
    """Where the passage first occurs, or -1."""
    raw, want, at = codes.tobytes(), passage.tobytes(), -1
    while True:
        at = raw.find(want, at + 1)
        if at < 0 or at % 4 == 0:
            return at // 4 if at >= 0 else -1


def _hits(batches: Iterator[pa.RecordBatch], index: Index) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, 1, 1 << 20):
            rows: list[list] = [[] for _ in _OUT]
            for doc_id, found in zip(batch.column(0).to_pylist(), index.find(batch.column(1).to_pylist())):
                for hit in found:
                    for column, value in zip(rows, (doc_id, *hit)):
                        column.append(value)
            yield record_batch(_OUT, rows)


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, start, end, edits for each passage of (item_id, text) in each row of (doc_id, text).

    Offsets are code points of the text. A passage counts once for each document row, at its best place. Null, empty
    and blank passages are in no text, and null or empty texts hold none. Repeated rows on either side repeat, and
    rows with a null id keep it. Other columns are ignored. The benchmark goes to every task in parts of about
    MOST_CHARACTERS; every part takes one pass over the documents, without a shuffle.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = None
    for shared in _parts(benchmark):

        def work(batches, shared=shared):
            return _hits(batches, Index(shared.value))

        found = map_arrow(own, work, "doc_id long, item_id long, start long, end long, edits int")
        out = found if out is None else out.unionByName(found)
    return out


def _parts(benchmark: DataFrame) -> list:
    """Broadcast parts of the benchmark's (item_id, text) pairs."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull())
    total = items.agg(F.coalesce(F.sum(F.char_length("text")), F.lit(0))).first()[0]
    passes = 1 + int(total) // MOST_CHARACTERS
    parts = (items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(passes)) == k).orderBy("item_id", "text") for k in range(passes))
    return [benchmark.sparkSession.sparkContext.broadcast([(r["item_id"], r["text"]) for r in p.collect()]) for p in parts]


def keep_uncontaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of (text, ...) whose text holds no benchmark passage, with all their columns, whatever their names.

    Null and empty texts hold none and stay; so do all rows if the benchmark is empty. Repeated rows are judged alike and
    stay repeated.
    """
    for shared in _parts(benchmark):
        made: list[Index] = []

        def decide(texts: list[str | None], shared=shared, made=made) -> list[bool]:
            if not made:
                made.append(Index(shared.value))
            return [not found for found in made[0].find(texts)]

        docs = filter_rows(docs, decide, 1 << 20)
    return docs


def op8_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
