"""Near-duplicate documents by a MinHash forest, with links confirmed on full shingle sets.

1. Each text becomes its set of shingle hashes, a fingerprint of the set, minimum hashes, and a sketch of their lowest
   bits. Texts with equal sets are one class, whose representative is the smallest doc_id.
2. The forest has TREES orders of the signature; tree t starts at another place and goes on through the next values.
   Representatives are sorted in each order. Those that share the first DEPTH values are a region, whatever its size.
   A region that a sample of all texts shows to be of more than some REGION rows is dealt into parts by hash. In a
   part, the neighbours of longest common prefix are compared first, by size and sketch, which drops pairs far below the
   threshold: a row is paired with the leaders of its prefix that it may be near to, or becomes a leader itself and
   goes up to the next shorter prefix that other rows share. So a part is as deep as its rows are alike.
3. Pairs are confirmed on full sets, which are made again from the texts of the documents concerned alone.
4. Links are contracted to components. Pairs of a region inside one component need no more work. For any other pair
   that may be near, the row of the smaller component is compared with all of the larger one, which no more gathers
   pairs than rows; so no link between components of a region, or of its parts, is left out. The rows of a region's
   largest component are dealt into blocks, and so are its other rows: each two blocks of which one holds other rows
   meet in a task. Rows that ask a large component, and its rows, are dealt into blocks of bounded bytes likewise.

A pair of similarity 0.8 shares a region with probability 1 - (1 - 0.8 ** 4) ** 24, all but three in a million.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import Scratch, byte_words, fresh_name, id_bitmap, id_slot, in_bitmap, map_arrow, record_batch, slices, table, text_bytes, without_ids
from tablevec.llm.components import components

TREES, DEPTH = 24, 4
SIGNATURE = TREES * DEPTH
MINHASHES = 2 * SIGNATURE
#: Rows of a region that are compared at once, about; larger ones are dealt into parts and blocks of so many.
REGION = 8192
#: Of a region of REGION rows, about so many are in the sample that shows its size, and so many are enough to deal it.
SEEN, ENOUGH = 64, 16
#: How many of the MINHASHES must agree in their two lowest bits: five standard deviations below what 0.8 gives.
LEAST_ALIKE = 138
#: Components of up to so many rows are compared as pairs; bytes of full sets on either side that a task compares at once.
SMALL_COMPONENT, TOGETHER = 16, 16 << 20
#: Regions that are broadcast to their rows, some 24 bytes each; more are joined.
MOST_SENT = 200_000
_RNG = np.random.default_rng(20)
_XOR = _RNG.integers(0, 1 << 63, MINHASHES, dtype=np.uint64)
_ODD = _RNG.integers(0, 1 << 63, MINHASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0xFF51AFD7ED558CCD))
_MOST_WORDS = 150_000


@dataclass(frozen=True)
class Rule:
    """Shingles of so many words; sets are linked if 100 * intersection >= percent * union."""

    words: int = 5
    percent: int = 80


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        self[word] = out = xxhash.xxh3_64_intdigest(word)
        return out


def shingle_set(hashes: np.ndarray, words: int) -> np.ndarray:
    """Sorted distinct hashes of all runs of `words` words; of the whole text if it has fewer; none for no words."""
    n = len(hashes)
    if not n:
        return hashes
    width = min(words, n)
    out = hashes[: n - width + 1] * _MIX[0]
    for j in range(1, width):
        out = (out ^ (out >> np.uint64(29))) * _MIX[1] + hashes[j : n - width + 1 + j]
    if n < words:
        out = out + np.uint64(width)
    out = (out ^ (out >> np.uint64(32))) * _MIX[2]
    return np.unique(out ^ (out >> np.uint64(31)))


class Shingler:
    def __init__(self, words: int):
        self.words, self.known = words, WordHashes()

    def __call__(self, text: bytes | None) -> np.ndarray:
        found = byte_words(text)
        if len(self.known) > _MOST_WORDS:
            self.known.clear()
        return shingle_set(np.fromiter(map(self.known.__getitem__, found), np.uint64, len(found)), self.words)


def min_hashes(sets: list[np.ndarray]) -> np.ndarray:
    """Sets x MINHASHES minimum hashes, 32 bits; no set may be empty."""
    out = np.empty((len(sets), MINHASHES), dtype=np.uint32)
    start = 0
    while start < len(sets):
        end, size = start, 0
        while end < len(sets) and (end == start or size + len(sets[end]) <= 100_000):
            size += len(sets[end])
            end += 1
        flat = np.concatenate(sets[start:end])
        begins = np.concatenate([[0], np.cumsum([len(s) for s in sets[start : end - 1]])]).astype(np.int64)
        for k in range(MINHASHES):
            out[start:end, k] = np.minimum.reduceat((flat ^ _XOR[k]) * _ODD[k], begins) >> np.uint64(32)
        start = end
    return out


_SKETCH = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("print_a", pa.int64()), ("print_b", pa.int64()), ("signature", pa.binary()), ("bits", pa.binary())])


def low_bits(hashes: np.ndarray) -> np.ndarray:
    """The two lowest bits of each hash, four to a byte."""
    two = (hashes & 3).astype(np.uint8)
    return two[:, 0::4] | two[:, 1::4] << 2 | two[:, 2::4] << 4 | two[:, 3::4] << 6


def _sketched(batches: Iterator[pa.RecordBatch], words: int) -> Iterator[pa.RecordBatch]:
    import xxhash

    shingler = Shingler(words)
    for whole in batches:
        for batch in slices(whole, 1, 2 << 20):
            sets = [shingler(t) for t in batch.column(1).to_pylist()]
            full = [i for i, s in enumerate(sets) if len(s)]
            signatures: list[bytes | None] = [None] * len(sets)
            bits: list[bytes | None] = [None] * len(sets)
            if full:
                hashes = min_hashes([sets[i] for i in full])
                for i, row, low in zip(full, hashes[:, :SIGNATURE].astype("<u4"), low_bits(hashes)):
                    signatures[i], bits[i] = row.tobytes(), low.tobytes()
            prints = np.array([np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), dtype="<i8") for s in sets]).reshape(-1, 2)
            yield record_batch(_SKETCH, [batch.column(0), [len(s) for s in sets], prints[:, 0], prints[:, 1], signatures, bits])


_BRANCH = pa.schema([("tree", pa.int32()), ("key", pa.int64()), ("deeper", pa.int64()), ("rep", pa.int64()), ("n", pa.int32()), ("bits", pa.binary())])
_BRANCH_KIND = "tree int, key long, deeper long, rep long, n int, bits binary"


def _large_regions(linkable: DataFrame) -> DataFrame:
    """(tree, key, parts) of regions of more than some REGION rows, by a sample of the different texts.

    It only says which regions are dealt into how many parts; a region found or not, all its pairs are compared.
    """
    scale = 1 << 30
    drawn = F.pmod(F.xxhash64("print_a", "print_b"), F.lit(scale)) < min(scale, scale * SEEN // REGION)
    few = linkable.where(drawn).dropDuplicates(["print_a", "print_b"]).select(F.col("doc_id").alias("rep"), F.col("n_shingles").cast("int").alias("n"), "signature", "bits")
    seen = map_arrow(few, _branches, _BRANCH_KIND).groupBy("tree", "key").agg(F.count(F.lit(1)).alias("n"))
    return seen.where(F.col("n") >= ENOUGH).select("tree", "key", (1 + F.floor(F.col("n") / min(SEEN, REGION))).cast("int").alias("parts")).where("parts > 1")


def _branches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each representative once for every tree: its prefix, what follows in the order, and its sketch."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sig = np.array([np.frombuffer(s, dtype="<u4") for s in batch.column(2).to_pylist()])
        for t in range(TREES):
            order = (np.arange(2 * DEPTH) + t * DEPTH) % SIGNATURE
            key = np.zeros(len(sig), dtype=np.uint64)
            for j in order[:DEPTH]:
                key = (key ^ (key >> np.uint64(29))) * _MIX[1] + sig[:, j]
            deeper = np.zeros(len(sig), dtype=np.uint64)
            for j in order[DEPTH:]:
                deeper = (deeper << np.uint64(16)) | (sig[:, j] & 0xFFFF)
            key = (key ^ (key >> np.uint64(32))) * _MIX[2]
            yield record_batch(_BRANCH, [np.full(len(sig), t, np.int32), key.view(np.int64), deeper.view(np.int64), batch.column(0), batch.column(1), batch.column(3)])


def _columns(t: pa.Table) -> dict[str, np.ndarray]:
    """Columns as arrays; sketches as rows of unsigned 64-bit numbers."""
    return {c: np.frombuffer(b"".join(t.column(c).to_pylist()), dtype="<u8").reshape(t.num_rows, -1) if c == "bits" else t.column(c).to_numpy() for c in t.column_names}


def _regions(batches: Iterator[pa.RecordBatch], by: list[str]) -> Iterator[dict[str, np.ndarray]]:
    """Runs of rows with equal `by` columns, from batches sorted by them; runs of one row are left out."""
    rest: list[pa.RecordBatch] = []

    def runs(t: pa.Table, whole: bool) -> Iterator[dict[str, np.ndarray]]:
        nonlocal rest
        keys = [t.column(c).to_numpy() for c in by]
        cuts = np.flatnonzero(np.any([k[1:] != k[:-1] for k in keys], axis=0)) + 1
        ends = np.append(cuts, t.num_rows) if whole else cuts
        last = int(ends[-1]) if len(ends) else 0
        starts = np.concatenate([[0], ends[:-1]]).astype(np.int64) if len(ends) else ends
        rest = [b for b in t.slice(last).to_batches() if b.num_rows]
        if (ends - starts > 1).any():
            columns = _columns(t.slice(0, last))
            for a, b in zip(starts, ends):
                if b - a > 1:
                    yield {c: v[a:b] for c, v in columns.items()}

    for batch in batches:
        if batch.num_rows:
            same = rest and all(batch.column(c)[batch.num_rows - 1] == rest[0].column(c)[0] for c in by)
            rest.append(batch)
            if not same:  # else the run goes on beyond this batch
                yield from runs(pa.Table.from_batches(rest), False)
    if rest:
        yield from runs(pa.Table.from_batches(rest), True)


def _alike(n: int, bits: np.ndarray, ns: np.ndarray, others: np.ndarray, percent: int) -> np.ndarray:
    """Which of the other rows may be near to a row, by size and sketch."""
    n, ns = int(n), ns.astype(np.int64)
    fit = 100 * np.minimum(n, ns) >= percent * np.maximum(n, ns)
    differ = others ^ bits
    differ = (differ | differ >> np.uint64(1)) & np.uint64(0x5555555555555555)
    return fit & (np.bitwise_count(differ).sum(axis=1, dtype=np.int64) <= MINHASHES - LEAST_ALIKE)


def _near(r: dict[str, np.ndarray], i: int, others: np.ndarray, percent: int) -> np.ndarray:
    """Which of the other rows may be near to row i."""
    return _alike(r["n"][i], r["bits"][i], r["n"][others], r["bits"][others], percent)


def _ascended(r: dict[str, np.ndarray], percent: int) -> tuple[list[tuple[int, np.ndarray]], np.ndarray]:
    """Leaders with the later rows that may be near to them, and which rows may be near to any, of rows sorted by id.

    Runs of rows that share the longest prefix come first; of each run the rows that follow no leader go up to the
    next shorter prefix that neighbours in the order share, at last to that of all rows. What is near to nothing by
    then is compared with all rows, so of any two rows that may be near both are marked.
    """
    g, found = len(r["rep"]), []
    alive, marked = np.arange(g), np.zeros(g, bool)

    def lead(run: np.ndarray) -> np.ndarray:
        free = np.ones(len(run), bool)
        for k, i in enumerate(run):
            if free[k] and k + 1 < len(run):
                near = np.flatnonzero(_near(r, i, run[k + 1 :], percent)) + k + 1
                if len(near):
                    free[near], marked[i], marked[run[near]] = False, True, True
                    found.append((int(i), run[near]))
        return run[free]

    if g > 2:
        deeper = r["deeper"].view(np.uint64)
        order = np.argsort(deeper, kind="stable")
        differ = deeper[order][1:] ^ deeper[order][:-1]
        shared = np.sum([differ < np.uint64(1 << 16 * k) for k in range(DEPTH)], axis=0)  # values beyond the region's own
        for depth in sorted(set(shared[shared > 0].tolist()), reverse=True):
            run = np.empty(g, np.int64)
            run[order] = np.concatenate([[0], np.cumsum(shared < depth)])
            alive = alive[np.argsort(run[alive], kind="stable")]
            cuts = np.flatnonzero(np.diff(run[alive])) + 1
            alive = np.sort(np.concatenate([lead(part) for part in np.split(alive, cuts)]))
    alive = lead(alive)
    for i in alive[~marked[alive]]:
        marked[i] = _near(r, i, np.arange(g), percent).sum() > 1  # it is near to itself
    return found, marked


_CANDIDATE = pa.schema([("region", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("n", pa.int32()), ("bits", pa.binary())])
_CANDIDATE_KIND = "region long, a long, b long, n int, bits binary"


def _led(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """Pairs (a, b) of a leader and a row; and for regions with more to compare, their rows (b null).

    Of a region in parts, all rows are put out: any may be near to a row that was in another part.
    """
    out: list[list] = [[] for _ in _CANDIDATE]

    def put(*values) -> None:
        for column, v in zip(out, values):
            column.extend(v)

    for region in _regions(batches, ["tree", "key", "part"]):
        order = np.argsort(region["rep"], kind="stable")
        region = {c: v[order] for c, v in region.items()}
        found, marked = _ascended(region, percent)
        for i, near in found:
            none = [None] * len(near)
            put(none, [int(region["rep"][i])] * len(near), region["rep"][near].tolist(), none, none)
            if len(out[0]) > 50_000:
                yield record_batch(_CANDIDATE, out)
                out = [[] for _ in _CANDIDATE]
        parted = region["parts"][0] > 1
        members = np.arange(len(order)) if parted else np.flatnonzero(marked)
        if parted or len(members) > 2:
            name = int(region["key"][0]) ^ (int(region["tree"][0]) << 48)
            put([name] * len(members), region["rep"][members].tolist(), [None] * len(members), region["n"][members].tolist(), [b.tobytes() for b in region["bits"][members]])
        if len(out[0]) > 50_000:
            yield record_batch(_CANDIDATE, out)
            out = [[] for _ in _CANDIDATE]
    yield record_batch(_CANDIDATE, out)


def _left_over(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """(id, other): a row, and a larger component with a row of its region that may be near to it.

    A cell holds two blocks of a region: of its largest component's rows (`top`) and of its other rows, or two blocks
    of other rows, or one of them twice.
    """
    schema, out = pa.schema([("id", pa.int64()), ("other", pa.int64())]), ([], [])
    for cell in _regions(batches, ["region", "x", "y"]):
        order = np.lexsort((cell["component"], cell["size"], cell["top"]))
        cell = {c: v[order] for c, v in cell.items()}
        label, rep, own, top, g = cell["component"], cell["rep"], cell["own"], int((cell["top"] == 0).sum()), len(order)
        ends = np.append(np.flatnonzero(label[1:] != label[:-1]) + 1, g)
        end = ends[np.searchsorted(ends, np.arange(g), side="right")]
        met, twice = cell["x"][0] < 0, cell["x"][0] == cell["y"][0]
        found = set()
        for i in range(top):
            others = np.arange(top if met else end[i], g)
            if not met and not twice:
                others = others[own[others] != own[i]]
            if len(others):
                found.update((int(rep[i]), int(x)) for x in np.unique(label[others[_near(cell, i, others, percent)]]))
        for x, y in found:
            out[0].append(x)
            out[1].append(y)
        if len(out[0]) > 50_000:
            yield record_batch(schema, list(out))
            out = ([], [])
    yield record_batch(schema, list(out))


def _met(asked: pa.Table, members: pa.Table, percent: int) -> pa.Table:
    """For each asked set, one linked set of the members, if there is any."""
    schema, out = pa.schema([("a", pa.int64()), ("b", pa.int64())]), ([], [])
    if asked.num_rows and members.num_rows:
        ids = members.column("id").to_numpy()
        sets = [np.frombuffer(b, dtype="<u8") for b in members.column("set").to_pylist()]
        sizes = np.array([len(x) for x in sets], dtype=np.int64)
        flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
        order = np.argsort(flat, kind="stable")
        flat, owner = flat[order], owner[order]
        for x, packed in zip(asked.column("id").to_pylist(), asked.column("set").to_pylist()):
            own = np.frombuffer(packed, dtype="<u8")
            low, high = np.searchsorted(flat, own, "left"), np.searchsorted(flat, own, "right")
            many = high - low
            at = np.repeat(low - np.cumsum(many) + many, many) + np.arange(many.sum())
            both = np.bincount(owner[at], minlength=len(sets))
            good = np.flatnonzero(100 * both >= percent * (len(own) + sizes - both))
            if len(good):
                out[0].append(x)
                out[1].append(int(ids[good[0]]))
    return pa.table([pa.array(c, pa.int64()) for c in out], schema=schema)


def _sets_of(batches: Iterator[pa.RecordBatch], words: int, bitmap: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Full sets of the documents whose id may be in the bitmap."""
    schema, shingler = pa.schema([("id", pa.int64()), ("set", pa.binary())]), Shingler(words)
    for whole in batches:
        keep = pa.array(np.flatnonzero(in_bitmap(bitmap, whole.column(1).to_numpy())))
        for batch in slices(whole.take(keep), 2, 2 << 20):
            yield record_batch(schema, [batch.column(0), [shingler(t).astype("<u8").tobytes() for t in batch.column(2).to_pylist()]])


def _confirmed(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    for batch in (part for whole in batches for part in slices(whole, 2, 4 << 20)):
        good = []
        for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
            p, q = np.frombuffer(x, dtype="<u8"), np.frombuffer(y, dtype="<u8")
            both = len(np.intersect1d(p, q, assume_unique=True))
            good.append(100 * both >= percent * (len(p) + len(q) - both))
        yield batch.select([0, 1]).filter(pa.array(good, pa.bool_()))


def _full_sets(docs: DataFrame, ids: DataFrame, rule: Rule) -> DataFrame:
    """(id, set) of the documents among the distinct ids, from their texts."""
    shared = docs.sparkSession.sparkContext.broadcast(id_bitmap(ids))
    asked = docs.where(F.col("doc_id").isNotNull()).select("doc_id", id_slot("doc_id").alias("slot"), text_bytes())
    return map_arrow(asked, lambda b: _sets_of(b, rule.words, shared.value), "id long, set binary").join(ids, "id", "left_semi")


def _confirm(pairs: DataFrame, sets: DataFrame, rule: Rule) -> DataFrame:
    """The pairs (a, b) that are links, by full sets."""
    first = pairs.join(sets.select(F.col("id").alias("a"), F.col("set").alias("set_a")), "a")
    both = first.join(sets.select(F.col("id").alias("b"), F.col("set").alias("set_b")), "b").select("a", "b", "set_a", "set_b")
    return map_arrow(both, partial(_confirmed, percent=rule.percent), "a long, b long")


def _ends(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct()


def _links_between(docs: DataFrame, members: DataFrame, labels: DataFrame, rule: Rule, scratch: Scratch) -> DataFrame:
    """Links of rows with other, larger components, at least one for each two that have any in their regions."""
    sizes = labels.groupBy("component").agg(F.count(F.lit(1)).alias("size"))
    known = labels.join(sizes, "component").select(F.col("node").alias("rep"), "component", "size")
    labelled = members.join(known, "rep", "left").select("region", "rep", "n", "bits", F.coalesce("component", "rep").alias("component"), F.coalesce("size", F.lit(1)).alias("size"))
    each = labelled.groupBy("region", "component").agg(F.max("size").alias("size"), F.count(F.lit(1)).alias("n"))
    rows = each.groupBy("region").agg(F.max(F.struct("size", "component", "n")).alias("m"), F.sum("n").alias("n"), F.count(F.lit(1)).alias("kinds")).where("kinds > 1")
    blocks = rows.select("region", F.col("m.component").alias("largest"), F.ceil(F.col("m.n") / REGION).cast("int").alias("tops"), F.ceil((F.col("n") - F.col("m.n")) / REGION).cast("int").alias("others"))
    blocks = scratch.keep(blocks, "blocks")
    blocks = F.broadcast(blocks) if blocks.count() <= MOST_SENT else blocks
    marked = labelled.join(blocks, "region").withColumn("top", (F.col("component") == F.col("largest")).cast("int"))
    dealt = marked.withColumn("own", F.pmod(F.xxhash64("rep"), F.when(F.col("top") == 1, F.col("tops")).otherwise(F.col("others"))).cast("int"))
    upto = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    cell = lambda x, y: F.struct(x.cast("int").alias("x"), y.cast("int").alias("y"))
    with_top = lambda t, o: cell(-1 - t, o)  # noqa: E731  a cell of top and other rows has x below 0
    own = F.col("own")
    beside = F.transform(upto("others"), lambda o: cell(F.least(own, o), F.greatest(own, o)))
    cells = F.when(F.col("top") == 1, F.transform(upto("others"), lambda o: with_top(own, o))).otherwise(F.concat(F.transform(upto("tops"), lambda t: with_top(t, own)), beside))
    spread = dealt.withColumn("cell", F.explode(cells)).select("region", "cell.x", "cell.y", "rep", "n", "bits", "component", "size", "top", "own")
    ordered = spread.repartition("region", "x", "y").sortWithinPartitions("region", "x", "y")
    asked = scratch.keep(map_arrow(ordered, partial(_left_over, percent=rule.percent), "id long, other long").distinct(), "asked")
    wanted = asked.select("other").distinct().join(sizes.withColumnRenamed("component", "other"), "other", "left").select("other", F.coalesce("size", F.lit(1)).alias("size"))
    inside = wanted.join(labels.select(F.col("component").alias("other"), "node"), "other", "left").select("other", "size", F.coalesce("node", "other").alias("node"))
    inside = scratch.keep(inside, "inside")
    few = asked.join(inside.where(F.col("size") <= SMALL_COMPONENT), "other").select(F.col("id").alias("a"), F.col("node").alias("b"))
    sets = _full_sets(docs, asked.select("id").union(inside.select(F.col("node").alias("id"))).distinct(), rule)
    sets = scratch.keep(sets, "sets")
    links = _confirm(few.distinct(), sets, rule)
    large = inside.where(F.col("size") > SMALL_COMPONENT).select("other", F.col("node").alias("id"))
    asking = asked.join(large.select("other").distinct(), "other").select("other", "id")
    bytes_of = sets.select("id", F.octet_length("set").cast("long").alias("bytes"))
    in_blocks = lambda rows, name: rows.join(bytes_of, "id").groupBy("other").agg((F.floor(F.sum("bytes") / TOGETHER) + 1).cast("int").alias(name))
    dealing = in_blocks(large, "blocks").join(in_blocks(asking, "turns"), "other")
    upto = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    hashed = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    fields = ("other", "block", "turn", "id", "set")
    held = large.join(dealing, "other").select("other", hashed("blocks").alias("block"), upto("turns").alias("turn"), "id").join(sets, "id").select(*(F.col(c).alias(c) for c in fields))
    queries = asking.join(dealing, "other").select("other", upto("blocks").alias("block"), hashed("turns").alias("turn"), "id").join(sets, "id").select(*(F.col(c).alias(c) for c in fields))
    met = queries.groupBy("other", "block", "turn").cogroup(held.groupBy("other", "block", "turn")).applyInArrow(lambda q, m: _met(q, m, rule.percent), "a long, b long")
    return links.union(met)


def near_duplicates(docs: DataFrame, rule: Rule = Rule()) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row of (doc_id, text).

    A text without words, or null, has an empty set and links with nothing; a text of fewer words than a shingle is
    one shingle. Rows that repeat a doc_id are documents of their own that carry the same id; rows with a null doc_id
    link with nothing and have a null component and are kept. Other columns are ignored.
    """
    spark: SparkSession = docs.sparkSession
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    scratch = Scratch(spark, "neardup")
    sketches = scratch.keep(map_arrow(own.select("doc_id", text_bytes()), partial(_sketched, words=rule.words), "doc_id long, n_shingles long, print_a long, print_b long, signature binary, bits binary"), "sketches")
    linkable = sketches.where((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull())
    classes = linkable.groupBy("print_a", "print_b").agg(F.min("doc_id").alias("rep"))
    reps = linkable.join(classes, ["print_a", "print_b"]).where(F.col("doc_id") == F.col("rep")).dropDuplicates(["print_a", "print_b"])
    branches = map_arrow(reps.select("rep", F.col("n_shingles").cast("int").alias("n"), "signature", "bits"), _branches, _BRANCH_KIND)
    regions = scratch.keep(_large_regions(linkable), "regions")
    regions = F.broadcast(regions) if regions.count() <= MOST_SENT else regions
    parts = F.coalesce("parts", F.lit(1))
    dealt = branches.join(regions, ["tree", "key"], "left").select("tree", "key", F.pmod(F.xxhash64("rep", "tree"), parts).cast("int").alias("part"), parts.alias("parts"), "deeper", "rep", "n", "bits")
    sorted_branches = dealt.repartition("tree", "key", "part").sortWithinPartitions("tree", "key", "part", "deeper")
    found = scratch.keep(map_arrow(sorted_branches, partial(_led, percent=rule.percent), _CANDIDATE_KIND), "candidates")
    pairs = scratch.keep(found.where(F.col("region").isNull()).select("a", "b").where(F.col("a") != F.col("b")).distinct(), "pairs")
    links = scratch.keep(_confirm(pairs, scratch.keep(_full_sets(own, _ends(pairs), rule), "pair-sets"), rule), "links")
    scratch.drop("pair-sets")
    labels = scratch.keep(components(links, scratch), "labels")
    members = found.where(F.col("region").isNotNull()).select("region", F.col("a").alias("rep"), "n", "bits")
    extra = scratch.keep(_links_between(own, members, labels, rule, scratch), "more-links")
    scratch.drop("sets")
    if not extra.isEmpty():
        roots = labels.select(F.col("node").alias("a"), F.col("component").alias("b"))
        labels = scratch.keep(components(extra.union(roots), scratch, "again"), "labels-again")
    scratch.drop("regions", "candidates", "pairs", "links", "blocks", "asked", "inside", "more-links")
    by_class = classes.join(labels.withColumnRenamed("node", "rep"), "rep", "left").select("print_a", "print_b", F.coalesce("component", "rep").alias("component_id"))
    joined = linkable.select("doc_id", "n_shingles", "print_a", "print_b").join(by_class, ["print_a", "print_b"]).select("doc_id", "n_shingles", "component_id")
    alone = sketches.where((F.col("n_shingles") == 0) | F.col("doc_id").isNull()).select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return joined.unionByName(alone).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_first(docs: DataFrame, rule: Rule = Rule()) -> DataFrame:
    """The rows of (doc_id, text, ...) that stay when one row of each group of linked texts is kept, with all columns.

    The row of the smallest doc_id stays. Rows are told apart even if their doc_id is null or on several rows: such rows
    come after all others, and of equal ones a single one stays. Texts without words link with nothing and stay, so
    repeated rows of them stay repeated. Other columns may have any names.
    """
    spark, scratch = docs.sparkSession, Scratch(docs.sparkSession, "keepfirst")
    key, again = fresh_name(docs.columns, "_key"), fresh_name(docs.columns, "_again")
    ids = docs.select(F.col("doc_id").cast("long").alias("id"))
    many = ids.where("id is not null").groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("id")
    many = scratch.keep(many, "many")
    nulls, top = ids.agg(F.count_if(F.col("id").isNull()), F.coalesce(F.max("id"), F.lit(0))).first()
    if not nulls and many.isEmpty():
        found = near_duplicates(docs.select("doc_id", "text"), rule)
        return without_ids(docs, "doc_id", found.where(~F.col("kept")).select(F.col("doc_id").alias("id")))
    # rows whose doc_id does not tell them apart get numbers above all others, written once so that they stay the same
    doubled = docs.join(many.select(F.col("id").alias(again)), F.col("doc_id").cast("long") == F.col(f"`{again}`"), "left_semi")
    doubled = doubled.union(docs.where(F.col("doc_id").isNull()))
    doubled = scratch.keep(doubled.select("*", (F.lit(top) + 1 + F.monotonically_increasing_id()).alias(key)), "doubled")
    single = without_ids(docs.where(F.col("doc_id").isNotNull()), "doc_id", many)
    every = single.select(F.col("doc_id").cast("long").alias("doc_id"), "text").union(doubled.select(F.col(f"`{key}`"), "text"))
    found = near_duplicates(every, rule)
    gone = found.where(~F.col("kept")).select(F.col("doc_id").alias("id"))
    return without_ids(single, "doc_id", gone).union(without_ids(doubled, key, gone).drop(key))


def op10_minhash_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), Rule(words=2))
