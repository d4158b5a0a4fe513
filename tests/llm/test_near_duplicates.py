import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tablevec.llm import near_duplicates as nd
from tablevec.llm.common import Scratch
from tablevec.llm.components import components


def brute(rows, words, percent=80):
    """Component of each row by comparing all pairs of plain shingle sets; rows are (id, text)."""
    sets = []
    for _, text in rows:
        w = (text or "").encode().lower().split()
        sets.append(set() if not w else {tuple(w)} if len(w) < words else set(zip(*[w[j:] for j in range(words)])))
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, p in enumerate(sets):
        for j in range(i):
            q = sets[j]
            if p and q and 100 * len(p & q) >= percent * len(p | q):
                parent[root(i)] = root(j)
    least = {}
    for i, (k, _) in enumerate(rows):
        least[root(i)] = min(k, least.get(root(i), k))
    return sorted((k, len(sets[i]), least[root(i)], k == least[root(i)]) for i, (k, _) in enumerate(rows))


def _got(df):
    return sorted((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in df.collect())


@pytest.mark.parametrize("words", [2, 5])
def test_table_against_all_pairs(spark, tiny, words):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    assert _got(nd.near_duplicates(docs, nd.Rule(words))) == brute(rows, words)


def _chains(rng, n):
    """Texts that drift word by word, so that links form long chains, beside texts that share a passage."""
    vocabulary = [f"w{i}" for i in range(500)]
    text, out = [rng.choice(vocabulary) for _ in range(60)], []
    for _ in range(n):
        for _ in range(2):
            text[rng.randrange(60)] = rng.choice(vocabulary)
        out.append(" ".join(text))
    passage = " ".join(rng.choice(vocabulary) for _ in range(30))
    return out + [passage + " " + " ".join(rng.choice(vocabulary) for _ in range(rng.randrange(3, 40))) for _ in range(n)]


def test_chains_and_shared_passages(spark):
    rng = random.Random(6)
    texts = _chains(rng, 120)
    rows = list(enumerate(rng.sample(texts, len(texts))))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert _got(nd.near_duplicates(df, nd.Rule(2))) == brute(rows, 2)


def test_large_regions_in_parts(spark, monkeypatch):
    monkeypatch.setattr(nd, "REGION", 20)
    rng = random.Random(7)
    base = [f"w{rng.randrange(900)}" for _ in range(200)]
    rows = []
    for i in range(150):
        words = list(base)
        for _ in range(2):
            words[rng.randrange(200)] = f"x{i}"
        rows.append((i, " ".join(words)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert _got(nd.near_duplicates(df, nd.Rule(2))) == brute(rows, 2)


def _drifting(rng, n, pendants):
    """Near copies whose drift is slow, so that all share regions, and copies that only one of them is near to."""
    base, out = [f"w{rng.randrange(900)}" for _ in range(200)], []
    for i in range(n):
        base[rng.randrange(200)] = f"x{i}"
        out.append(list(base))
    for i in range(pendants):
        words = list(rng.choice(out[:n]))
        for j in rng.sample(range(200), 15):
            words[j] = f"y{i}-{j}"
        out.append(words)
    return [" ".join(w) for w in out]


def test_regions_in_blocks_lose_no_links(spark, monkeypatch):
    monkeypatch.setattr(nd, "REGION", 6)
    texts = _drifting(random.Random(5), 160, 40)
    rows = list(enumerate(random.Random(8).sample(texts, len(texts))))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert _got(nd.near_duplicates(df, nd.Rule(2))) == brute(rows, 2)


def _sketches(rng, n, drift):
    """n rows of one region whose sketches drift; (batch of branches, rows that may be near to each other)."""
    import pyarrow as pa

    bits, rows = rng.integers(0, 4, nd.MINHASHES), []
    for _ in range(n):
        bits = bits.copy()
        bits[rng.choice(nd.MINHASHES, drift, replace=False)] = rng.integers(0, 4, drift)
        rows.append(bits)
    packed = nd.low_bits(np.array(rows)).view("<u8")
    deeper = rng.permutation(n)
    order = np.argsort(deeper)
    columns = {"tree": np.zeros(n, np.int32), "key": np.full(n, 5), "deeper": deeper[order], "rep": order, "n": np.full(n, 100, np.int32), "bits": [packed[i].tobytes() for i in order]}
    region = {"n": np.full(n, 100), "bits": packed}
    near = {(i, j) for i in range(n) for j in np.flatnonzero(nd._near(region, i, np.arange(n), 80)).tolist() if i != j}
    return pa.table(columns), near


@pytest.mark.parametrize("parts", [20, 1])
def test_every_near_pair_of_a_region_is_paired_or_left_to_one_region(parts):
    import pyarrow as pa

    t, near = _sketches(np.random.default_rng(2), 150, 12)
    part = np.random.default_rng(3).integers(0, parts, 150).astype(np.int32)
    t = t.append_column("part", pa.array(part)).append_column("parts", pa.array(np.full(150, parts, np.int32))).sort_by("part")
    rows = [r for b in nd._led(iter(t.to_batches(max_chunksize=10)), 80) for r in b.to_pylist()]
    pairs = {(r["a"], r["b"]) for r in rows if r["region"] is None}
    names, members = {r["region"] for r in rows if r["region"] is not None}, [r["a"] for r in rows if r["region"] is not None]
    assert len(near) > 300 and len(names) == 1 and len(members) == len(set(members)) and pairs <= near
    assert all((i, j) in pairs or (j, i) in pairs or {i, j} <= set(members) for i, j in near)


def test_large_regions_are_found_and_dealt(spark, monkeypatch):
    monkeypatch.setattr(nd, "REGION", 40)
    texts = [t for t in _drifting(random.Random(5), 400, 0)] + [f"lone{i} text{i} of{i} its{i} own{i}" for i in range(200)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts + texts[:1] * 500)], "doc_id long, text string")
    sketches = nd.map_arrow(df.select("doc_id", nd.text_bytes()), lambda b: nd._sketched(b, 2), "doc_id long, n_shingles long, print_a long, print_b long, signature binary, bits binary")
    found = nd._large_regions(sketches).collect()
    assert found and {r["parts"] for r in found} <= set(range(2, 12))
    branches = nd.map_arrow(sketches.dropDuplicates(["print_a", "print_b"]).select(F.col("doc_id").alias("rep"), F.col("n_shingles").cast("int").alias("n"), "signature", "bits"), nd._branches, nd._BRANCH_KIND)
    sizes = {(r["tree"], r["key"]): r["count"] for r in branches.groupBy("tree", "key").count().collect()}
    large = {k for k, n in sizes.items() if n > 80}
    assert large <= {(r["tree"], r["key"]) for r in found} and all(sizes[r["tree"], r["key"]] > 10 for r in found)


@pytest.mark.parametrize("small", [0, 3, 16])
def test_links_between_components(spark, monkeypatch, small):
    monkeypatch.setattr(nd, "SMALL_COMPONENT", small)
    monkeypatch.setattr(nd, "TOGETHER", 10)
    rng = random.Random(11)
    rows = list(enumerate(t for k in range(4) for t in _chains(random.Random(k), 60)[:60]))
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert _got(nd.near_duplicates(df, nd.Rule(2))) == brute(rows, 2)


def test_runs_over_many_batches_come_whole():
    import pyarrow as pa

    keys = [1] * 3 + [2] + [5] * 100 + [6, 6]
    batches = [pa.RecordBatch.from_arrays([pa.array(keys[i : i + 7]), pa.array(list(range(i, min(i + 7, len(keys)))))], names=["key", "rep"]) for i in range(0, len(keys), 7)]
    whole = [(r["key"][0], list(r["rep"])) for r in nd._regions(iter(batches), ["key"])]
    assert whole == [(1, [0, 1, 2]), (5, list(range(4, 104))), (6, [104, 105])]
    assert not list(nd._regions(iter([]), ["key"])) and not list(nd._regions(iter([batches[0].slice(0, 1)]), ["key"]))


def test_nulls_short_texts_repeats_and_no_rows(spark):
    rows = [(1, None, 0), (2, "", 0), (3, " \t\n", 0), (4, "One", 0), (5, "one", 0), (6, "one two", 0), (7, "ONE  two", 0), (7, "one two", 0), (8, "É x", 0), (9, "é x", 0), (10, "a\x1cb", 0), (None, "one two", 0), (None, None, 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, kept int")
    got = sorted(((r["doc_id"] or -1, r["n_shingles"], r["component_id"], r["kept"]) for r in nd.near_duplicates(df, nd.Rule(2)).collect()), key=repr)
    want = [(1, 0, 1, True), (2, 0, 2, True), (3, 0, 3, True), (4, 1, 4, True), (5, 1, 4, False), (6, 1, 6, True), (7, 1, 6, False), (7, 1, 6, False), (8, 1, 8, True), (9, 1, 9, True), (10, 1, 10, True), (-1, 1, None, True), (-1, 0, None, True)]
    assert got == sorted(want, key=repr)
    assert nd.near_duplicates(df.limit(0), nd.Rule(2)).count() == 0


def test_components_of_paths_and_hubs(spark):
    rng = random.Random(9)
    order = list(range(100, 400))
    rng.shuffle(order)
    edges = list(zip(order, order[1:])) + [(1000, k) for k in range(1001, 1500)] + [(7, 7), (8, 9), (9, 8), (9, 8)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long"), Scratch(spark, "t")).collect()}
    assert all(got[k] == 100 for k in order) and all(got[k] == 1000 for k in range(1000, 1500)) and got[9] == got[8] == 8
    assert components(spark.createDataFrame([], "a long, b long"), Scratch(spark, "t")).count() == 0


def test_sketch_bits_keep_near_sets():
    rng = np.random.default_rng(1)
    lost = 0
    for _ in range(200):
        pool = rng.integers(0, 1 << 63, 540, dtype=np.uint64)
        sets = [np.unique(pool[:300]), np.unique(np.concatenate([pool[:267], pool[300:333]]))]  # similarity 0.802
        bits = nd.low_bits(nd.min_hashes(sets)).view("<u8")
        region = {"n": np.array([len(x) for x in sets]), "bits": bits}
        lost += not nd._near(region, 0, np.array([1]), 80)[0]
    assert lost == 0


@pytest.mark.parametrize("rows", [1, 2, 3, 40, 300])
def test_prefixes_are_compared_from_the_longest_and_no_near_pair_is_left(rows):
    rng = np.random.default_rng(rows)
    base = rng.integers(0, 1 << 62, (6, nd.MINHASHES // 32), dtype=np.uint64)
    bits = base[rng.integers(0, 6, rows)]
    for i in range(rows):  # up to 120 of 384 bits differ: some rows of a kind are near, some not
        for k in rng.integers(0, bits.shape[1] * 64, rng.integers(0, 120)):
            bits[i, k // 64] ^= np.uint64(1) << np.uint64(k % 64)
    # values of four kinds each, so that rows share prefixes of every length
    deeper = sum(rng.integers(0, 4, rows).astype(np.int64) << 16 * k for k in range(3)) + (rng.integers(0, 2, rows).astype(np.int64) << 48)
    region = {"rep": np.arange(rows), "n": np.full(rows, 50, np.int32), "bits": bits, "deeper": deeper}
    found, marked = nd._ascended(region, 80)
    near = np.array([nd._near(region, i, np.arange(rows), 80) for i in range(rows)])
    assert all(near[i, j] and i < j for i, js in found for j in js)
    both = near & ~np.eye(rows, dtype=bool)
    assert (marked == both.any(axis=1)).all()
    led = {int(j) for _, js in found for j in js}
    leaders = [i for i in range(rows) if i not in led]
    assert not both[np.ix_(leaders, leaders)].any()  # no two rows without a leader are near
    # a row with a near earlier row of the longest prefix that it shares with any row before it is led at that depth
    for j in range(rows):
        same = [i for i in range(j) if deeper[i] == deeper[j] and near[i, j] and i in leaders]
        assert not same or any(j in js and deeper[i] == deeper[j] for i, js in found)
