import numpy as np
import pytest
from pyspark.sql import functions as F

from tablevec.llm import exact_search as es


def _brute(queries, q_ids, data, d_ids, k):
    out = {}
    for q, i in zip(queries, q_ids):
        scored = sorted((-int(q @ d), int(j)) for d, j in zip(data, d_ids) if j != i)
        out[int(i)] = [(j, -s) for s, j in scored[:k]]
    return out


@pytest.mark.parametrize("kind", ["random", "clustered", "copies", "few"])
def test_dual_search_against_all_products(kind):
    rng = np.random.default_rng(3)
    data = rng.integers(-900, 900, size=(2000, 8)).astype(float)
    if kind == "clustered":
        data = np.floor(rng.normal(size=(20, 8))[rng.integers(0, 20, 2000)] * 900 + rng.normal(size=(2000, 8)) * 5)
    if kind == "copies":
        data[100:1500] = data[7]
    if kind == "few":
        data = data[:6]
    ids = rng.permutation(len(data))
    best, work = es.dual_search(data[:200], ids[:200], data, ids, 10)
    want = _brute(data[:200], ids[:200], data, ids, 10)
    for row, i in enumerate(ids[:200]):
        got = [(int(j), int(s)) for j, s in zip(best.ids[row], best.scores[row]) if np.isfinite(s)]
        assert got == want[int(i)]
    if kind == "clustered":
        assert work < 0.6 * 200 * len(data)


def test_tree_covers_its_points():
    rng = np.random.default_rng(4)
    tree = es.CoverTree(rng.normal(size=(3000, 3)))
    for c, r, (a, b), (low, high) in zip(tree.centers, tree.radius, tree.span, tree.kids):
        assert (np.sqrt(((tree.points[a:b] - c) ** 2).sum(axis=1)) <= r + 1e-9).all()
        if high:
            assert tree.span[low][0] == a and tree.span[high - 1][1] == b
    assert sorted(tree.order) == list(range(3000))


def test_search_on_spark_with_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(es, "BLOCK", 150)
    monkeypatch.setattr(es, "QUERY_BLOCK", 7)
    rng = np.random.default_rng(5)
    x = rng.normal(size=(1200, 6)).astype(np.float32)
    x[50:400] = x[3]
    rows = [(int(i), [float(v) for v in r]) for i, r in enumerate(x)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = es.search(df, df.where("vec_id % 25 = 0"), 10).collect()
    data, ids = np.floor(1024 * x.astype(float)), np.arange(1200)
    want = _brute(data[::25], ids[::25], data, ids, 10)
    found = {}
    for r in sorted(got, key=lambda r: (r["query_id"], r["rank"])):
        found.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert found == want


def test_odd_vectors_ids_and_no_rows(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 2.0], 9), (1, None, 9), (2, [nan, 1.0], 9), (3, [inf, 1.0], 9), (4, [None, 1.0], 9), (None, [5.0, 5.0], 9), (5, [2.0], 9), (5, [2.0], 9), (6, [0.0, -1.0, 4.0], 9), (100, [1.0, 1.0], 9)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, rank int")
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in es.search(df, df.where("vec_id % 100 = 0"), 10).collect())
    k = 1024 * 1024
    assert got == [(0, 1, 100, 3 * k), (0, 2, 5, 2 * k), (0, 3, 5, 2 * k), (0, 4, 6, -2 * k), (100, 1, 0, 3 * k), (100, 2, 5, 2 * k), (100, 3, 5, 2 * k), (100, 4, 6, -k)]
    assert es.search(df.limit(0), df, 3).count() == es.search(df, df.where(F.lit(False)), 3).count() == 0
    assert es.search(df.where("vec_id = 0"), df.where("vec_id = 0"), 3).count() == 0


def test_query_parts_are_bounded_and_share_cells():
    got = es.query_parts({0: 3, 1: 3, 2: 20, 3: 1, 5: 7}, 7)
    assert got == [(0, 0, 1), (1, 0, 1), (2, 1, 3), (3, 4, 1), (5, 5, 1)]


def test_clustered_vectors_are_pruned_and_not_copied_to_all_parts(spark, monkeypatch):
    monkeypatch.setattr(es, "QUERY_BLOCK", 20)
    rng = np.random.default_rng(8)
    centers = rng.normal(size=(20, 16))
    x = centers[rng.integers(0, 20, 3000)] + rng.normal(size=(3000, 16)) * 0.01
    x = (x / np.linalg.norm(x, axis=1)[:, None]).astype(np.float32)
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<float>")
    seen, counted = spark.sparkContext.accumulator(0), es._searched
    monkeypatch.setattr(es, "_searched", lambda q, d, k: (seen.add(q.num_rows * d.num_rows), counted(q, d, k))[1])
    got = es.search(df, df.where("vec_id % 10 = 0"), 10).collect()
    data = np.floor(1024 * x.astype(float))
    want = _brute(data[::10], np.arange(0, 3000, 10), data, np.arange(3000), 10)
    found = {}
    for r in sorted(got, key=lambda r: (r["query_id"], r["rank"])):
        found.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert found == want
    assert 0 < seen.value < 0.5 * 300 * 3000
