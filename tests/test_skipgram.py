import numpy as np
import pyspark.ml.feature
import pytest
from pyspark.sql import functions as F

from tablevec.operators import graph, skipgram


def _two_groups(spark, n=60):
    """Values 0 to n - 1, even ones around value 0 and the column 'a', odd ones around 1 and 'b'."""
    vertices = spark.createDataFrame([(str(i), "value") for i in range(n)] + [("a", "column"), ("b", "column")], "vertex string, kind string")
    pairs = [(str(i), v) for i in range(2, n) for v in (str(i % 2), "ab"[i % 2])] + [("0", "a"), ("1", "b")]
    return vertices, spark.createDataFrame([(*e, "x") for p in pairs for e in (p, p[::-1])], "src string, dst string, label string")


def test_many_vertices_need_no_model_on_the_driver(spark, monkeypatch):
    monkeypatch.setattr(pyspark.ml.feature, "Word2Vec", None)
    monkeypatch.setattr(graph, "MODEL_VERTICES", 20, raising=False)
    monkeypatch.setattr(skipgram, "BLOCK", 25)
    monkeypatch.setattr(skipgram, "BLOCKS", 2)
    vertices, edges = _two_groups(spark)
    fit = lambda v, e: {r["node_id"]: r["vec"] for r in graph.fit_walks((v, e), 10, 10, 3, 8, rounds=2).collect()}
    got = fit(vertices, edges)
    assert sorted(got) == list(range(60)) and all(len(v) == 8 for v in got.values())
    assert got == fit(vertices.repartition(7), edges.repartition(5))
    x = np.array([got[i] for i in range(60)])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    near = x @ x.T - 9 * np.eye(60)
    assert (near.argmax(axis=1) % 2 == np.arange(60) % 2).mean() > 0.95


def test_every_pair_in_the_window_and_none_across_paths():
    flat, sizes = np.array([5, 6, 7, 8, 9]), np.array([3, 2])
    assert sorted(map(tuple, skipgram.pairs_of(flat, sizes, 1, np.random.default_rng(0)))) == [(5, 6), (6, 5), (6, 7), (7, 6), (8, 9), (9, 8)]
    far = {tuple(p) for k in range(50) for p in skipgram.pairs_of(flat, sizes, 2, np.random.default_rng(k))}
    assert far == {(5, 6), (6, 5), (6, 7), (7, 6), (5, 7), (7, 5), (8, 9), (9, 8)}
    assert len(skipgram.pairs_of(flat[:1], np.array([1]), 5, np.random.default_rng(0))) == 0


@pytest.mark.parametrize(("found", "wanted"), [(["0", "1", "x"], (2, ["x"])), (["1", "2"], None), (["0", "01"], (1, ["01"]))])
def test_numbers_are_told_from_names(spark, found, wanted):
    assert skipgram.numbering(spark.createDataFrame([(v,) for v in found], "vertex string").select(F.col("vertex"))) == wanted
