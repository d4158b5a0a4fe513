"""The kernel that moves only the vectors of hubs, against the two others."""

import numpy as np
import pytest

from tablevec.operators import solvers
from tablevec.operators.weights import Params
from tablevec.queries import core

from tests.test_methods import toy, vectors

FITS = {
    "objective": lambda p, **more: solvers.fit_objective(p, core.OBJECTIVE, 3, **more),
    "series": lambda p, **more: solvers.fit_series(p, core.SERIES, 3, **more),
    "graph": lambda p, **more: solvers.fit_graph_baseline(p, 4, **more),
}


def _no_joins(*_):
    raise AssertionError("the joins were used")


@pytest.mark.parametrize("method", FITS)
def test_hubs_agree_with_broadcast_without_any_join_of_vectors(spark, tiny, method, monkeypatch):
    p = core.mini(spark, tiny).problem
    want = FITS[method](p, kernel="broadcast")
    monkeypatch.setattr(solvers, "HUB_DEGREE", 4)
    monkeypatch.setattr(solvers, "CHUNK", 40)
    monkeypatch.setattr(solvers, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(solvers, "SUM_BYTES", 0)
    monkeypatch.setattr(solvers, "_shuffle", _no_joins)
    got = FITS[method](p)
    assert np.allclose(vectors(got), vectors(want), atol=1e-12)
    assert got.vectors.count() == p.base.count()
    assert got.history[-1]["rel_step"] == pytest.approx(want.history[-1]["rel_step"], rel=1e-9)
    assert got.least_denominator == pytest.approx(want.least_denominator)


def test_hubs_stop_at_the_same_sweep(spark, tiny, monkeypatch):
    p = core.mini(spark, tiny).problem
    monkeypatch.setattr(solvers, "HUB_DEGREE", 4)
    want = solvers.fit_series(p, core.SERIES, 30, kernel="broadcast", tol=1e-3)
    monkeypatch.setattr(solvers, "_shuffle", _no_joins)
    got = solvers.fit_series(p, core.SERIES, 30, kernel="hubs", tol=1e-3)
    assert [h["sweep"] for h in got.history] == [h["sweep"] for h in want.history]
    assert np.allclose([h["rel_step"] for h in got.history], [h["rel_step"] for h in want.history])
    assert np.allclose(vectors(got), vectors(want), atol=1e-12)


def test_more_ends_than_hubs_go_by_joins(spark, monkeypatch):
    p, _ = toy(spark)
    monkeypatch.setattr(solvers, "HUBS", 1)
    for kernel in ("hubs", "broadcast"):
        got = solvers.fit_series(p, Params(1, 0, 3, 1), 3, kernel=kernel)
        want = solvers.fit_series(p, Params(1, 0, 3, 1), 3, kernel="shuffle")
        assert np.allclose(vectors(got), vectors(want), atol=1e-12)


def test_upkeep_that_moves_all_values_is_a_fit(spark, tiny, monkeypatch):
    from tablevec.streaming import upkeep

    db = core.mini(spark, tiny)
    want = solvers.fit_objective(db.problem, core.OBJECTIVE, 3)
    kept = upkeep.local_sweeps(db, want.vectors, db.nodes.select("node_id").limit(1), core.OBJECTIVE, 1)  # a part: by joins
    assert kept.count() == db.nodes.count()
    monkeypatch.setattr(solvers, "sweep", _no_joins)
    got = upkeep.local_sweeps(db, db.problem.base.select("node_id", "vec"), db.nodes.select("node_id"), core.OBJECTIVE, 3)
    assert np.allclose(np.array([r["vec"] for r in got.orderBy("node_id").collect()]), vectors(want), atol=1e-12)


def test_written_tables_broadcast_only_what_was_measured(spark, monkeypatch):
    from pyspark.sql import DataFrameWriter

    from tablevec.plans import checks
    from tablevec.plans.stages import Stages

    names = ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold")
    before, found, write = [spark.conf.get(n, None) for n in names], [], DataFrameWriter.parquet
    stages = Stages(spark, "measured")
    a, b = stages.keep(spark.range(40_000)), stages.keep(spark.range(40_000))
    joined = a.join(b, "id")
    assert checks.joins(joined.select("id")) == ["BroadcastHashJoin"]

    def look(self, path, *args):
        found.append((checks.joins(self._df.select("*")), spark.conf.get(names[1])))
        return write(self, path, *args)

    monkeypatch.setattr(DataFrameWriter, "parquet", look)
    assert stages.keep(joined).count() == 40_000
    assert found == [(["SortMergeJoin"], before[0])]
    assert [spark.conf.get(n, None) for n in names] == before
