"""Queries of the library by name, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tablevec.operators import solvers
from tablevec.operators.weights import Params
from tablevec.queries import core, relational, tasks

_MODULES = [core, relational, tasks]
QUERIES = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in _MODULES for k, v in m.ORACLES.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three sweeps of the series solver on the smallest database, by value."""
    db = core.mini(spark, sf_dir)
    return db.named(solvers.fit_series(db.problem, Params(1, 0, 3, 1), 3).vectors).select("category", "value", "vec")
