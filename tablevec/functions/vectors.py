"""Vector functions on arrays of doubles, as Catalyst expressions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _c(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def vec_dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(_c(a), _c(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column | str) -> Column:
    return F.sqrt(F.aggregate(_c(a), F.lit(0.0), lambda s, x: s + x * x))


def vec_scale(a: Column | str, k: Column | float) -> Column:
    return F.transform(_c(a), lambda x: x * k)


def vec_add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x + y)


def vec_sub(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_c(a), _c(b), lambda x, y: x - y)


def vec_zero(dims: int) -> Column:
    return F.array_repeat(F.lit(0.0), dims)


def vec_unit(a: Column | str) -> Column:
    """Scaled to length 1; the zero vector stays."""
    n = vec_norm(a)
    return F.when(n > 0, vec_scale(a, F.lit(1.0) / n)).otherwise(_c(a))


def vec_cosine(a: Column | str, b: Column | str) -> Column:
    """0 if either is the zero vector."""
    n = vec_norm(a) * vec_norm(b)
    return F.when(n > 0, vec_dot(a, b) / n).otherwise(F.lit(0.0))


def vec_sum(a: Column | str, dims: int, weight: Column | float | None = None) -> Column:
    """Aggregate: one scalar sum for each dimension, so sums are partial before the shuffle and can spill."""
    a = _c(a)
    return F.array(*(F.sum(F.get(a, F.lit(i)) if weight is None else F.get(a, F.lit(i)) * weight) for i in range(dims)))


def vec_mean(a: Column | str, dims: int) -> Column:
    a = _c(a)
    return F.array(*(F.avg(F.get(a, F.lit(i))) for i in range(dims)))


def tokens(text: Column | str) -> Column:
    """Lower-case runs of letters and digits."""
    return F.filter(F.split(F.lower(_c(text)), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def register(spark: SparkSession) -> None:
    """The same functions for SQL."""
    for sql in (
        "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        "vec_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
        "vec_add(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x + y)",
        "vec_scale(a ARRAY<DOUBLE>, k DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * k)",
        "vec_zero(n INT) RETURNS ARRAY<DOUBLE> RETURN array_repeat(0D, n)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {sql}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_unit(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN CASE WHEN vec_norm(a) > 0 THEN vec_scale(a, 1 / vec_norm(a)) ELSE a END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN CASE WHEN vec_norm(a) * vec_norm(b) > 0 THEN vec_dot(a, b) / (vec_norm(a) * vec_norm(b)) ELSE 0D END")
