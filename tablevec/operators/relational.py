"""Operators around the methods that Spark lacks in one call: interval, range and as-of joins, sampling."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def broadcast_if_small(df: DataFrame, most_rows: int = 1_000_000) -> DataFrame:
    """A hint to broadcast only if a limited count shows that the rows are few."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


def interval_join(left: DataFrame, right: DataFrame, by: str, time: str, seconds: int) -> DataFrame:
    """Pairs of rows with equal `by` and times at most so far apart.

    Right columns get the suffix _r. Rows meet by key and time bin, and the right side stands in its bin and both
    beside it, so a key with many rows is dealt over its bins.
    """
    bin_of = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.withColumn("_bin", bin_of(F.col(time)))
    b = right.select(*(F.col(c).alias(f"{c}_r") for c in right.columns))
    b = b.withColumn("_at", bin_of(F.col(f"{time}_r"))).withColumn("_bin", F.explode(F.array(F.col("_at") - 1, F.col("_at"), F.col("_at") + 1)))
    gap = F.abs(F.unix_micros(F.col(time).cast("timestamp")) - F.unix_micros(F.col(f"{time}_r").cast("timestamp")))
    return a.join(b, (a[by] == b[f"{by}_r"]) & (a["_bin"] == b["_bin"])).where(gap <= seconds * 1_000_000).drop("_bin", "_at")


def range_join(df: DataFrame, value: str, bands: DataFrame, low: str, high: str) -> DataFrame:
    """Rows with the bands whose [low, high) holds their value; bands are few and go to every task."""
    return df.join(broadcast_if_small(bands, 100_000), (F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def as_of_join(left: DataFrame, right: DataFrame, by: str, time: str, take: str, seconds: int = 86_400) -> DataFrame:
    """Each left row with the right's last `take` (as `last_take`) of the same key at or before its time; no pairs.

    Rows are sorted by key and stretch of time, so a key with many rows is dealt over its stretches; the last value of
    all earlier stretches comes from a table with a row for each key and stretch. Of values at one time the largest is
    taken; a null value is none; null keys are a key, and null times come before all others.
    """
    a = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(right.schema[take].dataType)})
    b = right.select(by, time, F.lit(0).alias("_side"), F.col(take).alias("_v"))
    both = a.unionByName(b, allowMissingColumns=True).withColumn("_part", F.floor(F.unix_timestamp(F.col(time).cast("timestamp")) / seconds))
    within = Window.partitionBy(by, "_part").orderBy(time, "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    own = both.withColumn("_own", F.last("_v", ignorenulls=True).over(within)).where("_side = 1")
    ends = both.groupBy(F.col(by).alias("_by"), F.col("_part").alias("_at")).agg(F.max_by("_v", F.when(F.col("_v").isNotNull(), F.struct(time, "_v"))).alias("_end"))
    earlier = Window.partitionBy("_by").orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
    before = ends.select("_by", "_at", F.last("_end", ignorenulls=True).over(earlier).alias("_before")).where("_before IS NOT NULL")
    met = own.join(before, F.col(by).eqNullSafe(F.col("_by")) & F.col("_part").eqNullSafe(F.col("_at")), "left")
    return met.withColumn(f"last_{take}", F.coalesce("_own", "_before")).drop("_side", "_v", "_part", "_own", "_by", "_at", "_before")


def hash_order(*columns: str) -> Column:
    """A reproducible order for samples that SQL can give too."""
    return F.md5(F.concat_ws("/", *(F.col(c).cast("string") for c in columns)))


def sample_exact(df: DataFrame, n: int, *columns: str) -> DataFrame:
    """n rows in hash order; each task keeps its first n."""
    return df.orderBy(hash_order(*columns), *columns).limit(n)


def sample_each(df: DataFrame, label: str, n: int, *columns: str) -> DataFrame:
    """At most n rows of each label, in hash order; Spark keeps only the first n of a label in each task."""
    order = Window.partitionBy(label).orderBy(hash_order(*columns), *columns)
    return df.withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= n).drop("_rank")
