"""Reading tables and writing results."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession

from tablevec.plans.stages import Stages


def load(spark: SparkSession, folder: str, table: str, columns: Sequence[str] = (), predicate: Column | str | None = None) -> DataFrame:
    """A Parquet table with columns and a filter that reach the scan."""
    df = spark.read.parquet(f"{folder}/{table}.parquet")
    df = df if predicate is None else df.where(predicate)
    return df.select(*columns) if columns else df


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.csv(path, schema=schema, header=True)


def read_json_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.json(path, schema=schema)


def read_jdbc(spark: SparkSession, url: str, table: str, **options) -> DataFrame:
    """A table of a database server; needs its driver on the class path. Pass partitionColumn, lowerBound, upperBound and
    numPartitions to read in parallel."""
    return spark.read.format("jdbc").option("url", url).option("dbtable", table).options(**options).load()


def save(df: DataFrame, path: str, partition_by: Sequence[str] = (), mode: str = "errorifexists") -> None:
    """Parquet, in folders by the given columns."""
    writer = df.write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def save_bucketed(df: DataFrame, table: str, buckets: int, by: str, mode: str = "overwrite") -> None:
    """A table bucketed and sorted by a key, so that repeated joins on the key, as in sweeps, need no exchange of it."""
    df.write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(table)


def round_trip(df: DataFrame, kind: str, **options) -> DataFrame:
    """Writes in a format and reads back with the same schema."""
    stages = Stages(df.sparkSession, "trip")
    df.write.format(kind).options(**options).save(f"{stages.root}/{kind}")
    return df.sparkSession.read.format(kind).schema(df.schema).options(**options).load(f"{stages.root}/{kind}")


def partitioned_round_trip(df: DataFrame, by: str) -> DataFrame:
    stages = Stages(df.sparkSession, "trip")
    save(df, f"{stages.root}/parts", [by])
    return df.sparkSession.read.parquet(f"{stages.root}/parts").select(*df.columns)
