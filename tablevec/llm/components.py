"""Connected components of a link table by star contraction, with each round written to the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tablevec.llm.common import Scratch


def _stars(edges: DataFrame) -> DataFrame:
    """For (a, b) rows: each node's edges in both directions with the smallest node among it and its neighbours."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).union(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
    return both.join(least, "u")


def components(links: DataFrame, scratch: Scratch, name: str = "components", most_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of the links (a, b): the smallest node that it reaches.

    Every round hangs larger neighbours, then smaller ones, below the least node around; the rounds end when all
    edges point at roots, after about the logarithm of the longest path. Aggregates are partial and nothing is
    gathered by node, so hubs are no hot groups.
    """
    edges, before = scratch.keep(links.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"{name}-0"), None
    for k in range(1, most_rounds + 1):
        large = _stars(edges).where(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b")).where(F.col("a") != F.col("b")).distinct()
        down = large.select(F.col("a").alias("u"), F.col("b").alias("v"))
        least = down.groupBy("u").agg(F.min("v").alias("m"))
        joined = down.join(least, "u")
        small = joined.select(F.col("v").alias("a"), F.col("m").alias("b")).union(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
        after = scratch.keep(small.where(F.col("a") != F.col("b")).distinct(), f"{name}-{k}")
        scratch.drop(f"{name}-{k - 1}")
        edges = after
        state = tuple(after.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0))).first())
        if state == before:
            return edges.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("component")).union(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
        before = state
    raise RuntimeError("components did not settle")
