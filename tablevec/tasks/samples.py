"""Samples for trials: reproducible by md5 order, so SQL can draw the same ones."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tablevec.operators.relational import broadcast_if_small, hash_order
from tablevec.plans.stages import Stages

#: Most draws of free pairs that are sent to all tasks.
DRAWS = 200_000


def trials(rows: DataFrame, n: int) -> DataFrame:
    return rows.select("*", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("trial"))


def without_ambiguity(rows: DataFrame, key: str, label: str) -> DataFrame:
    """(key, label): keys that have one label only; holders of several are dropped, nulls are no labels."""
    kept = rows.where(F.col(key).isNotNull() & F.col(label).isNotNull()).groupBy(key).agg(F.min(label).alias(label), F.max(label).alias("_high"))
    return kept.where(F.col(label) == F.col("_high")).select(key, label)


def least(rows: DataFrame, groups: list[str], n: int) -> DataFrame:
    """Rows among which are the first n of each group in the order of _place, a digest of the key, and few others.

    The digests alone are ordered, so keys that are long texts are neither sorted nor sent for the other rows.
    """
    order = Window.partitionBy(*(groups or [F.lit(1)])).orderBy("_place")
    ranked = rows.select(*groups, "_place").withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= n)
    cut = ranked.groupBy(*(F.col(g).alias(f"_{g}") for g in groups)).agg(F.max("_place").alias("_cut"))
    cut = broadcast_if_small(Stages(rows.sparkSession, "cuts").keep(cut), 10_000)
    within = F.col("_place") <= F.col("_cut")
    for g in groups:
        within &= F.col(g).eqNullSafe(F.col(f"_{g}"))
    return rows.join(cut, within).drop("_cut", *(f"_{g}" for g in groups))


def balanced(rows: DataFrame, key: str, label: str, per_class: int | None = None, n_trials: int = 1) -> DataFrame:
    """(trial, split, key, label): the same number of each class in each trial, at most per_class, half for training.

    Without per_class all rows of the smallest class are taken, and as many of each other class.
    Each trial orders the rows of a class anew; Spark keeps only the first ones of a class in each task.
    """
    smallest = rows.groupBy(label).count().agg(F.min("count")).first()[0] or 0
    n = smallest if per_class is None else min(per_class, smallest)
    order = Window.partitionBy("trial", label).orderBy("_place", key)
    dealt = trials(rows, n_trials).withColumn("_place", hash_order("trial", key))
    ranked = (dealt if per_class is None else least(dealt, ["trial", label], n)).withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= n)
    return ranked.select("trial", F.when(F.col("_rank") % 2 == 1, "train").otherwise("test").alias("split"), key, label)


def train_test(rows: DataFrame, key: str, n_train: int, n_test: int, n_trials: int = 1) -> DataFrame:
    """Adds trial and split: the first n_train rows of each trial's order train, the next n_test test."""
    order = Window.partitionBy("trial").orderBy("_place", key)
    dealt = least(trials(rows, n_trials).withColumn("_place", hash_order("trial", key)), ["trial"], n_train + n_test)
    ranked = dealt.withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= n_train + n_test)
    return ranked.select(*rows.columns, "trial", F.when(F.col("_rank") <= n_train, "train").otherwise("test").alias("split"))


def negative_links(links: DataFrame, n: int, seed: int = 1) -> DataFrame:
    """n pairs (src, dst) of participating ends that are not linked; all there are, if they are fewer.

    Both ends are drawn by hash from numbered lists of distinct ends, and linked pairs are dropped by an anti-join; no
    product of the ends is formed. Draws are doubled until the pairs are enough. Pairs come in the order of their first
    draw, so more draws change none of those found before. Null ends are no ends.
    """
    from tablevec.operators.extract import dense_ids

    stages = Stages(links.sparkSession, "free")
    known = stages.keep(links.select("src", "dst").where("src is not null and dst is not null").distinct())
    sources = dense_ids(known.select("src").distinct(), ["src"], "i")
    targets = dense_ids(known.select("dst").distinct(), ["dst"], "j")
    n_src, n_dst, n_known = sources.count(), targets.count(), known.count()
    wanted = min(n, n_src * n_dst - n_known)
    if wanted <= 0:
        return known.limit(0)
    number = lambda tag: F.conv(F.substring(F.md5(F.concat_ws("/", F.lit(str(seed)), F.lit(tag), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
    draws = int(3 * wanted / max(0.02, 1 - n_known / (n_src * n_dst))) + 50
    while True:
        drawn = links.sparkSession.range(draws).select("id", F.pmod(number("s"), F.lit(n_src)).alias("i"), F.pmod(number("t"), F.lit(n_dst)).alias("j"))
        drawn = F.broadcast(drawn) if draws <= DRAWS else drawn
        asked = stages.keep(drawn.join(sources, "i")).join(targets, "j").select("src", "dst", "id")
        near = asked.select(F.xxhash64("src").alias("_digest")).distinct()
        mine = known.withColumn("_digest", F.xxhash64("src")).join(F.broadcast(near) if draws <= DRAWS else near, "_digest", "left_semi").drop("_digest")
        pairs = asked.join(mine, ["src", "dst"], "left_anti")
        found = pairs.groupBy("src", "dst").agg(F.min("id").alias("id")).orderBy("id").limit(wanted)
        if found.count() == wanted:
            return found.select("src", "dst")
        draws *= 2
