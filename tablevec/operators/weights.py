"""Weights of nodes, links and non-links from four global ones, and what they say about convexity."""

from __future__ import annotations

import warnings
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Params:
    base: float = 1.0
    column: float = 0.0
    link: float = 3.0
    repel: float = 3.0
    strict: bool = False


#: The settings of the reported tasks.
OBJECTIVE_TASK, SERIES_TASK = Params(1, 0, 3, 3), Params(1, 0, 3, 1)


def degrees(links: DataFrame) -> DataFrame:
    """(rel, rel_inv, src, out_degree) of mirrored links."""
    return links.groupBy("rel", "rel_inv", "src").agg(F.count(F.lit(1)).alias("out_degree"))


def relation_counts(links: DataFrame) -> DataFrame:
    """(src, k): in how many groups, mirrors included, a node is a source."""
    return links.select("src", "rel", "rel_inv").distinct().groupBy("src").agg(F.count(F.lit(1)).alias("k"))


def group_sizes(links: DataFrame) -> DataFrame:
    """(rel, rel_inv, n_src, n_dst, n_links): distinct ends and links of each group."""
    return links.groupBy("rel", "rel_inv").agg(F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"), F.count(F.lit(1)).alias("n_links"))


def group_repulsion(links: DataFrame, params: Params, mc: str = "distinct") -> DataFrame:
    """(rel, rel_inv, n_src, n_dst, repel): the objective's constant of a group, equal for a group and its mirror.

    The weight over the larger number of distinct ends ('distinct'), or over the largest degree ('degree'), times the
    largest k + 1 among the nodes that take part.
    """
    sizes = group_sizes(links)
    most = links.join(relation_counts(links), "src").groupBy("rel").agg(F.max(F.col("k") + 1).alias("mr"))
    if mc == "degree":
        sizes = sizes.join(degrees(links).groupBy("rel").agg(F.max("out_degree").alias("mc")), "rel")
    else:
        sizes = sizes.withColumn("mc", F.greatest("n_src", "n_dst"))
    return sizes.join(most, "rel").select("rel", "rel_inv", "n_src", "n_dst", "n_links", (F.lit(params.repel) / (F.col("mc") * F.col("mr"))).alias("repel"))


def derive_weights(links: DataFrame, params: Params, solver: str, repulsion: str = "centroid", mc: str = "distinct") -> DataFrame:
    """(rel, rel_inv, src, out_degree, k, n_dst, link_w, rep_w) for each node and group that it is a source of.

    For the objective rep_w is the group's constant; for the series it is the weight over the number of distinct
    targets ('centroid') or over the node's links ('outdegree'), and over k + 1.
    """
    rows = degrees(links).join(relation_counts(links), "src")
    link_w = F.lit(params.link) / (F.col("out_degree") * (F.col("k") + 1))
    if solver == "objective":
        groups = group_repulsion(links, params, mc).select("rel", "rel_inv", "n_dst", "repel")
        return rows.join(F.broadcast(groups), ["rel", "rel_inv"]).select("rel", "rel_inv", "src", "out_degree", "k", "n_dst", link_w.alias("link_w"), F.col("repel").alias("rep_w"))
    groups = group_sizes(links).select("rel", "rel_inv", "n_dst")
    per = F.col("n_dst") if repulsion == "centroid" else F.col("out_degree")
    return rows.join(F.broadcast(groups), ["rel", "rel_inv"]).select("rel", "rel_inv", "src", "out_degree", "k", "n_dst", link_w.alias("link_w"), (F.lit(params.repel) / (per * (F.col("k") + 1))).alias("rep_w"))


def convexity_report(nodes: DataFrame, links: DataFrame, params: Params, weights: DataFrame | None = None) -> DataFrame:
    """(node_id, slack_stated, slack_sufficient) for the objective.

    The published condition, 4 base - sum of repulsions of the node's non-links, is not enough; what is enough, by
    diagonal dominance, is base + column share of at least twice the sum of both directions' repulsions.
    """
    w = derive_weights(links, params, "objective") if weights is None else weights
    away = w.groupBy("src").agg(F.sum(F.col("rep_w") * (F.col("n_dst") - F.col("out_degree"))).alias("away"), F.max("k").alias("k"))
    rows = nodes.select("node_id").join(away.withColumnRenamed("src", "node_id"), "node_id", "left").na.fill(0)
    column = F.lit(params.column) / (F.col("k") + 1)
    out = rows.select("node_id", (F.lit(4.0 * params.base) - F.col("away")).alias("slack_stated"), (F.lit(params.base) + column - 4 * F.col("away")).alias("slack_sufficient"))
    return out


def warn_if_unsafe(nodes: DataFrame, links: DataFrame, params: Params, weights: DataFrame | None = None) -> float:
    """The least sufficient slack; raises in strict mode, else warns, if it is negative."""
    if min(params.base, params.column, params.link) < 0:
        raise ValueError("base, column and link weights must not be negative")
    least = convexity_report(nodes, links, params, weights).agg(F.min("slack_sufficient")).first()[0]
    if least is not None and least < 0:
        if params.strict:
            raise ValueError(f"the loss may not be convex: least slack {least:.3g}")
        warnings.warn(f"the loss may not be convex: least slack {least:.3g}", stacklevel=2)
    return 0.0 if least is None else float(least)
