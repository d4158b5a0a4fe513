"""Streams over events, and upkeep of fitted vectors as rows arrive."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec import database as d
from tablevec.operators import solvers
from tablevec.operators.weights import Params
from tablevec.plans.stages import Stages
from tablevec.spec import SchemaSpec


def event_stream(spark: SparkSession, folder: str, files: int = 1) -> DataFrame:
    """The events as a stream of files."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{folder}/events*.parquet")


def drained(stream: DataFrame, mode: str = "append", name: str = "stream") -> DataFrame:
    """Runs a query over all that is there, then stops; its rows, read from where it wrote them."""
    stages = Stages(stream.sparkSession, name)
    out = f"{stages.root}/rows"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{stages.root}/state").trigger(availableNow=True).outputMode("append").start()
    else:

        def put(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(out)

        q = stream.writeStream.foreachBatch(put).option("checkpointLocation", f"{stages.root}/state").trigger(availableNow=True).outputMode("complete").start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out)


def stream_values(stream: DataFrame, table: str, column: str) -> DataFrame:
    """New distinct values of a text column."""
    return stream.where(F.col(column).isNotNull() & (F.col(column) != "")).select(F.lit(f"{table}.{column}").alias("category"), F.col(column).alias("value")).dropDuplicates(["category", "value"])


def windowed_counts(stream: DataFrame, kind: str, late: str | None = None) -> DataFrame:
    """Counts of each event type in tumbling hours, hours that slide by a quarter, or sessions with ten-minute gaps."""
    rows = stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late) if late else stream
    w = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "10 minutes")}[kind]
    return rows.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n")


def running_degrees(stream: DataFrame) -> DataFrame:
    """(src, degree): how many different targets each source of a stream of (src, dst) has had; nulls do not count.

    Pairs are made distinct first, each a key of its own in the state, so no source's targets meet in one place; the
    state of a source is a number.
    """

    def step(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(int(part["dst"].notna().sum()) for part in parts)
        state.update((n,))
        yield pd.DataFrame({"src": [key[0]], "degree": [n]})

    pairs = stream.select("src", "dst").dropDuplicates(["src", "dst"])
    return pairs.groupBy("src").applyInPandasWithState(step, "src string, degree long", "n long", "append", "NoTimeout")


def refresh_vectors(old: d.Database, fitted: DataFrame, frames: dict[str, DataFrame], spec: SchemaSpec, params: Params, sweeps: int, method: str = "objective") -> tuple[d.Database, DataFrame]:
    """The database after changes, and vectors fitted from where the old ones stood.

    Values that stayed start at their old vector, new ones at their start vector. With a convex loss the objective
    reaches the same optimum as a fit from the beginning; nothing such is known of the series.
    """
    new = d.build(fitted.sparkSession, frames, spec, old.lexicon)
    before = old.named(fitted).select("category", "value", F.col("vec").alias("_old"))
    start = new.problem.base.join(before, ["category", "value"], "left").select("node_id", F.coalesce("_old", "vec").alias("vec"))
    start = Stages(fitted.sparkSession, "refresh").keep(start)
    fit = solvers.fit_objective if method == "objective" else solvers.fit_series
    return new, fit(new.problem, params, sweeps, start=start).vectors


def local_sweeps(db: d.Database, fitted: DataFrame, touched: DataFrame, params: Params, sweeps: int = 3, hops: int = 1) -> DataFrame:
    """Vectors after sweeps of the objective over the touched values and those within some links of them.

    All other values keep their vectors; values without one start at their start vector. Weights and group totals are
    those of the whole database.
    """
    stages, p = Stages(fitted.sparkSession, "local"), db.problem
    near = touched
    for _ in range(hops):
        beside = p.links.join(near.select(F.col("node_id").alias("src")), "src", "left_semi").select(F.col("dst").alias("node_id"))
        near = stages.keep(near.union(beside).distinct())
    old = fitted.select("node_id", F.col("vec").alias("_old"))
    x = stages.keep(p.base.join(old, "node_id", "left").select("node_id", F.coalesce("_old", "vec").alias("vec")))
    if near.count() == x.count():  # all values move
        step = solvers.objective_step(p, params)
        return solvers.run(replace(step, strict=params.strict), x, sweeps).vectors
    made = Stages(fitted.sparkSession, "weights")
    step = solvers.objective_step(p, params, made=made)
    least, zeros = step.nodes.agg(F.min("den"), F.coalesce(F.sum((F.col("den") == 0).cast("int")), F.lit(0))).first()
    solvers.check_denominators(least, params.strict)
    nodes = stages.keep(step.nodes.join(near, "node_id", "left_semi"))
    coefs = stages.keep(step.coefs.join(near.select(F.col("node_id").alias("src")), "src", "left_semi"))
    step = replace(step, nodes=nodes, coefs=coefs, push=stages.keep(step.push), targets=stages.keep(step.targets), stuck=zeros > 0)
    made.clear()
    for k in range(sweeps):
        last = stages.made
        x = stages.keep(x.join(nodes.select("node_id"), "node_id", "left_anti").unionByName(solvers.sweep(step, x)))
        if k:
            stages.drop(last)
    return x


def upkeep(stream: DataFrame, old: d.Database, fitted: DataFrame, table: str, params: Params, sweeps: int = 3, hops: int = 1, compact_after: int = 16) -> dict:
    """Takes a stream of new rows of one table; after each batch the touched values are moved. Returns the last state."""
    state = {"db": old, "vectors": fitted, "batches": 0}
    stages = Stages(stream.sparkSession, "upkeep")

    def take(batch: DataFrame, number: int) -> None:
        if batch.isEmpty():
            return
        db, touched = d.extend(state["db"], table, batch)
        state["batches"] += 1
        state["db"] = d.compacted(db) if state["batches"] % compact_after == 0 else db
        state["vectors"] = local_sweeps(state["db"], state["vectors"], touched, params, sweeps, hops)

    stream.writeStream.foreachBatch(take).option("checkpointLocation", f"{stages.root}/state").trigger(availableNow=True).start().awaitTermination()
    return state
