"""The property graph of values and columns, and vectors from random walks on it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tablevec.functions.vectors import vec_scale, vec_unit
from tablevec.operators.extract import dense_ids
from tablevec.operators.relational import broadcast_if_small
from tablevec.operators.skipgram import fit_skipgram, numbering
from tablevec.plans.stages import Stages

#: Most vertices whose vectors Spark's skip-gram holds on the driver, and neighbours of a vertex in one row.
MODEL_VERTICES, PLACES = 100_000, 1024


def build_graph(nodes: DataFrame, links: DataFrame) -> tuple[DataFrame, DataFrame]:
    """vertices (vertex, kind) and edges (src, dst, label), both ways: links, and each value to its column's blank vertex.

    Values have their node ids as text; the blank vertex of a column has the column's name.
    """
    values = nodes.select(F.col("node_id").cast("string").alias("vertex"), F.lit("value").alias("kind"))
    blanks = nodes.select("category").distinct().select(F.col("category").alias("vertex"), F.lit("column").alias("kind"))
    typed = links.select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"), F.col("rel").alias("label"))
    mine = nodes.select(F.col("node_id").cast("string").alias("src"), F.col("category").alias("dst"))
    member = F.struct("src", "dst", F.lit("category").alias("label")), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit("category").alias("label"))
    return values.union(blanks), typed.unionByName(mine.select(F.explode(F.array(*member)).alias("e")).select("e.*")).distinct()


def build_unlabelled(nodes: DataFrame, links: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The same vertices, and edges (src, dst), each once: walks read no labels. Numbers are made distinct, not texts."""
    vertices, _ = build_graph(nodes, links)
    typed = links.select("src", "dst").distinct().select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst"))
    mine = nodes.select(F.col("node_id").cast("string").alias("a"), F.col("category").alias("b"))
    member = F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))
    return vertices, typed.unionByName(mine.select(F.explode(F.array(*member)).alias("e")).select("e.*"))


def places(edges: DataFrame, stages: Stages) -> tuple[DataFrame, DataFrame]:
    """Of edges with labels, or of (src, dst) that are distinct: (_many, _degree) of vertices with more than PLACES neighbours, and (vertex, part, next): neighbours in order.

    Each row holds PLACES of a vertex's neighbours, so a walk's next step is found by a join on few rows and no row has to
    hold all neighbours of a hub. The hubs' neighbours alone are sorted over all tasks.
    """
    pairs = stages.keep(edges.select("src", "dst").distinct() if "label" in edges.columns else edges)
    many = stages.keep(pairs.groupBy(F.col("src").alias("_many")).agg(F.count(F.lit(1)).alias("_degree")).where(F.col("_degree") > PLACES))
    many = broadcast_if_small(many)
    few = pairs.join(many, F.col("src") == F.col("_many"), "left_anti").groupBy(F.col("src").alias("vertex")).agg(F.array_sort(F.collect_list("dst")).alias("next"))
    numbered = stages.keep(dense_ids(pairs.join(many, F.col("src") == F.col("_many"), "left_semi"), ["src", "dst"], "_place"))
    firsts = broadcast_if_small(stages.keep(numbered.groupBy(F.col("src").alias("vertex")).agg(F.min("_place").alias("_first"))))
    at = (F.col("_place") - F.col("_first")).alias("_at")
    dealt = numbered.withColumnRenamed("src", "vertex").join(firsts, "vertex").select("vertex", at, "dst")
    parts = dealt.groupBy("vertex", F.floor(F.col("_at") / PLACES).alias("part")).agg(F.array_sort(F.collect_list(F.struct("_at", "dst")))["dst"].alias("next"))
    around = few.select("vertex", F.lit(0).cast("long").alias("part"), "next").unionByName(parts)
    return many, stages.keep(around)


def walks(graph: tuple[DataFrame, DataFrame], per_node: int = 10, length: int = 40, seed: int = 1) -> DataFrame:
    """(walk_id, path): truncated random walks from every vertex.

    A step goes to the neighbour that an md5 of seed, walk and step picks, so walks are the same however the data are
    dealt. Each step is one join on the walks' heads and the numbers drawn, and is written.
    """
    vertices, edges = graph
    stages = Stages(vertices.sparkSession, "walks")
    many, around = places(edges, stages)
    now = vertices.select(F.explode(F.sequence(F.lit(0), F.lit(per_node - 1))).alias("_n"), F.col("vertex").alias("head")).select(F.concat_ws("#", "head", F.col("_n").cast("string")).alias("walk_id"), F.array("head").alias("path"), "head")
    for step in range(1, length):
        drawn = F.conv(F.substring(F.md5(F.concat_ws("/", F.lit(str(seed)), "walk_id", F.lit(str(step)))), 1, 8), 16, 10).cast("long")
        asked = now.select("*", drawn.alias("_drawn")).join(many, F.col("head") == F.col("_many"), "left")
        asked = asked.withColumn("_at", F.when(F.col("_degree").isNotNull(), F.pmod("_drawn", "_degree")))
        asked = asked.withColumn("_part", F.coalesce(F.floor(F.col("_at") / PLACES), F.lit(0)))
        moved = asked.join(around, (asked["head"] == around["vertex"]) & (asked["_part"] == around["part"]), "left")
        next_ = F.get("next", F.when(F.col("_at").isNotNull(), F.col("_at") % PLACES).otherwise(F.pmod("_drawn", F.size("next"))).cast("int"))
        moved = moved.select("walk_id", "path", "head", next_.alias("_next"))
        now = moved.select("walk_id", F.when(F.col("_next").isNull(), F.col("path")).otherwise(F.array_append("path", F.col("_next"))).alias("path"), F.coalesce("_next", "head").alias("head"))
        if step % 8 == 0:
            now = stages.keep(now)
    return now.select("walk_id", "path")


def fit_walks(graph: tuple[DataFrame, DataFrame], per_node: int = 10, length: int = 40, window: int = 5, dim: int = 64, seed: int = 1, rounds: int = 1, parts: int = 8) -> DataFrame:
    """(node_id, vec) of the values by walks and skip-gram.

    Up to MODEL_VERTICES this is Spark's skip-gram, whose whole model is on the driver and in every task. It is trained on
    `parts` parts of the paths, dealt by the hash of the walk, whatever the machine; each round averages them, so more
    parts want more rounds. Above, it is trained by blocks.
    """
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    vertices = graph[0]
    many = numbering(vertices) if vertices.count() > MODEL_VERTICES else None
    if many is not None:
        return fit_skipgram(walks(graph, per_node, length, seed), *many, window, dim, seed, rounds)
    paths = walks(graph, per_node, length, seed).repartition(parts, "walk_id").sortWithinPartitions("walk_id").select("path")
    model = Word2Vec(vectorSize=dim, windowSize=window, minCount=1, seed=seed, maxIter=rounds, inputCol="path", outputCol="out", numPartitions=parts).fit(paths)
    found = model.getVectors().select(F.col("word").alias("vertex"), vector_to_array("vector").alias("vec"))
    return found.where(F.col("vertex").rlike(r"^\d+$")).select(F.col("vertex").cast("long").alias("node_id"), "vec")


def unit_vectors(x: DataFrame) -> DataFrame:
    return x.select("node_id", vec_unit("vec").alias("vec"))


def combine_vectors(a: DataFrame, b: DataFrame, mode: str = "concat") -> DataFrame:
    """Two sets of vectors as one: 'concat', or 'average' or 'sum' for equal dimensions."""
    both = a.select("node_id", F.col("vec").alias("x")).join(b.select("node_id", F.col("vec").alias("y")), "node_id")
    added = F.zip_with("x", "y", lambda u, v: u + v)
    made = {"concat": F.concat("x", "y"), "sum": added, "average": vec_scale(added, F.lit(0.5))}[mode]
    return both.select("node_id", made.alias("vec"))


def nearest_values(named: DataFrame, value: str, k: int, category: str | None = None, of: str | None = None) -> DataFrame:
    """(category, value, cosine): the k values with the largest cosine to a value, other than itself.

    The value's vectors, one for each column it is in, go to every task; the rows are scanned once.
    """
    asked = named.where(F.col("value") == value)
    if of:
        asked = asked.where(F.col("category") == of)
    q = asked.select(F.col("node_id").alias("_q"), vec_unit("vec").alias("_v"))
    rows = named if category is None else named.where(F.col("category") == category)
    dot = F.aggregate(F.zip_with(vec_unit("vec"), "_v", lambda u, v: u * v), F.lit(0.0), lambda s, e: s + e)
    found = rows.join(F.broadcast(q), F.col("node_id") != F.col("_q")).select("category", "value", dot.alias("cosine"))
    return found.groupBy("category", "value").agg(F.max("cosine").alias("cosine")).orderBy(F.desc(F.round("cosine", 9)), "category", "value").limit(k)


def approximate_nearest(named: DataFrame, vector: list[float], k: int, bucket: float = 0.5, tables: int = 8, seed: int = 1) -> DataFrame:
    """The same by locality-sensitive hashing of unit vectors; may miss some."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.linalg import Vectors

    rows = named.select("category", "value", array_to_vector(vec_unit("vec")).alias("v"))
    q = np.array(vector) / max(np.linalg.norm(vector), 1e-12)
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=bucket, numHashTables=tables, seed=seed).fit(rows)
    return model.approxNearestNeighbors(rows, Vectors.dense(q), k).select("category", "value", (1 - F.col("distCol") ** 2 / 2).alias("cosine"))


def analogy(named: DataFrame, a: str, b: str, c: str, k: int = 5) -> DataFrame:
    """Values nearest to b - a + c."""
    found = {r["value"]: np.array(r["vec"]) for r in named.where(F.col("value").isin(a, b, c)).select("value", "vec").collect()}
    target = found[b] - found[a] + found[c]
    target = (target / max(np.linalg.norm(target), 1e-12)).tolist()
    dot = F.aggregate(F.zip_with(vec_unit("vec"), F.array(*map(F.lit, target)), lambda u, v: u * v), F.lit(0.0), lambda s, e: s + e)
    return named.where(~F.col("value").isin(a, b, c)).select("category", "value", dot.alias("cosine")).orderBy(F.desc("cosine"), "category", "value").limit(k)


def clusters(named: DataFrame, k: int, seed: int = 1) -> DataFrame:
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = named.select("category", "value", array_to_vector(vec_unit("vec")).alias("features"))
    return KMeans(k=k, seed=seed).fit(rows).transform(rows).select("category", "value", F.col("prediction").alias("cluster"))


def score_all(vectors: DataFrame, weights: list[tuple[np.ndarray, np.ndarray]]) -> DataFrame:
    """(node_id, score): a trained network's first output for all nodes; sigmoid layers, weights sent to every task."""
    shared = vectors.sparkSession.sparkContext.broadcast(weights)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = np.array(b.column(1).to_pylist(), dtype=float)
                for w, bias in shared.value:
                    x = 1 / (1 + np.exp(-(x @ w + bias)))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x[:, 0])], names=["node_id", "score"])

    return vectors.select("node_id", "vec").mapInArrow(work, "node_id long, score double")
