"""From a database's tables to a problem that can be fitted, and on to vectors written back."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.operators import extract, lexicon, solvers
from tablevec.operators.weights import Params
from tablevec.plans.stages import Stages, never_broadcast
from tablevec.spec import COMMERCE, SchemaSpec, load_tables

DIMS = 64


@dataclass
class Database:
    frames: dict[str, DataFrame]
    spec: SchemaSpec
    nodes: DataFrame
    links: DataFrame  # by value, without mirrors
    lexicon: DataFrame
    hits: DataFrame
    problem: solvers.Problem

    def named(self, vectors: DataFrame) -> DataFrame:
        """(node_id, category, value, vec)."""
        return self.nodes.join(vectors.select("node_id", "vec"), "node_id")


def stand_in_lexicon(spark: SparkSession, folder: str, with_corpus: bool = False) -> DataFrame:
    frames = {t: spark.read.parquet(f"{folder}/{t}.parquet") for t in ("region", "nation", "part", "customer", "orders", "lineitem")}
    corpus = spark.read.parquet(f"{folder}/documents.parquet").select("text") if with_corpus else None
    return lexicon.lexicon_from_tables(frames, spark.read.parquet(f"{folder}/embeddings.parquet"), corpus)


def build(spark: SparkSession, frames: dict[str, DataFrame], spec: SchemaSpec, words: DataFrame, dims: int = DIMS, matcher: str = "phrases") -> Database:
    """Values, links and start vectors of a database, each written once, so that sweeps read tables, not long plans."""
    stages = Stages(spark, "database")
    words = stages.keep(words)
    nodes = extract.dense_ids(extract.extract_values(frames, spec), ["category", "value"])
    nodes = stages.keep(nodes.select("node_id", "category", "value"))
    links = stages.keep(extract.extract_links(frames, spec))
    base = lexicon.start_vectors(nodes, words, dims) if matcher == "phrases" else None
    if base is None:
        hits = stages.keep(lexicon.match_phrases(nodes, words) if matcher == "phrases" else lexicon.match_tokens(nodes, words))
        base = lexicon.init_vectors(nodes, hits, words, dims)
    else:
        hits = lexicon.match_phrases(nodes, words, "trie")  # read by reports alone, so not written
    base = stages.keep(base)
    numbered = stages.keep(extract.numbered(links, nodes))
    return Database(frames, spec, nodes, links, words, hits, solvers.Problem(base, numbered, dims))


def extend(db: Database, table: str, rows: DataFrame) -> tuple[Database, DataFrame]:
    """The database with new rows of one table, and (node_id) of its new values and of the ends of its new links.

    Only the new rows are read for values, matches, start vectors and links; what is known already is told apart by
    joins, so rows that come twice change nothing. Old values keep their numbers; new ones go on from the largest.
    """
    stages = Stages(rows.sparkSession, "extended")
    rows = stages.keep(rows.select(db.frames[table].columns))
    frames = {**db.frames, table: db.frames[table].unionByName(rows)}
    found = extract.extract_values({table: rows}, db.spec) if db.spec.categories(table) else None
    nodes, hits, base = db.nodes, db.hits, db.problem.base
    touched = db.nodes.select("node_id").limit(0)
    if found is not None:
        fresh = extract.dense_ids(found.join(db.nodes, ["category", "value"], "left_anti"), ["category", "value"])
        top = db.nodes.agg(F.coalesce(F.max("node_id") + 1, F.lit(0))).first()[0]
        fresh = stages.keep(fresh.select((F.col("node_id") + top).alias("node_id"), "category", "value"))
        more = stages.keep(lexicon.match_phrases(fresh, db.lexicon))
        base = base.unionByName(stages.keep(lexicon.init_vectors(fresh, more, db.lexicon, db.problem.dims)))
        nodes, hits, touched = nodes.unionByName(fresh), hits.unionByName(more), fresh.select("node_id")
    names = ["rel", "src_category", "src", "dst_category", "dst"]
    links = extract.links_of_new_rows(frames, table, rows, db.spec).select(names)
    links = stages.keep(links.join(db.links, names, "left_anti"))
    numbered = stages.keep(extract.numbered(links, never_broadcast(nodes)))
    touched = stages.keep(touched.union(numbered.select("src")).distinct())
    # a union drops what its parts say about broadcasts
    problem = solvers.Problem(never_broadcast(base), never_broadcast(db.problem.links.unionByName(numbered)), db.problem.dims, db.problem.include_oov)
    return Database(frames, db.spec, never_broadcast(nodes), db.links.unionByName(links), db.lexicon, hits, problem), touched


def compacted(db: Database) -> Database:
    """The same, with each table written as one; after many small extensions plans are short again."""
    stages = Stages(db.nodes.sparkSession, "database")
    p = db.problem
    problem = solvers.Problem(stages.keep(p.base), stages.keep(p.links), p.dims, p.include_oov)
    return Database(db.frames, db.spec, stages.keep(db.nodes), stages.keep(db.links), db.lexicon, stages.keep(db.hits), problem)


_BUILT: dict[tuple, Database] = {}


def database(spark: SparkSession, folder: str, spec: SchemaSpec = COMMERCE, with_corpus: bool = False) -> Database:
    """A given data set's database; built once in a session for the same files."""
    frames = load_tables(spark, folder, spec)
    files = tuple(sorted(f for df in frames.values() for f in df.inputFiles()))
    key = (files, spark.sparkContext.applicationId, folder, repr(spec.text), spec.keys, spec.links, spec.kinds, spec.excluded_categories, spec.excluded_pairs, with_corpus)
    if key not in _BUILT:
        _BUILT[key] = build(spark, frames, spec, stand_in_lexicon(spark, folder, with_corpus))
    return _BUILT[key]


def fit(db: Database, method: str, params: Params | None = None, iters: int | None = None, **more) -> DataFrame:
    """(node_id, vec) by a method's name: base, objective, series, graph or walks."""
    p = db.problem
    if method == "base":
        return solvers.base_vectors(p)
    if method == "objective":
        return solvers.fit_objective(p, params or Params(1, 0, 3, 3), iters or 10, **more).vectors
    if method == "series":
        return solvers.fit_series(p, params or Params(1, 0, 3, 1), iters or 10, **more).vectors
    if method == "graph":
        return solvers.fit_graph_baseline(p, iters or 20, **more).vectors
    if method == "walks":
        from tablevec.operators.graph import build_unlabelled, fit_walks

        return fit_walks(build_unlabelled(db.nodes, p.links), **more)
    raise ValueError(f"no method {method}")


def save_vectors(db: Database, vectors: DataFrame, path: str) -> None:
    """Vectors beside their values, one folder for each column."""
    db.named(vectors).select("category", "value", "vec").write.mode("overwrite").partitionBy("category").parquet(path)


def run_pipeline(spark: SparkSession, config: dict) -> DataFrame:
    """All steps from a configuration: folder, spec, method, params, iters, and a path to write to if given."""
    db = database(spark, config["folder"], config.get("spec", COMMERCE), config.get("with_corpus", False))
    params = Params(**config["params"]) if "params" in config else None
    vectors = fit(db, config.get("method", "series"), params, config.get("iters"))
    if config.get("path"):
        save_vectors(db, vectors, config["path"])
    return db.named(vectors)


def profile(db: Database) -> DataFrame:
    """(kind, name, n): values by column and links by group."""
    values = db.nodes.groupBy("category").agg(F.count(F.lit(1)).alias("n")).select(F.lit("values").alias("kind"), F.col("category").alias("name"), "n")
    links = db.links.groupBy("rel").agg(F.count(F.lit(1)).alias("n")).select(F.lit("links").alias("kind"), F.col("rel").alias("name"), "n")
    return values.unionByName(links)
