"""The experiments, on the given tables. Sizes default to what a small data set can give; all are parameters."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec import database as d
from tablevec.functions.vectors import vec_unit
from tablevec.operators import extract, graph, solvers
from tablevec.operators.relational import broadcast_if_small
from tablevec.operators.weights import OBJECTIVE_TASK, SERIES_TASK, Params
from tablevec.plans.stages import Stages
from tablevec.spec import COMMERCE, SchemaSpec, load_tables
from tablevec.tasks import nets, samples, scores

METHODS = ("base", "graph", "objective", "series")
#: Small networks for quick runs; pass nets.BINARY and so on for the published widths.
QUICK = nets.Settings((64,), rate=1e-2, l2=1e-5, max_epochs=150, patience=40)
QUICK_LINK = nets.Settings((48, 24), rate=5e-3, l2=1e-5, max_epochs=150, patience=40)
QUICK_NUMBER = nets.Settings((64, 64, 32, 32), rate=1e-3, max_epochs=60, patience=15)
QUICK_WALKS = {"per_node": 5, "length": 12, "rounds": 2}
DOCUMENTS = SchemaSpec({"documents": ("text", "lang", "source")})


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


#: Most values of a sample that are sent to all tasks.
SAMPLE_VALUES = 100_000


def sample_nodes(rows: DataFrame, db: d.Database, category: str, name: str = "item") -> DataFrame:
    """(node_id, item): the nodes of a category's values that rows hold.

    Rows are a bounded sample, so values that it lacks are told by digests where they lie; none of their texts moves.
    """
    asked = rows.select(name).distinct()
    digests = broadcast_if_small(asked.select(F.xxhash64(name).alias("_digest")).distinct(), SAMPLE_VALUES)
    nodes = db.nodes.where(F.col("category") == category).select("node_id", F.col("value").alias(name), F.xxhash64("value").alias("_digest"))
    return nodes.join(digests, "_digest", "left_semi").drop("_digest").join(asked, name)


def _of_nodes(x: DataFrame, nodes: DataFrame) -> DataFrame:
    """The vectors of these nodes; all others stay where they lie."""
    return x.join(broadcast_if_small(nodes.select("node_id").distinct(), SAMPLE_VALUES), "node_id", "left_semi")


def method_vectors(db: d.Database, methods: tuple[str, ...], walks: dict | None = None, params: dict[str, Params] | None = None, of: tuple[tuple[DataFrame, str], ...] = ()) -> DataFrame:
    """(method, node_id, vec), scaled to length 1. 'm+walks' is a method's vectors with walk vectors appended.

    With `of`, pairs of a sample with item and the category of its items, only the vectors of these values are returned.
    """
    params = {"objective": OBJECTIVE_TASK, "series": SERIES_TASK} | (params or {})
    stages, made = Stages(db.nodes.sparkSession, "methods"), {}
    wanted = stages.keep(_union([sample_nodes(rows, db, c).select("node_id") for rows, c in of])) if of else None

    def get(name: str) -> DataFrame:
        if name not in made:
            if "+" in name:
                a, b = name.split("+")
                x = graph.combine_vectors(graph.unit_vectors(get(a)), graph.unit_vectors(get(b)))
            else:
                more = (walks or QUICK_WALKS) if name == "walks" else {}
                x = d.fit(db, name, params.get(name), **more)
                x = x if wanted is None else _of_nodes(x, wanted)
            made[name] = stages.keep(x.select("node_id", "vec"))
        return made[name]

    return _union([get(m).select(F.lit(m).alias("method"), "node_id", vec_unit("vec").alias("features")) for m in methods])


def _with_vectors(rows: DataFrame, db: d.Database, category: str, vectors: DataFrame) -> DataFrame:
    """rows (item is a value of the category) with each method's features."""
    stages = Stages(db.nodes.sparkSession, "sample")
    nodes = stages.keep(sample_nodes(rows, db, category))
    return rows.join(nodes, "item").join(stages.keep(_of_nodes(vectors, nodes)), "node_id").drop("node_id")


def region_labels(frames_of: SparkSession, folder: str) -> DataFrame:
    """(item, label): customers by whether they are in America, from the withheld region column; ambiguous ones dropped."""
    t = {n: frames_of.read.parquet(f"{folder}/{n}.parquet") for n in ("customer", "nation", "region")}
    rows = t["customer"].join(broadcast_if_small(t["nation"]), F.col("c_nationkey") == F.col("n_nationkey")).join(broadcast_if_small(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"))
    return samples.without_ambiguity(rows.select(F.col("c_name").alias("item"), F.when(F.col("r_name") == "AMERICA", "yes").otherwise("no").alias("label")), "item", "label")


def run_binary(spark: SparkSession, folder: str, methods=METHODS, per_class: int = 3000, n_trials: int = 3, settings=QUICK, vectors: DataFrame | None = None) -> DataFrame:
    """Accuracy of telling customers of one region, whose column is withheld before any extraction."""
    db = d.database(spark, folder, COMMERCE.without("region.r_name"))
    drawn = Stages(spark, "labels").keep(samples.balanced(region_labels(spark, folder), "item", "label", per_class, n_trials))
    x = vectors if vectors is not None else method_vectors(db, methods, of=((drawn, "customer.c_name"),))
    return scores.accuracy(scores.predict(_with_vectors(drawn, db, "customer.c_name", x), "binary", settings), "binary_region")


def run_document_labels(spark: SparkSession, folder: str, label: str, methods=METHODS, per_class: int = 3000, n_trials: int = 3, settings=QUICK) -> DataFrame:
    """Accuracy of telling documents by a label from outside the database; texts of several labels are left out."""
    db = d.database(spark, folder, DOCUMENTS, True)
    known = spark.read.parquet(f"{folder}/labels.parquet").select("doc_id", F.col(label).cast("string").alias("label"))
    texts = spark.read.parquet(f"{folder}/documents.parquet").where("text != ''").select("doc_id", F.col("text").alias("item"))
    labels = samples.without_ambiguity(texts.join(known, "doc_id"), "item", "label")
    stages = Stages(spark, "labels")
    drawn = stages.keep(samples.balanced(stages.keep(labels), "item", "label", per_class, n_trials))
    x = method_vectors(db, methods, of=((drawn, "documents.text"),))
    return scores.accuracy(scores.predict(_with_vectors(drawn, db, "documents.text", x), "binary", settings), f"binary_{label}")


def run_sample_sizes(spark: SparkSession, folder: str, sizes=(50, 100, 200), n_test: int = 200, n_trials: int = 3, methods=METHODS, settings=QUICK) -> DataFrame:
    """Accuracy by the number of training rows, two thirds of all rows at most."""
    db = d.database(spark, folder, COMMERCE.without("region.r_name"))
    x, out, labels = method_vectors(db, methods), [], region_labels(spark, folder)
    most = labels.count() * 2 // 3
    for n in sorted({min(n, most) for n in sizes}):
        rows = samples.train_test(labels, "item", n, n_test, n_trials)
        out.append(scores.accuracy(scores.predict(_with_vectors(rows, db, "customer.c_name", x), "binary", settings), f"binary_region_{n}"))
    return _union(out)


def text_labels(spark: SparkSession, folder: str, column: str) -> DataFrame:
    return samples.without_ambiguity(spark.read.parquet(f"{folder}/documents.parquet").where("text != ''").select(F.col("text").alias("item"), F.col(column).cast("string").alias("label")), "item", "label")


def document_columns(spark: SparkSession, folder: str, *columns: str) -> DataFrame:
    """(item, more): each text of documents with other text columns of its rows, the smallest value of each, in one string."""
    rows = spark.read.parquet(f"{folder}/documents.parquet").where("text != ''").groupBy(F.col("text").alias("item")).agg(*(F.min(c).alias(f"_{c}") for c in columns))
    return rows.select("item", F.concat_ws(" ", *(F.col(f"_{c}") for c in columns)).alias("more"))


def _imputed(spark: SparkSession, db: d.Database, labels: DataFrame, category: str, task: str, n_train: int, n_test: int, n_trials: int, methods, settings, ngram: str | None, more: DataFrame | None = None) -> DataFrame:
    stages = Stages(spark, "imputation")
    labels = stages.keep(labels)
    known = labels.count()
    n_train, n_test = min(n_train, known // 2), min(n_test, known // 2)
    rows = stages.keep(samples.train_test(labels, "item", n_train, n_test, n_trials))
    got = scores.predict(_with_vectors(rows, db, category, method_vectors(db, methods, of=((rows, category),))), "categories", settings)
    mode = rows.where("split = 'test'").join(scores.impute_mode(rows, "label"), "trial").select(F.lit("mode").alias("method"), "trial", "item", "label", "pred")
    out = got.unionByName(mode)
    if ngram:
        read = rows.withColumn("text", F.col("item")) if more is None else rows.join(more, "item", "left").withColumn("text", F.concat_ws(" ", "item", "more"))
        out = out.unionByName(scores.impute_ngram(read, "text", "label", ngram))
    return scores.accuracy(out, task)


def run_imputation(spark: SparkSession, folder: str, column: str = "lang", n_train: int = 5000, n_test: int = 5000, n_trials: int = 2, methods=METHODS, settings=QUICK, ngram: str | None = "linear", beside: tuple[str, ...] = ()) -> DataFrame:
    """Accuracy of imputing a documents column, withheld before extraction: vectors, mode and n-grams.

    The n-grams are of the text, and of the columns `beside` it in the same table if any are given.
    """
    db = d.database(spark, folder, DOCUMENTS.without(f"documents.{column}"), True)
    more = document_columns(spark, folder, *beside) if beside else None
    return _imputed(spark, db, text_labels(spark, folder, column), "documents.text", f"impute_{column}", n_train, n_test, n_trials, methods, settings, ngram, more)


def supplier_regions(spark: SparkSession, folder: str) -> DataFrame:
    """(item, label): suppliers and the regions of their nations; ambiguous ones dropped."""
    t = {n: spark.read.parquet(f"{folder}/{n}.parquet") for n in ("supplier", "nation", "region")}
    rows = t["supplier"].join(broadcast_if_small(t["nation"]), F.col("s_nationkey") == F.col("n_nationkey")).join(broadcast_if_small(t["region"]), F.col("n_regionkey") == F.col("r_regionkey"))
    return samples.without_ambiguity(rows.select(F.col("s_name").alias("item"), F.col("r_name").alias("label")), "item", "label")


def part_types(spark: SparkSession, folder: str) -> DataFrame:
    """(item, label): part names and the most frequent of their types, the smallest of equals; a name has many types."""
    rows = spark.read.parquet(f"{folder}/part.parquet").where("p_name != '' and p_type != ''").groupBy("p_name", "p_type").agg(F.count(F.lit(1)).alias("n"))
    return rows.groupBy(F.col("p_name").alias("item")).agg(F.min(F.struct((-F.col("n")).alias("n"), "p_type"))["p_type"].alias("label"))


def run_supplier_regions(spark: SparkSession, folder: str, n_train: int = 400, n_test: int = 400, n_trials: int = 2, methods=METHODS, settings=QUICK, ngram: str | None = "linear") -> DataFrame:
    """Accuracy of imputing the region of suppliers, with the region column withheld."""
    db = d.database(spark, folder, COMMERCE.without("region.r_name"))
    return _imputed(spark, db, supplier_regions(spark, folder), "supplier.s_name", "impute_supplier_region", n_train, n_test, n_trials, methods, settings, ngram)


def run_part_types(spark: SparkSession, folder: str, n_train: int = 400, n_test: int = 400, n_trials: int = 2, methods=METHODS, settings=QUICK, ngram: str | None = "linear") -> DataFrame:
    """Accuracy of imputing the type of part names, with the type column withheld; types are dealt at random."""
    db = d.database(spark, folder, COMMERCE.without("part.p_type"))
    return _imputed(spark, db, part_types(spark, folder), "part.p_name", "impute_part_type", n_train, n_test, n_trials, methods, settings, ngram)


def _regressed(spark: SparkSession, db: d.Database, rows: DataFrame, category: str, task: str, n_train: int, n_test: int, n_trials: int, methods, settings) -> DataFrame:
    stages = Stages(spark, "regression")
    rows = stages.keep(rows)
    known = rows.count()
    n_train, n_test = min(n_train, known * 9 // 10), min(n_test, max(known // 10, 1))
    drawn = stages.keep(samples.train_test(rows, "item", n_train, n_test, n_trials))
    got = scores.predict(_with_vectors(drawn, db, category, method_vectors(db, methods, of=((drawn, category),))), "regression", settings)
    middle = drawn.where("split = 'train'").groupBy("trial").agg(F.percentile("label", 0.5).cast("string").alias("pred"))
    median = drawn.where("split = 'test'").join(middle, "trial").select(F.lit("median").alias("method"), "trial", "item", F.col("label").cast("string").alias("label"), "pred")
    return scores.mean_abs_error(got.unionByName(median), task)


def run_regression(spark: SparkSession, folder: str, n_train: int = 9000, n_test: int = 1000, n_trials: int = 2, methods=METHODS, settings=QUICK_NUMBER) -> DataFrame:
    """Mean absolute error of the log length of documents, beside the training median's."""
    db = d.database(spark, folder, DOCUMENTS, True)
    rows = spark.read.parquet(f"{folder}/documents.parquet").where("text != ''").groupBy(F.col("text").alias("item")).agg(F.ln(1 + F.max("n_chars")).alias("label"))
    return _regressed(spark, db, rows, "documents.text", "regress_length", n_train, n_test, n_trials, methods, settings)


def _exact_sum(column: str) -> Column:
    """A sum that does not depend on the order of the rows, so labels are the same in every run."""
    return F.sum(F.col(column).cast("decimal(24,6)"))


def customer_totals(spark: SparkSession, folder: str) -> DataFrame:
    """(item, label): customers with orders, and the mean total price of these."""
    orders = spark.read.parquet(f"{folder}/orders.parquet").groupBy("o_custkey").agg(_exact_sum("o_totalprice").alias("s"), F.count("o_totalprice").alias("n"))
    customers = spark.read.parquet(f"{folder}/customer.parquet").where("c_name != ''")
    rows = customers.join(orders, F.col("c_custkey") == F.col("o_custkey")).groupBy(F.col("c_name").alias("item")).agg(F.sum("s").alias("s"), F.sum("n").alias("n"))
    return rows.where("n > 0").select("item", (F.col("s").cast("double") / F.col("n")).alias("label"))


def part_prices(spark: SparkSession, folder: str) -> DataFrame:
    """(item, label): part names and the mean of their retail prices."""
    rows = spark.read.parquet(f"{folder}/part.parquet").where("p_name != '' and p_retailprice is not null")
    return rows.groupBy(F.col("p_name").alias("item")).agg((_exact_sum("p_retailprice").cast("double") / F.count(F.lit(1))).alias("label"))


def run_customer_totals(spark: SparkSession, folder: str, n_train: int = 9000, n_test: int = 1000, n_trials: int = 2, methods=METHODS, settings=QUICK_NUMBER) -> DataFrame:
    """Mean absolute error of the mean order total of customers; totals are random, so the median is as good."""
    return _regressed(spark, d.database(spark, folder, COMMERCE), customer_totals(spark, folder), "customer.c_name", "regress_customer_total", n_train, n_test, n_trials, methods, settings)


def run_part_prices(spark: SparkSession, folder: str, n_train: int = 9000, n_test: int = 1000, n_trials: int = 2, methods=METHODS, settings=QUICK_NUMBER) -> DataFrame:
    """Mean absolute error of the mean price of part names; a data set has 64 names, so this is a small one."""
    return _regressed(spark, d.database(spark, folder, COMMERCE), part_prices(spark, folder), "part.p_name", "regress_part_price", n_train, n_test, n_trials, methods, settings)


def _link_scores(spark: SparkSession, db: d.Database, yes: DataFrame, src: str, dst: str, task: str, n_each: int, n_trials: int, methods, settings) -> DataFrame:
    """Accuracy of telling links (src, dst) between values of two categories from non-links, half of each drawn for training."""
    stages = Stages(spark, "links")
    yes = stages.keep(yes.distinct())
    pairs = yes.agg(F.countDistinct("src").alias("a"), F.countDistinct("dst").alias("b"), F.count(F.lit(1)).alias("n")).first()
    n = min(n_each, pairs["n"], pairs["a"] * pairs["b"] - pairs["n"])
    no = samples.negative_links(yes, n)
    first = samples.least(yes.withColumn("_place", F.md5("src")), [], n)
    rows = stages.keep(first.orderBy("_place", F.md5("dst")).limit(n).drop("_place").withColumn("label", F.lit("yes")).unionByName(no.withColumn("label", F.lit("no"))).withColumn("item", F.concat_ws("|", F.md5("src"), "dst")))
    half = rows.count() // 2
    drawn = samples.train_test(rows, "item", half, half, n_trials)
    x = method_vectors(db, methods, of=tuple((rows.select(F.col(tag).alias("item")), c) for tag, c in (("src", src), ("dst", dst))))
    ids = lambda c, tag: stages.keep(sample_nodes(rows, db, c, tag)).withColumnRenamed("node_id", f"{tag}_id")
    a = x.select("method", F.col("node_id").alias("src_id"), F.col("features").alias("fa"))
    b = x.select("method", F.col("node_id").alias("dst_id"), F.col("features").alias("fb"))
    both = drawn.join(ids(src, "src"), "src").join(ids(dst, "dst"), "dst").join(a, "src_id").join(b, ["method", "dst_id"])
    return scores.accuracy(scores.predict(both.select("method", "trial", "split", "item", F.concat("fa", "fb").alias("features"), "label"), "link", settings), task)


def run_links(spark: SparkSession, folder: str, n_each: int = 5000, n_trials: int = 2, methods=METHODS, settings=QUICK_LINK) -> DataFrame:
    """Accuracy of telling links of text and language from non-links, with that relation withheld."""
    db = d.database(spark, folder, DOCUMENTS.without(relation=("documents.text", "documents.lang")), True)
    docs = spark.read.parquet(f"{folder}/documents.parquet").where("text != '' and lang != ''")
    return _link_scores(spark, db, docs.select(F.col("text").alias("src"), F.col("lang").alias("dst")), "documents.text", "documents.lang", "link_text_lang", n_each, n_trials, methods, settings)


def run_customer_part_links(spark: SparkSession, folder: str, n_each: int = 5000, n_trials: int = 2, methods=METHODS, settings=QUICK_LINK) -> DataFrame:
    """Accuracy of telling which part names a customer ordered; no declared relation holds these links, and they are random."""
    read = lambda t: spark.read.parquet(f"{folder}/{t}.parquet")
    ties = read("lineitem").select("l_orderkey", "l_partkey").join(read("orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_partkey").distinct()
    named = ties.join(read("customer").where("c_name != ''"), F.col("o_custkey") == F.col("c_custkey")).join(read("part").where("p_name != ''"), F.col("l_partkey") == F.col("p_partkey"))
    return _link_scores(spark, d.database(spark, folder, COMMERCE), named.select(F.col("c_name").alias("src"), F.col("p_name").alias("dst")), "customer.c_name", "part.p_name", "link_customer_part", n_each, n_trials, methods, settings)


def run_part_brand_links(spark: SparkSession, folder: str, n_each: int = 5000, n_trials: int = 2, methods=METHODS, settings=QUICK_LINK) -> DataFrame:
    """Accuracy of telling which brands a part name has, with that relation withheld."""
    db = d.database(spark, folder, COMMERCE.without(relation=("part.p_name", "part.p_brand")))
    parts = spark.read.parquet(f"{folder}/part.parquet").where("p_name != '' and p_brand != ''")
    return _link_scores(spark, db, parts.select(F.col("p_name").alias("src"), F.col("p_brand").alias("dst")), "part.p_name", "part.p_brand", "link_part_brand", n_each, n_trials, methods, settings)


def _grid_vectors(spark: SparkSession, db: d.Database, grid: list[Params], solver: str, walks: bool, of: tuple[DataFrame, str] | None = None) -> DataFrame:
    """(method, node_id, features) for each setting; with walks, walk vectors are fitted once and appended to each.

    With `of`, a sample with item and the category of its items, only for these values.
    """
    stages, out = Stages(spark, "grid"), []
    wanted = stages.keep(sample_nodes(of[0], db, of[1]).select("node_id")) if of else None
    beside = stages.keep(graph.unit_vectors(d.fit(db, "walks", **QUICK_WALKS))) if walks else None
    for p in grid:
        x = graph.unit_vectors(d.fit(db, solver, p, iters=6))
        x = x if wanted is None else _of_nodes(x, wanted)
        x = x if beside is None else graph.combine_vectors(x, beside)
        name = f"{solver}({p.base:g},{p.column:g},{p.link:g},{p.repel:g})" + ("+walks" if walks else "")
        out.append(x.select(F.lit(name).alias("method"), "node_id", vec_unit("vec").alias("features")))
    return stages.keep(_union(out))


def grid_search(spark: SparkSession, folder: str, grid: list[Params], solver: str = "series", n_trials: int = 2, settings=QUICK, walks: bool = False) -> DataFrame:
    """Accuracy of the region task for each setting of the weights; links and samples are shared."""
    db = d.database(spark, folder, COMMERCE.without("region.r_name"))
    return run_binary(spark, folder, n_trials=n_trials, settings=settings, vectors=_grid_vectors(spark, db, grid, solver, walks))


def grid_search_imputation(spark: SparkSession, folder: str, grid: list[Params], solver: str = "series", n_train: int = 5000, n_test: int = 5000, n_trials: int = 2, settings=QUICK, walks: bool = False) -> DataFrame:
    """Accuracy of imputing the language of documents for each setting of the weights."""
    db = d.database(spark, folder, DOCUMENTS.without("documents.lang"), True)
    stages = Stages(spark, "imputation")
    labels = stages.keep(text_labels(spark, folder, "lang"))
    known = labels.count()
    rows = stages.keep(samples.train_test(labels, "item", min(n_train, known // 2), min(n_test, known // 2), n_trials))
    x = _grid_vectors(spark, db, grid, solver, walks, (rows, "documents.text"))
    return scores.accuracy(scores.predict(_with_vectors(rows, db, "documents.text", x), "categories", settings), "impute_lang")


def run_ablation(spark: SparkSession, folder: str, kinds=("row", "fk", "nm"), settings=QUICK) -> DataFrame:
    """The region task with links of some kinds left out."""
    out, labels = [], region_labels(spark, folder)
    for left_out in (None, *kinds):
        spec = COMMERCE.without("region.r_name")
        spec = spec if left_out is None else spec.only(*(k for k in kinds if k != left_out))
        db = d.database(spark, folder, spec)
        x = d.fit(db, "series", SERIES_TASK).select(F.lit(f"without_{left_out}" if left_out else "all").alias("method"), "node_id", vec_unit("vec").alias("features"))
        drawn = samples.balanced(labels, "item", "label", 1000, 2)
        out.append(scores.accuracy(scores.predict(_with_vectors(drawn, db, "customer.c_name", x), "binary", settings), "ablation"))
    return _union(out)


def run_runtime(spark: SparkSession, folder: str, methods=METHODS, repeats: int = 3, spec: SchemaSpec = COMMERCE) -> list[dict]:
    """Seconds of fitting each method on a built database: mean and deviation."""
    db, out = d.database(spark, folder, spec), []
    for m in methods:
        took = scores.timed(lambda m=m: d.fit(db, m, **(QUICK_WALKS if m == "walks" else {})), repeats)
        out.append({"method": m, "n_values": db.nodes.count(), "n_links": db.problem.links.count(), "mean_s": float(np.mean(took)), "sd_s": float(np.std(took))})
    return out


def run_fractions(spark: SparkSession, folder: str, shares=(1 / 16, 1 / 8, 1 / 4, 1 / 2, 1.0), methods=("objective", "series")) -> list[dict]:
    """Seconds by size: parts of the orders by key, without the values that lose all their links."""
    frames, out = load_tables(spark, folder, COMMERCE), []
    most = frames["orders"].agg(F.max("o_orderkey")).first()[0]
    words = d.stand_in_lexicon(spark, folder)
    for share in shares:
        part = extract.fraction(frames, "orders", "o_orderkey", int(most * share) + 1)
        part["customer"] = part["customer"].join(part["orders"].select(F.col("o_custkey").alias("c_custkey")).distinct(), "c_custkey", "left_semi")
        db = d.build(spark, part, COMMERCE, words)
        for m in methods:
            took = scores.timed(lambda m=m, db=db: d.fit(db, m), 1)
            out.append({"share": share, "method": m, "n_values": db.nodes.count(), "seconds": took[0]})
    return out


def weight_effects(spark: SparkSession) -> DataFrame:
    """(setting, node, x, y): three titles and two countries in two dimensions under twelve settings of the weights."""
    base = [(0, "country", "c1", [2.0, -1.0], False), (1, "country", "c2", [-1.5, -1.0], False), (2, "title", "t1", [1.0, 1.5], False), (3, "title", "t2", [-1.0, 2.0], False), (4, "title", "t3", [0.5, 0.5], False)]
    pairs = [(2, 0), (3, 1), (4, 1)]
    rows = spark.createDataFrame(base, "node_id long, category string, value string, vec array<double>, is_oov boolean")
    links = spark.createDataFrame([("r", inv, *(p[::-1] if inv else p)) for p in pairs for inv in (False, True)], "rel string, rel_inv boolean, src long, dst long")
    p, out = solvers.Problem(rows, links, 2), []
    settings = [("base", Params(a, 1, 2, 1)) for a in (1, 2, 3)] + [("column", Params(2, b, 2, 1)) for b in (1, 2, 3)] + [("link", Params(2, 1, g, 1)) for g in (1, 2, 3)] + [("repel", Params(2, 1, 3, r)) for r in (0, 1, 2)]
    for varied, s in settings:
        x = solvers.fit_objective(p, s, 60).vectors
        out.append(x.select(F.lit(varied).alias("varied"), F.lit(f"{s.base:g},{s.column:g},{s.link:g},{s.repel:g}").alias("setting"), "node_id", F.get("vec", F.lit(0)).alias("x"), F.get("vec", F.lit(1)).alias("y")))
    return _union(out)


def run_oov_neighbours(spark: SparkSession, folder: str) -> DataFrame:
    """(value, own, nearest): customers, which have no words, with their nation and the nation nearest after fitting."""
    db = d.database(spark, folder)
    x = db.named(graph.unit_vectors(d.fit(db, "series", Params(1, 0, 3, 0.2), 3)))
    names = broadcast_if_small(x.where("category = 'nation.n_name'").select(F.col("value").alias("nation"), F.col("vec").alias("v")), 10_000)
    dot = F.aggregate(F.zip_with("vec", "v", lambda a, b: a * b), F.lit(0.0), lambda s, e: s + e)
    near = x.where("category = 'customer.c_name'").crossJoin(names).groupBy("value").agg(F.max_by("nation", dot).alias("nearest"))  # nations are few
    own = db.links.where("rel = 'fk:customer.c_name>nation.n_name'").select(F.col("src").alias("value"), F.col("dst").alias("own"))
    return near.join(own, "value").select("value", "own", "nearest")
