"""Queries of the methods: values, links, start vectors, weights, solvers, losses, baselines and measures."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tablevec import database as d
from tablevec.functions.vectors import vec_cosine, vec_dot, vec_norm, vec_unit
from tablevec.operators import extract, graph, lexicon, solvers
from tablevec.operators import weights as w
from tablevec.operators.weights import Params
from tablevec.queries import sql
from tablevec.spec import COMMERCE, CORPUS, MINI, LinkTable, SchemaSpec

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
OBJECTIVE, SERIES = Params(1.0, 0.5, 3.0, 2.0), Params(1.0, 0.5, 3.0, 1.0)
PARTS = SchemaSpec({"part": ("p_name", "p_brand", "p_type")})


def query(oracle: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return add


def read(spark: SparkSession, sf: str, *names: str):
    frames = [spark.read.parquet(f"{sf}/{n}.parquet") for n in names]
    return frames[0] if len(frames) == 1 else frames


def mini(spark, sf) -> d.Database:
    return d.database(spark, sf, MINI)


def compact(db: d.Database, x: DataFrame) -> DataFrame:
    rows = db.problem.base.select("node_id", "category", "value", F.col("vec").alias("b")).join(x, "node_id")
    ramp = F.aggregate(F.zip_with("vec", F.sequence(F.lit(1), F.size("vec")), lambda v, k: v * k), F.lit(0.0), lambda s, v: s + v)
    r = lambda c, n=6: F.round(c, n) + F.lit(0.0)
    return rows.select("category", "value", r(vec_norm("vec")).alias("norm"), r(vec_dot("vec", "b")).alias("dot_base"), r(F.get("vec", F.lit(0))).alias("first"), r(ramp, 5).alias("ramp"))


# values and links


@query(f"SELECT category, count(*) AS n, min(value) AS first_value, max(value) AS last_value FROM ({sql.values(COMMERCE)}) GROUP BY category")
def values_by_category(spark, sf):
    frames = d.load_tables(spark, sf, COMMERCE)
    return extract.extract_values(frames, COMMERCE).groupBy("category").agg(F.count(F.lit(1)).alias("n"), F.min("value").alias("first_value"), F.max("value").alias("last_value"))


@query(f"SELECT value, count(*) AS n_categories FROM ({sql.values(CORPUS)}) GROUP BY value HAVING count(*) > 1")
def values_shared_across_columns(spark, sf):
    found = extract.extract_values(d.load_tables(spark, sf, CORPUS), CORPUS)
    return found.groupBy("value").agg(F.count(F.lit(1)).alias("n_categories")).where("n_categories > 1")


@query(sql.links(PARTS))
def links_row_part(spark, sf):
    return extract.links_row(d.load_tables(spark, sf, PARTS), "part", PARTS)


@query(sql.links(MINI.only("fk")))
def links_fk_customer_nation(spark, sf):
    return extract.extract_links(d.load_tables(spark, sf, MINI), MINI.only("fk"))


@query(sql.links(COMMERCE.only("nm")))
def links_nm_part_supplier(spark, sf):
    return extract.links_nm(d.load_tables(spark, sf, COMMERCE), COMMERCE.links[0], COMMERCE)


@query("SELECT DISTINCT c_name AS src, p_name AS dst FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey")
def links_two_hop_customer_part(spark, sf):
    orders, items = read(spark, sf, "orders", "lineitem")
    ties = items.select("l_orderkey", "l_partkey").join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_partkey")
    spec = SchemaSpec({"customer": ("c_name",), "part": ("p_name",)})
    frames = {"ties": ties, **d.load_tables(spark, sf, spec)}
    return extract.links_nm(frames, LinkTable("ties", "o_custkey", "customer", "c_custkey", "l_partkey", "part", "p_partkey"), spec).select("src", "dst")


@query(f"SELECT rel, count(*) AS n, count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM ({sql.links(COMMERCE)}) GROUP BY rel")
def links_all_counts(spark, sf):
    found = extract.extract_links(d.load_tables(spark, sf, COMMERCE), COMMERCE)
    return found.groupBy("rel").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))


@query(f"WITH raw AS ({sql.links(MINI)}) SELECT rel, false AS rel_inv, count(*) AS n, min(src) AS low_src, max(dst) AS high_dst FROM raw GROUP BY rel UNION ALL SELECT rel, true, count(*), min(dst), max(src) FROM raw GROUP BY rel")
def links_mirror_check(spark, sf):
    return extract.mirrored(mini(spark, sf).links).groupBy("rel", "rel_inv").agg(F.count(F.lit(1)).alias("n"), F.min("src").alias("low_src"), F.max("dst").alias("high_dst"))


@query("SELECT DISTINCT event_type AS src, json_extract_string(props, '$.k') AS dst FROM events WHERE event_type <> '' AND json_extract_string(props, '$.k') IS NOT NULL")
def links_json_events(spark, sf):
    rows = read(spark, sf, "events").select("event_type", F.concat(F.lit("["), "props", F.lit("]")).alias("list"))
    entries = extract.expand_json(rows, "list", "struct<k:string>", "event_type")
    return entries.select(F.col("event_type").alias("src"), F.col("entry.k").alias("dst")).where("src != '' and dst is not null").distinct()


@query("SELECT DISTINCT src, dst FROM (SELECT text AS src, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL AND src <> '' AND dst <> ''")
def links_conversation_next(spark, sf):
    order = Window.partitionBy("conv_id").orderBy("turn")
    rows = read(spark, sf, "conversations").select(F.col("text").alias("src"), F.lead("text").over(order).alias("dst"))
    return rows.where("dst is not null and src != '' and dst != ''").distinct()


@query("SELECT DISTINCT d.text AS src, b.text AS dst FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE b.text <> ''")
def links_containment_benchmark(spark, sf):
    docs, passages = read(spark, sf, "documents", "benchmark")
    return extract.containment_links(docs.select(F.col("text").alias("src")).distinct(), passages.select(F.col("text").alias("dst")).distinct())


@query(f"WITH raw AS ({sql.links(MINI)}) SELECT category, value FROM ({sql.values(MINI)}) WHERE (category, value) NOT IN (SELECT src_category, src FROM raw UNION SELECT dst_category, dst FROM raw)")
def values_without_links(spark, sf):
    db = mini(spark, sf)
    return extract.orphans(db.nodes.select("category", "value"), db.links)


# lexicon and start vectors


@query(f"WITH {sql.lexicon(True)} SELECT term, vec_id FROM lex")
def lexicon_terms(spark, sf):
    words = d.stand_in_lexicon(spark, sf, True)
    vectors = read(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("vec"))
    return words.join(vectors, "vec").select("term", "vec_id")


_PREFIXES = "SELECT array_to_string(t[1:n], ' ') AS prefix, bool_or(n = len(t)) AS is_term FROM (SELECT t, unnest(range(1, len(t) + 1)) AS n FROM (SELECT string_split(term, ' ') AS t FROM lex)) GROUP BY 1"


@query(f"WITH {sql.lexicon()} {_PREFIXES}")
def lexicon_prefixes(spark, sf):
    return lexicon.build_prefixes(d.stand_in_lexicon(spark, sf))


_PART_HITS = " SELECT category, value, CAST(pos AS INTEGER) AS pos, term FROM hits"


@query(sql.start(PARTS) + _PART_HITS)
def phrase_hits_parts(spark, sf):
    db = d.database(spark, sf, PARTS)
    return db.hits.join(db.nodes, "node_id").select("category", "value", "pos", "term")


@query(sql.start(PARTS) + _PART_HITS)
def phrase_hits_parts_by_join(spark, sf):
    db = d.database(spark, sf, PARTS)
    return lexicon.match_phrases(db.nodes, db.lexicon, "join").join(db.nodes, "node_id").select("category", "value", F.col("pos").cast("int").alias("pos"), "term")


@query(sql.start(PARTS, phrases=False) + _PART_HITS)
def token_hits_parts(spark, sf):
    db = d.database(spark, sf, PARTS)
    return lexicon.match_tokens(db.nodes, db.lexicon.where("n_tokens = 1")).join(db.nodes, "node_id").select("category", "value", F.col("pos").cast("int").alias("pos"), "term")


ORACLES["token_hits_parts"] = sql.start(PARTS, phrases=False) + _PART_HITS


@query(f"WITH {sql.lexicon(True)}, words AS (SELECT doc_id, unnest({sql.TOKENS.replace('{0}', 'text')}) AS term FROM documents) SELECT doc_id, count(*) AS n, count(DISTINCT term) AS n_terms FROM words WHERE term IN (SELECT term FROM lex) GROUP BY doc_id")
def token_hits_documents(spark, sf):
    docs = read(spark, sf, "documents").select(F.col("doc_id").alias("node_id"), F.col("text").alias("value"))
    hits = lexicon.match_tokens(docs, d.stand_in_lexicon(spark, sf, True))
    return hits.groupBy(F.col("node_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("term").alias("n_terms"))


_GREEDY = f"""WITH {sql.lexicon(True)}, toks AS (SELECT doc_id, {sql.TOKENS.replace('{0}', 'text')} AS t FROM documents),
    best AS (SELECT doc_id, i, max(n) AS n, max_by(term, n) AS term FROM (SELECT doc_id, i, n, array_to_string(t[i:i + n - 1], ' ') AS term FROM (SELECT doc_id, t, i, unnest(range(1, 5)) AS n FROM (SELECT doc_id, t, unnest(range(1, len(t) + 1)) AS i FROM toks)) WHERE i + n - 1 <= len(t)) WHERE term IN (SELECT term FROM lex) GROUP BY doc_id, i),
    runs AS (SELECT doc_id, list({{'at': i, 'next': i + n, 'terms': [term]}} ORDER BY i) AS h FROM best GROUP BY doc_id),
    taken AS (SELECT doc_id, list_reduce(h, lambda s, x: CASE WHEN x['at'] >= s['next'] THEN {{'at': x['at'], 'next': x['next'], 'terms': list_concat(s['terms'], x['terms'])}} ELSE s END)['terms'] AS terms FROM runs)
    SELECT doc_id, len(terms) AS n, list_unique(terms)::BIGINT AS n_terms, len(list_filter(terms, lambda x: contains(x, ' '))) AS n_phrases FROM taken"""


@query(_GREEDY)
def phrase_hits_documents(spark, sf):
    docs = read(spark, sf, "documents").select(F.col("doc_id").alias("node_id"), F.col("text").alias("value"))
    hits = lexicon.match_phrases(docs, d.stand_in_lexicon(spark, sf, True))
    phrases = F.count_if(F.contains("term", F.lit(" "))).alias("n_phrases")
    return hits.groupBy(F.col("node_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("term").alias("n_terms"), phrases)


@query(sql.start(PARTS) + ", x AS (SELECT id, dim, v FROM base)" + sql.compact("x"))
def base_vectors_parts(spark, sf):
    db = d.database(spark, sf, PARTS)
    return compact(db, solvers.base_vectors(db.problem))


@query(sql.start(PARTS, phrases=False) + ", x AS (SELECT id, dim, v FROM base)" + sql.compact("x"))
def base_vectors_token_mean(spark, sf):
    db = d.database(spark, sf, PARTS)
    naive = lexicon.init_vectors(db.nodes, lexicon.match_tokens(db.nodes, db.lexicon.where("n_tokens = 1")), db.lexicon, d.DIMS)
    return compact(d.Database(db.frames, db.spec, db.nodes, db.links, db.lexicon, db.hits, solvers.Problem(naive, db.problem.links, d.DIMS)), naive.select("node_id", "vec"))


ORACLES["token_hits_parts"] = ORACLES["token_hits_parts"].replace("(SELECT term FROM lex)", "(SELECT term FROM lex WHERE term NOT LIKE '% %')")
ORACLES["base_vectors_token_mean"] = ORACLES["base_vectors_token_mean"].replace("t[i] IN (SELECT term FROM lex)", "t[i] IN (SELECT term FROM lex WHERE term NOT LIKE '% %')")


@query(sql.start(COMMERCE) + " SELECT category, count(*) FILTER (WHERE dim = 0) AS n, count(*) FILTER (WHERE dim = 0 AND is_oov) AS n_oov FROM base GROUP BY category")
def base_oov_share(spark, sf):
    base = d.database(spark, sf, COMMERCE).problem.base
    return base.groupBy("category").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("is_oov").cast("long")).alias("n_oov"))


@query(sql.start(COMMERCE) + " SELECT category, round(sqrt(sum(c * c)), 6) + 0.0 AS norm, round(sum((dim + 1) * c), 5) + 0.0 AS ramp FROM cent GROUP BY category")
def column_centroids(spark, sf):
    means = d.database(spark, sf, COMMERCE).problem.column_means()
    ramp = F.aggregate(F.zip_with("centroid", F.sequence(F.lit(1), F.lit(64)), lambda v, k: v * k), F.lit(0.0), lambda s, v: s + v)
    return means.select("category", (F.round(vec_norm("centroid"), 6) + 0.0).alias("norm"), (F.round(ramp, 5) + 0.0).alias("ramp"))


@query(sql.start(COMMERCE) + " SELECT category, round(sqrt(sum(c * c)), 6) + 0.0 AS norm FROM (SELECT category, dim, coalesce(avg(v) FILTER (WHERE NOT is_oov), 0) AS c FROM base GROUP BY category, dim) GROUP BY category")
def column_centroids_known_only(spark, sf):
    means = lexicon.column_centroids(d.database(spark, sf, COMMERCE).problem.base, 64, include_oov=False)
    return means.select("category", (F.round(vec_norm("centroid"), 6) + 0.0).alias("norm"))


# graph and weights


@query(sql.weights(COMMERCE) + ", e AS (SELECT DISTINCT rel AS label, src, dst FROM l UNION ALL SELECT 'category', id, category FROM nodes UNION ALL SELECT 'category', category, id FROM nodes) SELECT label, count(*) AS n, count(DISTINCT src) AS n_src FROM e GROUP BY label")
def graph_degree(spark, sf):
    db = d.database(spark, sf, COMMERCE)
    _, edges = graph.build_graph(db.nodes, db.problem.links)
    return edges.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("src").alias("n_src"))


def _weight_rows(spark, sf, solver, params, **more):
    db = mini(spark, sf)
    rows = w.derive_weights(db.problem.links, params, solver, **more).join(db.nodes.withColumnRenamed("node_id", "src"), "src")
    return rows.select("rel", "rel_inv", "category", "value", "out_degree", "k", (F.round("link_w", 9)).alias("link_w"), (F.round("rep_w", 9)).alias("rep_w"))


_OWN = " SELECT o.rel, o.inv AS rel_inv, n.category, n.value, o.o AS out_degree, k.k, round(own.w, 9) AS link_w, round(own.r, 9) AS rep_w FROM own JOIN outs o USING (rel, inv, src) JOIN ks k ON k.src = o.src JOIN nodes n ON n.id = o.src"


@query(sql.weights(MINI) + "," + sql.objective_coefs(OBJECTIVE) + _OWN)
def weights_objective(spark, sf):
    return _weight_rows(spark, sf, "objective", OBJECTIVE)


@query(sql.weights(MINI) + "," + sql.series_coefs(SERIES) + _OWN)
def weights_series(spark, sf):
    return _weight_rows(spark, sf, "series", SERIES)


@query(sql.weights(MINI) + "," + sql.series_coefs(SERIES, True) + _OWN)
def weights_series_literal(spark, sf):
    return _weight_rows(spark, sf, "series", SERIES, repulsion="outdegree")


_AWAY = "," + sql.objective_coefs(OBJECTIVE) + ", away AS (SELECT n.src, sum(a.r) AS one, sum(a.r + b.r) AS both FROM nons n JOIN own a USING (rel, inv, src) JOIN own b ON b.rel = n.rel AND b.inv = NOT n.inv AND b.src = n.dst GROUP BY n.src)"


@query(sql.weights(MINI) + _AWAY + f" SELECT n.category, n.value, round({4 * OBJECTIVE.base!r} - coalesce(a.one, 0), 9) AS slack FROM nodes n LEFT JOIN away a ON a.src = n.id")
def convexity_slack_stated(spark, sf):
    db = mini(spark, sf)
    return w.convexity_report(db.nodes, db.problem.links, OBJECTIVE).join(db.nodes, "node_id").select("category", "value", F.round("slack_stated", 9).alias("slack"))


@query(sql.weights(MINI) + _AWAY + f" SELECT n.category, n.value, round({OBJECTIVE.base!r} + {OBJECTIVE.column!r} / (coalesce(k.k, 0) + 1) - 2 * coalesce(a.both, 0), 9) AS slack FROM nodes n LEFT JOIN away a ON a.src = n.id LEFT JOIN ks k ON k.src = n.id")
def convexity_slack_sufficient(spark, sf):
    db = mini(spark, sf)
    return w.convexity_report(db.nodes, db.problem.links, OBJECTIVE).join(db.nodes, "node_id").select("category", "value", F.round("slack_sufficient", 9).alias("slack"))


@query(sql.weights(COMMERCE) + " SELECT g.rel, g.inv AS rel_inv, g.nl AS n_links, coalesce(n.n, 0) AS n_nonlinks FROM grp g LEFT JOIN (SELECT rel, inv, count(*) AS n FROM nons GROUP BY rel, inv) n USING (rel, inv)")
def nonlink_counts(spark, sf):
    links = d.database(spark, sf, COMMERCE).problem.links
    return w.group_sizes(links).select("rel", "rel_inv", "n_links", (F.col("n_src") * F.col("n_dst") - F.col("n_links")).alias("n_nonlinks"))


# solvers and baselines

_START = sql.weights(MINI) + ","


@query(_START + sql.objective_coefs(OBJECTIVE) + sql.objective_sweeps(OBJECTIVE, 1) + sql.compact("x1"))
def objective_1_sweep(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_objective(db.problem, OBJECTIVE, 1, kernel="shuffle").vectors)


@query(_START + sql.objective_coefs(OBJECTIVE) + sql.objective_sweeps(OBJECTIVE, 3) + sql.compact("x3"))
def objective_3_sweeps(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_objective(db.problem, OBJECTIVE, 3).vectors)


@query(_START + sql.objective_coefs(Params(1.0, 0.0, 3.0, 3.0)) + sql.objective_sweeps(Params(1.0, 0.0, 3.0, 3.0), 2) + sql.compact("x2"))
def nonlink_sum_bruteforce_vs_shortcut(spark, sf):
    db, p = mini(spark, sf), Params(1, 0, 3, 3)
    short = compact(db, solvers.fit_objective(db.problem, p, 2).vectors)
    listed = compact(db, solvers.fit_objective(db.problem, p, 2, nonlinks="bruteforce").vectors)
    return short.intersect(listed)


_BLOCKS = ["customer.c_mktsegment", "customer.c_name", "nation.n_name", "region.r_name"]


@query(_START + sql.objective_coefs(OBJECTIVE) + sql.seidel_sweep(OBJECTIVE, _BLOCKS) + sql.compact("x4"))
def objective_gauss_seidel_1(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_objective(db.problem, OBJECTIVE, 1, update="block_seidel").vectors)


@query(_START + sql.series_coefs(SERIES) + sql.series_sweeps(SERIES, 1) + sql.compact("x1"))
def series_1_sweep(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_series(db.problem, SERIES, 1, kernel="shuffle").vectors)


@query(_START + sql.series_coefs(Params(1.0, 0.0, 3.0, 1.0)) + sql.series_sweeps(Params(1.0, 0.0, 3.0, 1.0), 3) + sql.compact("x3"))
def series_3_sweeps(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_series(db.problem, Params(1, 0, 3, 1), 3).vectors)


@query(_START + sql.series_coefs(SERIES, True) + sql.series_sweeps(SERIES, 1) + sql.compact("x1"))
def series_literal_1(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_series(db.problem, SERIES, 1, repulsion="outdegree").vectors)


@query(_START + sql.series_coefs(SERIES) + sql.series_sweeps(SERIES, 1) + sql.compact("x1"))
def series_per_node_totals(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_series(db.problem, SERIES, 1, totals="per_node").vectors)


@query(sql.weights(MINI) + sql.graph_sweeps(2) + sql.compact("x2"))
def graph_baseline_2_sweeps(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_graph_baseline(db.problem, 2).vectors)


@query(sql.weights(MINI) + sql.graph_sweeps(1, True) + sql.compact("x1"))
def graph_baseline_exact_1(spark, sf):
    db = mini(spark, sf)
    return compact(db, solvers.fit_graph_baseline(db.problem, 1, update="exact", kernel="shuffle").vectors)


# the whole database: link tables, hubs, columns of many kinds

_WHOLE = sql.weights(COMMERCE) + ","


@query(_WHOLE + sql.objective_coefs(OBJECTIVE) + sql.objective_sweeps(OBJECTIVE, 1) + sql.compact("x1"))
def objective_commerce(spark, sf):
    db = d.database(spark, sf, COMMERCE)
    return compact(db, solvers.fit_objective(db.problem, OBJECTIVE, 1, kernel="shuffle").vectors)


@query(_WHOLE + sql.series_coefs(SERIES) + sql.series_sweeps(SERIES, 1) + sql.compact("x1"))
def series_commerce(spark, sf):
    db = d.database(spark, sf, COMMERCE)
    return compact(db, solvers.fit_series(db.problem, SERIES, 1).vectors)


@query(sql.weights(COMMERCE) + sql.graph_sweeps(2) + sql.compact("x2"))
def graph_baseline_commerce(spark, sf):
    db = d.database(spark, sf, COMMERCE)
    return compact(db, solvers.fit_graph_baseline(db.problem, 2, kernel="shuffle").vectors)


@query(_WHOLE + sql.objective_coefs(OBJECTIVE) + " SELECT n.category, round(min(d.den), 6) AS least, round(max(d.den), 6) AS most FROM den d JOIN nodes n USING (id) GROUP BY n.category")
def min_denominator(spark, sf):
    """What each column's updates are divided by; not above 0 means that sweeps may diverge."""
    den = solvers.objective_step(d.database(spark, sf, COMMERCE).problem, OBJECTIVE).nodes
    return den.groupBy("category").agg(F.round(F.min("den"), 6).alias("least"), F.round(F.max("den"), 6).alias("most"))


def _rounded(loss: DataFrame) -> DataFrame:
    return loss.select(*((F.round(c, 5) + 0.0).alias(c) for c in loss.columns))


@query(_START + sql.objective_coefs(OBJECTIVE) + ", x0 AS (SELECT id, dim, v FROM base)" + sql.losses(OBJECTIVE, "x0"))
def loss_terms_initial(spark, sf):
    db = mini(spark, sf)
    return _rounded(solvers.objective_loss(db.problem, solvers.base_vectors(db.problem), OBJECTIVE))


@query(_START + sql.objective_coefs(OBJECTIVE) + sql.objective_sweeps(OBJECTIVE, 2) + sql.losses(OBJECTIVE, "x2"))
def loss_terms_after_2(spark, sf):
    db = mini(spark, sf)
    return _rounded(solvers.objective_loss(db.problem, solvers.fit_objective(db.problem, OBJECTIVE, 2).vectors, OBJECTIVE))


@query(sql.weights(MINI) + sql.graph_sweeps(2) + """, t1 AS (SELECT sum((x.v - b.v) * (x.v - b.v)) AS base_loss FROM base b JOIN x2 x USING (id, dim)),
    t2 AS (SELECT sum(a.beta * (p.v - q.v) * (p.v - q.v)) AS neighbour_loss FROM edges e JOIN deg a ON a.src = e.src JOIN x2 p ON p.id = e.src JOIN x2 q ON q.id = e.dst AND q.dim = p.dim)
    SELECT round(base_loss, 5) AS base_loss, round(neighbour_loss, 5) AS neighbour_loss, round(base_loss + neighbour_loss, 5) AS total FROM t1, t2""")  # fmt: skip
def loss_graph_baseline(spark, sf):
    db = mini(spark, sf)
    return _rounded(solvers.graph_loss(db.problem, solvers.fit_graph_baseline(db.problem, 2).vectors))


@query(sql.weights(MINI) + sql.graph_sweeps(1) + " SELECT b.category, b.value, CAST(128 AS INTEGER) AS dims, round(sqrt(sum(b.v * b.v) + sum(x.v * x.v)), 6) + 0.0 AS norm FROM base b JOIN x1 x USING (id, dim) GROUP BY b.category, b.value")
def combine_concat(spark, sf):
    db = mini(spark, sf)
    both = graph.combine_vectors(solvers.base_vectors(db.problem), solvers.fit_graph_baseline(db.problem, 1).vectors)
    return db.named(both).select("category", "value", F.size("vec").alias("dims"), (F.round(vec_norm("vec"), 6) + 0.0).alias("norm"))


@query(sql.start(MINI) + " SELECT category, CAST(round(sum(n)) AS BIGINT) AS n_unit FROM (SELECT category, value, CASE WHEN sum(v * v) > 0 THEN 1 ELSE 0 END AS n FROM base GROUP BY category, value) GROUP BY category")
def unit_vectors(spark, sf):
    db = mini(spark, sf)
    x = db.named(graph.unit_vectors(solvers.base_vectors(db.problem)))
    return x.groupBy("category").agg(F.round(F.sum(vec_norm("vec"))).cast("long").alias("n_unit"))


@query(sql.start(COMMERCE) + """, q AS (SELECT dim, v FROM base WHERE category = 'part.p_name' AND value = (SELECT min(p_name) FROM part)), c AS (
    SELECT b.category, b.value, sum(b.v * q.v) / (sqrt(sum(b.v * b.v)) * sqrt(sum(q.v * q.v))) AS cosine FROM base b JOIN q USING (dim) WHERE NOT (b.category = 'part.p_name' AND b.value = (SELECT min(p_name) FROM part)) AND NOT is_oov GROUP BY b.category, b.value)
    SELECT category, value, round(cosine, 6) + 0.0 AS cosine FROM c ORDER BY round(cosine, 9) DESC, category, value LIMIT 10""")  # fmt: skip
def nearest_values_topk(spark, sf):
    db = d.database(spark, sf, COMMERCE)
    name = read(spark, sf, "part").agg(F.min("p_name")).first()[0]
    named = db.named(solvers.base_vectors(db.problem)).join(db.problem.base.where("not is_oov").select("node_id"), "node_id", "left_semi")
    return graph.nearest_values(named, name, 10, of="part.p_name").select("category", "value", (F.round("cosine", 6) + 0.0).alias("cosine"))


@query("SELECT label, min(n) AS n, round(sum(m * m), 6) AS square FROM (SELECT label, dim, avg(v) AS m, count(*) AS n FROM (SELECT label, vec_id, unnest(range(64)) AS dim, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY label, dim) GROUP BY label")
def embedding_label_centroids(spark, sf):
    from tablevec.functions.vectors import vec_mean

    rows = read(spark, sf, "embeddings").select("label", F.col("embedding").cast("array<double>").alias("v"))
    return rows.groupBy("label").agg(vec_mean("v", 64).alias("c"), F.count(F.lit(1)).alias("n")).select("label", "n", F.round(vec_dot("c", "c"), 6).alias("square"))


# specs, fractions and counts


def _fraction_values(below: str) -> str:
    return f"SELECT '{below}' AS share, count(DISTINCT c_name) AS n_names, count(*) AS n_links FROM (SELECT DISTINCT c_name, o_orderpriority FROM orders JOIN customer ON c_custkey = o_custkey WHERE o_orderkey < (SELECT max(o_orderkey) FROM orders) * {below})"


@query(" UNION ALL ".join(_fraction_values(x) for x in ("0.0625", "0.125", "0.25", "0.5", "1.0")))
def fraction_counts(spark, sf):
    spec = SchemaSpec({"orders": ("o_orderpriority",), "customer": ("c_name",)}, (COMMERCE.keys[3],))
    frames = d.load_tables(spark, sf, spec)
    most, out = frames["orders"].agg(F.max("o_orderkey")).first()[0], None
    for share in ("0.0625", "0.125", "0.25", "0.5", "1.0"):
        part = {**frames, "orders": frames["orders"].where(F.col("o_orderkey") < F.lit(most) * F.lit(float(share)))}
        found = extract.extract_links(part, spec)
        row = found.agg(F.lit(share).alias("share"), F.countDistinct("dst").alias("n_names"), F.count(F.lit(1)).alias("n_links"))
        out = row if out is None else out.union(row)
    return out


_HELD = COMMERCE.without("region.r_name")


@query(f"SELECT 'links' AS kind, count(*) AS n FROM ({sql.links(_HELD)}) UNION ALL SELECT 'values', count(*) FROM ({sql.values(_HELD)})")
def spec_withheld_counts(spark, sf):
    frames = d.load_tables(spark, sf, _HELD)
    links, values = extract.extract_links(frames, _HELD), extract.extract_values(frames, _HELD)
    return links.agg(F.lit("links").alias("kind"), F.count(F.lit(1)).alias("n")).union(values.agg(F.lit("values"), F.count(F.lit(1))))


@query(f"SELECT kind, src_category, count(*) AS n FROM (SELECT split_part(rel, ':', 1) AS kind, src_category FROM ({sql.links(COMMERCE)})) GROUP BY CUBE (kind, src_category)")
def cube_links(spark, sf):
    links = d.database(spark, sf, COMMERCE).links
    return links.select(F.split_part("rel", F.lit(":"), F.lit(1)).alias("kind"), "src_category").cube("kind", "src_category").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT tab, category, count(*) AS n FROM (SELECT split_part(category, '.', 1) AS tab, category FROM ({sql.values(COMMERCE)})) GROUP BY ROLLUP (tab, category)")
def rollup_values(spark, sf):
    nodes = d.database(spark, sf, COMMERCE).nodes
    return nodes.select(F.split_part("category", F.lit("."), F.lit(1)).alias("tab"), "category").rollup("tab", "category").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT 'values' AS kind, category AS name, count(*) AS n FROM ({sql.values(COMMERCE)}) GROUP BY category UNION ALL SELECT 'links', rel, count(*) FROM ({sql.links(COMMERCE)}) GROUP BY rel")
def dataset_profile(spark, sf):
    return d.profile(d.database(spark, sf, COMMERCE))


@query("SELECT vec_id, round(sqrt(list_dot_product(e, e)), 6) AS norm, round(list_dot_product(e, e), 6) AS dot, round(list_cosine_similarity(e, list_reverse(e)), 6) + 0.0 AS cosine, round(list_sum(list_transform(e, lambda x: x / sqrt(list_dot_product(e, e)))), 6) + 0.0 AS unit_sum FROM (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings)")
def array_vec_math(spark, sf):
    rows = read(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    r = lambda c: F.round(c, 6) + F.lit(0.0)
    return rows.select("vec_id", r(vec_norm("e")).alias("norm"), r(vec_dot("e", "e")).alias("dot"), r(vec_cosine("e", F.reverse("e"))).alias("cosine"), r(F.aggregate(vec_unit("e"), F.lit(0.0), lambda s, x: s + x)).alias("unit_sum"))
