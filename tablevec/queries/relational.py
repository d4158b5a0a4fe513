"""Queries of the surrounding operators on the given tables."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from tablevec.operators import relational as r
from tablevec.operators.lexicon import read_lexicon_text
from tablevec.plans.stages import Stages
from tablevec.sources import io

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(oracle: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return put


def t(spark, sf, name):
    return spark.read.parquet(f"{sf}/{name}.parquet")


c = F.col


@add("SELECT doc_id, lang FROM documents")
def op_scan_pruned(spark, sf):
    return t(spark, sf, "documents").select("doc_id", "lang")


@add("SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 100000 AND o_orderstatus = 'F'")
def op_filter_pushdown(spark, sf):
    return t(spark, sf, "orders").where((c("o_totalprice") > 100000) & (c("o_orderstatus") == "F")).select("o_orderkey", "o_totalprice")


@add("SELECT o_orderkey FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_totalprice BETWEEN 1000 AND 200000 AND regexp_matches(o_orderstatus, '^[FO]') AND o_orderpriority LIKE '%H%'")
def op_filter_in_between_like(spark, sf):
    return t(spark, sf, "orders").where(c("o_orderpriority").isin("1-URGENT", "2-HIGH") & c("o_totalprice").between(1000, 200000) & c("o_orderstatus").rlike("^[FO]") & c("o_orderpriority").like("%H%")).select("o_orderkey")


@add("SELECT doc_id, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars < 3000 THEN 'middle' ELSE 'long' END AS size, coalesce(nullif(lang, 'en'), 'english') AS name FROM documents")
def op_case_coalesce(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.when(c("n_chars") < 500, "short").when(c("n_chars") < 3000, "middle").otherwise("long").alias("size"), F.coalesce(F.nullif("lang", F.lit("en")), F.lit("english")).alias("name"))


@add("SELECT p_partkey, p_name, p_brand, p_retailprice FROM part")
def op_csv_round_trip(spark, sf):
    return io.round_trip(t(spark, sf, "part").select("p_partkey", "p_name", "p_brand", "p_retailprice"), "csv", header="true")


@add("SELECT event_id, event_type, value, props FROM events")
def op_json_round_trip(spark, sf):
    return io.round_trip(t(spark, sf, "events").select("event_id", "event_type", "value", "props"), "json")


@add("SELECT p_partkey, p_brand FROM part")
def op_parquet_partitioned(spark, sf):
    return io.partitioned_round_trip(t(spark, sf, "part").select("p_partkey", "p_brand"), "p_brand")


@add("SELECT 'term ' || vec_id AS term, CAST(2 AS INTEGER) AS n_tokens, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)), 5) + 0.0 AS total FROM embeddings")
def op_vectors_text_source(spark, sf):
    stages = Stages(spark, "text")
    t(spark, sf, "embeddings").select(F.concat_ws(" ", F.concat(F.lit("term_"), "vec_id"), F.transform("embedding", lambda x: x.cast("double").cast("string"))).alias("value")).write.text(f"{stages.root}/v")
    return read_lexicon_text(spark, f"{stages.root}/v").select("term", "n_tokens", (F.round(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x), 5) + 0.0).alias("total"))


@add("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def op_join_broadcast(spark, sf):
    n, g = t(spark, sf, "nation"), t(spark, sf, "region")
    return t(spark, sf, "customer").join(F.broadcast(n), c("c_nationkey") == c("n_nationkey")).join(F.broadcast(g), c("n_regionkey") == c("r_regionkey")).select("c_custkey", "n_name", "r_name")


_PART_ITEMS = "SELECT p_brand, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"


def _part_items(spark, sf, hint):
    p = t(spark, sf, "part").select("p_partkey", "p_brand").hint(hint)
    return t(spark, sf, "lineitem").select("l_partkey", "l_quantity").join(p, c("l_partkey") == c("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@add(_PART_ITEMS)
def op_join_merge(spark, sf):
    return _part_items(spark, sf, "merge")


@add(_PART_ITEMS)
def op_join_shuffle_hash(spark, sf):
    return _part_items(spark, sf, "shuffle_hash")


def _docs_labels(spark, sf, how):
    return t(spark, sf, "documents").select("doc_id", "lang").join(t(spark, sf, "labels"), "doc_id", how)


@add("SELECT doc_id, lang, quality, toxic FROM documents LEFT JOIN labels USING (doc_id)")
def op_join_left_outer(spark, sf):
    return _docs_labels(spark, sf, "left")


@add("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, lang, quality, toxic FROM (SELECT * FROM documents WHERE lang <> 'en') d FULL JOIN labels l ON d.doc_id = l.doc_id")
def op_join_full_outer(spark, sf):
    return t(spark, sf, "documents").where("lang != 'en'").select("doc_id", "lang").join(t(spark, sf, "labels"), "doc_id", "full").select("doc_id", "lang", "quality", "toxic")


@add("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(spark, sf):
    return _docs_labels(spark, sf, "left_semi")


@add("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, sf):
    return _docs_labels(spark, sf, "left_anti")


@add("SELECT r_name, c_mktsegment FROM region CROSS JOIN (SELECT DISTINCT c_mktsegment FROM customer)")
def op_join_cross(spark, sf):
    return t(spark, sf, "region").select("r_name").crossJoin(t(spark, sf, "customer").select("c_mktsegment").distinct())


@add("SELECT a.n_name AS low, b.n_name AS high FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def op_join_theta(spark, sf):
    a, b = t(spark, sf, "nation").alias("a"), t(spark, sf, "nation").alias("b")
    return a.join(b, (c("a.n_regionkey") == c("b.n_regionkey")) & (c("a.n_nationkey") < c("b.n_nationkey"))).select(c("a.n_name").alias("low"), c("b.n_name").alias("high"))


_BANDS = [(0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, 1e12)]


@add("SELECT band, count(*) AS n FROM orders JOIN (VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, 1e12)) b(band, low, high) ON o_totalprice >= low AND o_totalprice < high GROUP BY band")
def op_join_range(spark, sf):
    return r.range_join(t(spark, sf, "orders"), "o_totalprice", spark.createDataFrame(_BANDS, "band int, low double, high double"), "low", "high").groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT a.event_id, b.event_id AS event_id_r FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 WHERE a.event_type = 'click'")
def op_join_interval(spark, sf):
    e = t(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    return r.interval_join(e.where("event_type = 'click'"), e, "user_id", "ts", 600).where("event_id != event_id_r").select("event_id", "event_id_r")


@add("SELECT o.event_id, (SELECT arg_max(i.value, (i.ts, i.value)) FROM events i WHERE i.user_id = o.user_id AND i.event_type = 'view' AND i.ts <= o.ts) AS last_value FROM events o WHERE o.event_type = 'purchase'")
def op_join_asof(spark, sf):
    e = t(spark, sf, "events").select("event_id", "user_id", "ts", "value", "event_type")
    return r.as_of_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'"), "user_id", "ts", "value").select("event_id", "last_value")


@add("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount, min(l_shipdate) AS first_day, max(l_shipdate) AS last_day FROM lineitem GROUP BY ALL")
def op_agg_hash(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.min("l_shipdate").alias("first_day"), F.max("l_shipdate").alias("last_day"))


@add("SELECT p_brand, min(p_name) AS low, max(p_name) AS high FROM part GROUP BY p_brand")
def op_agg_sort_strings(spark, sf):
    return t(spark, sf, "part").groupBy("p_brand").agg(F.min("p_name").alias("low"), F.max("p_name").alias("high"))


@add("SELECT o_orderpriority, count(DISTINCT o_custkey) AS n FROM orders GROUP BY o_orderpriority")
def op_agg_distinct(spark, sf):
    return t(spark, sf, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("n"))


@add()
def op_agg_approx_distinct(spark, sf):
    return t(spark, sf, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("n"))


@add("SELECT p_type, round(quantile_cont(p_retailprice, 0.5), 6) AS middle, mode(p_size ORDER BY p_size) AS common FROM part GROUP BY p_type")
def op_agg_percentile(spark, sf):
    sizes = t(spark, sf, "part").groupBy("p_type", "p_size").count().groupBy("p_type").agg(F.max_by("p_size", F.struct("count", -c("p_size"))).alias("common"))
    return t(spark, sf, "part").groupBy("p_type").agg(F.round(F.percentile("p_retailprice", 0.5), 6).alias("middle")).join(sizes, "p_type")


ORACLES["op_agg_percentile"] = "SELECT p_type, middle, common FROM (SELECT p_type, round(quantile_cont(p_retailprice, 0.5), 6) AS middle FROM part GROUP BY p_type) JOIN (SELECT p_type, arg_max(p_size, (n, -p_size)) AS common FROM (SELECT p_type, p_size, count(*) AS n FROM part GROUP BY ALL) GROUP BY p_type) USING (p_type)"


@add("SELECT o_orderstatus, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY o_orderstatus")
def op_agg_max_by(spark, sf):
    key = F.struct("o_totalprice", "o_orderkey")
    return t(spark, sf, "orders").groupBy("o_orderstatus").agg(F.max_by("o_orderkey", key).alias("dearest"), F.min_by("o_orderkey", key).alias("cheapest"))


@add("SELECT n_regionkey, array_to_string(list(DISTINCT n_name ORDER BY n_name), ',') AS names FROM nation GROUP BY n_regionkey")
def op_agg_collect_sorted(spark, sf):
    return t(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_name")), ",").alias("names"))


@add("SELECT event_type, count(*) FILTER (WHERE value > 50) AS n_high, round(coalesce(sum(value) FILTER (WHERE value <= 50), 0), 4) AS low_sum FROM events GROUP BY event_type")
def op_agg_filter_clause(spark, sf):
    t(spark, sf, "events").createOrReplaceTempView("tv_events")
    return spark.sql("SELECT event_type, count(*) FILTER (WHERE value > 50) AS n_high, round(coalesce(sum(value) FILTER (WHERE value <= 50), 0), 4) AS low_sum FROM tv_events GROUP BY event_type")


@add("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type), ())")
def op_grouping_sets(spark, sf):
    return t(spark, sf, "part").groupingSets([[c("p_brand")], [c("p_type")], []], c("p_brand"), c("p_type")).agg(F.count(F.lit(1)).alias("n"))


@add("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_type)")
def op_cube(spark, sf):
    return t(spark, sf, "part").cube("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_type)")
def op_rollup(spark, sf):
    return t(spark, sf, "part").rollup("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY user_id")
def op_pivot(spark, sf):
    return t(spark, sf, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)


def _order():
    return W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


@add("SELECT o_orderkey, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS place FROM orders")
def op_window_rank(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", F.rank().over(W.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long").alias("place"))


@add("SELECT o_orderkey, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS place FROM orders")
def op_window_dense_rank(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", F.dense_rank().over(W.partitionBy("o_custkey").orderBy("o_orderpriority")).cast("long").alias("place"))


@add("SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS quarter FROM part")
def op_window_ntile(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.ntile(4).over(W.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("long").alias("quarter"))


@add("SELECT conv_id, turn, lag(role) OVER (PARTITION BY conv_id ORDER BY turn) AS before, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS after FROM conversations")
def op_window_lag_lead(spark, sf):
    w = W.partitionBy("conv_id").orderBy("turn")
    return t(spark, sf, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@add("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS so_far FROM orders")
def op_window_running_rows(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(_order().rowsBetween(W.unboundedPreceding, 0)), 2).alias("so_far"))


@add("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n_hour FROM events")
def op_window_range_frame(spark, sf):
    e = t(spark, sf, "events").withColumn("s", F.floor(F.unix_micros(c("ts").cast("timestamp")) / 1_000_000))
    return e.select("event_id", F.count(F.lit(1)).over(W.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n_hour"))


@add("SELECT o_orderkey, first_value(o_orderkey) OVER w AS first_order, last_value(o_orderkey) OVER w AS last_order FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def op_window_first_last(spark, sf):
    w = _order().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return t(spark, sf, "orders").select("o_orderkey", F.first("o_orderkey").over(w).alias("first_order"), F.last("o_orderkey").over(w).alias("last_order"))


@add("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber LIMIT 20")
def op_sort_limit(spark, sf):
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber").limit(20)


@add("SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def op_topk_per_group(spark, sf):
    w = W.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, sf, "part").withColumn("_k", F.row_number().over(w)).where("_k <= 3").select("p_brand", "p_partkey")


@add("SELECT p_partkey, p_name FROM part ORDER BY p_partkey LIMIT 10 OFFSET 25")
def op_offset_page(spark, sf):
    return t(spark, sf, "part").select("p_partkey", "p_name").orderBy("p_partkey").offset(25).limit(10)


_C, _S = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _keys(spark, sf):
    return t(spark, sf, "customer").select(c("c_nationkey").alias("k")), t(spark, sf, "supplier").select(c("s_nationkey").alias("k"))


@add(f"SELECT k, count(*) AS n FROM ({_C} UNION ALL {_S}) GROUP BY k")
def op_union_all(spark, sf):
    a, b = _keys(spark, sf)
    return a.union(b).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT c_name AS name, c_acctbal AS balance FROM customer UNION ALL SELECT s_name, s_acctbal FROM supplier")
def op_union_by_name(spark, sf):
    return t(spark, sf, "customer").select(c("c_name").alias("name"), c("c_acctbal").alias("balance")).unionByName(t(spark, sf, "supplier").select(c("s_acctbal").alias("balance"), c("s_name").alias("name")))


@add(f"{_C} INTERSECT {_S}")
def op_intersect(spark, sf):
    a, b = _keys(spark, sf)
    return a.intersect(b)


@add("SELECT p_name FROM part WHERE p_brand = 'Brand#11' EXCEPT SELECT p_name FROM part WHERE p_brand = 'Brand#12'")
def op_except(spark, sf):
    p = t(spark, sf, "part")
    return p.where("p_brand = 'Brand#11'").select("p_name").subtract(p.where("p_brand = 'Brand#12'").select("p_name"))


@add(f"{_C} EXCEPT ALL {_S}")
def op_except_all(spark, sf):
    a, b = _keys(spark, sf)
    return a.exceptAll(b)


@add("SELECT p_partkey, upper(p_name) AS up, lower(p_brand) AS low, trim('  ' || p_type || ' ') AS cut, lpad(p_type, 20, '*') AS padded, length(p_name) AS size, substring(p_name, 2, 3) AS part FROM part")
def op_string_case_trim_pad(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.upper("p_name").alias("up"), F.lower("p_brand").alias("low"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("cut"), F.lpad("p_type", 20, "*").alias("padded"), F.length("p_name").cast("long").alias("size"), F.substring("p_name", 2, 3).alias("part"))


@add("SELECT doc_id, len(regexp_split_to_array(text, ' ')) AS n_parts, regexp_replace(text, '[aeiou]', '_', 'g') AS masked, regexp_extract(text, '([A-Za-z]+)', 1) AS word FROM documents")
def op_string_split_regex(spark, sf):
    return t(spark, sf, "documents").select("doc_id", F.size(F.split("text", " ", -1)).cast("long").alias("n_parts"), F.regexp_replace("text", "[aeiou]", "_").alias("masked"), F.regexp_extract("text", "([A-Za-z]+)", 1).alias("word"))


@add("SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS edits FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey")
def op_string_edit_distance(spark, sf):
    a, b = t(spark, sf, "nation").alias("a"), t(spark, sf, "nation").alias("b")
    return a.join(b, c("a.n_regionkey") == c("b.n_regionkey")).select(c("a.n_name").alias("a"), c("b.n_name").alias("b"), F.levenshtein(c("a.n_name"), c("b.n_name")).cast("long").alias("edits"))


@add("SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def op_url_host(spark, sf):
    return t(spark, sf, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("n"))


@add("SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, count(*) AS n FROM orders GROUP BY ALL")
def op_date_trunc_parts(spark, sf):
    return t(spark, sf, "orders").groupBy(F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month"), F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count(F.lit(1)).alias("n"))


@add("SELECT l_orderkey, l_linenumber, date_diff('day', o_orderdate::DATE, l_shipdate::DATE) AS days, CAST(l_shipdate::DATE + 30 AS DATE) AS due FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def op_date_diff_add(spark, sf):
    o = t(spark, sf, "orders").select("o_orderkey", "o_orderdate")
    return t(spark, sf, "lineitem").join(o, c("l_orderkey") == c("o_orderkey")).select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").cast("long").alias("days"), F.date_add("l_shipdate", 30).alias("due"))


@add("SELECT o_orderkey, strftime(o_orderdate + INTERVAL 2 MONTH, '%Y-%m-%d') AS later FROM orders")
def op_interval_add(spark, sf):
    return t(spark, sf, "orders").select("o_orderkey", F.date_format(c("o_orderdate") + F.expr("INTERVAL 2 MONTH"), "yyyy-MM-dd").alias("later"))


@add("SELECT strftime(o_orderdate, '%Y-%m-%d') AS value, count(*) AS n FROM orders GROUP BY 1")
def date_values_orders(spark, sf):
    return t(spark, sf, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM-dd").alias("value")).agg(F.count(F.lit(1)).alias("n"))


@add("SELECT l_orderkey, l_linenumber, round(ln(1 + l_extendedprice), 6) AS logged, round(sqrt(l_quantity), 6) AS root, round(pow(l_discount + 1, 3), 6) AS cubed, round(abs(l_tax - 0.05), 6) AS away, greatest(l_discount, l_tax) AS most FROM lineitem")
def op_math_round_log_pow(spark, sf):
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.ln(1 + c("l_extendedprice")), 6).alias("logged"), F.round(F.sqrt("l_quantity"), 6).alias("root"), F.round(F.pow(c("l_discount") + 1, 3), 6).alias("cubed"), F.round(F.abs(c("l_tax") - 0.05), 6).alias("away"), F.greatest("l_discount", "l_tax").alias("most"))


@add("SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(12, 2)) * CAST(1 - l_discount AS DECIMAL(4, 2))) AS DOUBLE) AS revenue FROM lineitem GROUP BY l_returnflag")
def op_decimal_cast_sum(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.sum(c("l_extendedprice").cast("decimal(12,2)") * (1 - c("l_discount")).cast("decimal(4,2)")).cast("double").alias("revenue"))


@add("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n_positive, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE * x::DOUBLE)), 6) + 0.0 AS cubes FROM embeddings")
def op_array_transform_filter(spark, sf):
    return t(spark, sf, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n_positive"), (F.round(F.aggregate(F.transform("embedding", lambda x: F.pow(x.cast("double"), 3)), F.lit(0.0), lambda s, x: s + x), 6) + 0.0).alias("cubes"))


_E = "list_transform(embedding, lambda x: x::DOUBLE)"


@add(f"SELECT vec_id, round(sqrt(list_dot_product({_E}, {_E})), 6) AS norm FROM embeddings")
def op_array_aggregate_norm(spark, sf):
    return t(spark, sf, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 6).alias("norm"))


@add(f"SELECT a.vec_id, round(list_dot_product(a.e, b.e), 6) + 0.0 AS dot FROM (SELECT vec_id, {_E} AS e FROM embeddings) a JOIN (SELECT vec_id, {_E} AS e FROM embeddings) b ON b.vec_id = a.vec_id + 1")
def op_array_zip_dot(spark, sf):
    e = t(spark, sf, "embeddings").select("vec_id", c("embedding").cast("array<double>").alias("e"))
    n = e.select((c("vec_id") - 1).alias("vec_id"), c("e").alias("f"))
    return e.join(n, "vec_id").select("vec_id", (F.round(F.aggregate(F.zip_with("e", "f", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x), 6) + 0.0).alias("dot"))


@add("SELECT vec_id, CAST(i AS INTEGER) AS i, round(embedding[i + 1]::DOUBLE, 6) + 0.0 AS x FROM (SELECT vec_id, embedding, unnest(range(4)) AS i FROM embeddings)")
def op_array_slice_explode(spark, sf):
    return t(spark, sf, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 4)).alias("i", "x")).select("vec_id", "i", (F.round(c("x").cast("double"), 6) + 0.0).alias("x"))


@add("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def op_map_build_lookup(spark, sf):
    names = t(spark, sf, "nation").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m"))
    return t(spark, sf, "customer").crossJoin(F.broadcast(names)).select("c_custkey", F.element_at("m", c("c_nationkey")).alias("n_name"))


@add("SELECT p_partkey, 'size' AS name, CAST(p_size AS DOUBLE) AS x FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def op_map_explode(spark, sf):
    return t(spark, sf, "part").select("p_partkey", F.explode(F.create_map(F.lit("size"), c("p_size").cast("double"), F.lit("price"), c("p_retailprice"))).alias("name", "x"))


@add("SELECT n_nationkey, n_name || '/' || r_name AS path FROM nation JOIN region ON n_regionkey = r_regionkey")
def op_struct_nest(spark, sf):
    g = t(spark, sf, "region").select("r_regionkey", F.struct("r_name", F.struct(c("r_regionkey").alias("id")).alias("more")).alias("region"))
    return t(spark, sf, "nation").join(F.broadcast(g), c("n_regionkey") == c("region.more.id")).select("n_nationkey", F.concat_ws("/", "n_name", "region.r_name").alias("path"))


@add("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def op_json_extract(spark, sf):
    return t(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@add("SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT))::BIGINT AS total FROM events GROUP BY event_type")
def op_json_parse_schema(spark, sf):
    return t(spark, sf, "events").select("event_type", F.from_json("props", "k bigint").alias("p")).groupBy("event_type").agg(F.sum("p.k").alias("total"))


@add("""SELECT n_nationkey, '{"id":' || n_nationkey || ',"name":"' || n_name || '"}' AS js FROM nation""")
def op_json_emit(spark, sf):
    return t(spark, sf, "nation").select("n_nationkey", F.to_json(F.struct(c("n_nationkey").alias("id"), c("n_name").alias("name"))).alias("js"))


@add("SELECT p_partkey, length(replace(p_name, ' ', '')) AS n FROM part")
def op_udf_scalar_arrow(spark, sf):
    @F.pandas_udf("long")
    def letters(s: pd.Series) -> pd.Series:
        return s.str.replace(" ", "", regex=False).str.len()

    return t(spark, sf, "part").select("p_partkey", letters("p_name").alias("n"))


@add("SELECT label, round(sum(embedding[1]::DOUBLE), 5) + 0.0 AS x0, round(sum(embedding[2]::DOUBLE), 5) + 0.0 AS x1 FROM embeddings GROUP BY label")
def op_udaf_vector_sum(spark, sf):
    @F.pandas_udf("array<double>")
    def total(v: pd.Series) -> list:
        import numpy as np

        return np.array(v.tolist(), dtype=float).sum(axis=0).tolist()

    sums = t(spark, sf, "embeddings").groupBy("label").agg(total("embedding").alias("s"))
    return sums.select("label", (F.round(F.get("s", F.lit(0)), 5) + 0.0).alias("x0"), (F.round(F.get("s", F.lit(1)), 5) + 0.0).alias("x1"))


@add("SELECT p_name, CAST(i - 1 AS INTEGER) AS pos, string_split(p_name, ' ')[i] AS term FROM (SELECT p_name, unnest(range(1, len(string_split(p_name, ' ')) + 1)) AS i FROM (SELECT DISTINCT p_name FROM part))")
def op_udtf_phrase_hits(spark, sf):
    @F.udtf(returnType="pos: int, term: string")
    class Words:
        def eval(self, text: str):
            for k, w in enumerate((text or "").split(" ")):
                yield k, w

    spark.udtf.register("tv_words", Words)
    t(spark, sf, "part").select("p_name").distinct().createOrReplaceTempView("tv_names")
    return spark.sql("SELECT p_name, pos, term FROM tv_names, LATERAL tv_words(p_name)")


@add("SELECT vec_id, label * 2 AS twice FROM embeddings")
def op_map_in_arrow(spark, sf):
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pc.multiply(b.column(1), pa.scalar(2, pa.int32()))], names=["vec_id", "twice"])

    return t(spark, sf, "embeddings").select("vec_id", "label").mapInArrow(work, "vec_id long, twice int")


@add("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY l_returnflag")
def op_grouped_map(spark, sf):
    def total(x: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"l_returnflag": [x["l_returnflag"].iloc[0]], "n": [int(x["n"].sum())], "quantity": [round(float(x["quantity"].sum()), 2)]})

    small = t(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))
    return small.groupBy("l_returnflag").applyInPandas(total, "l_returnflag string, n long, quantity double")


@add(f"SELECT vec_id, round(sqrt(list_dot_product({_E}, {_E})), 6) AS norm, round(list_cosine_similarity({_E}, list_reverse({_E})), 6) + 0.0 AS cosine FROM embeddings")
def op_vec_sql_functions(spark, sf):
    from tablevec.functions.vectors import register

    register(spark)
    t(spark, sf, "embeddings").select("vec_id", c("embedding").cast("array<double>").alias("e")).createOrReplaceTempView("tv_vectors")
    return spark.sql("SELECT vec_id, round(vec_norm(vec_unit(e)) * vec_norm(e), 6) AS norm, round(vec_cosine(e, reverse(e)), 6) + 0D AS cosine FROM tv_vectors")


@add("SELECT doc_id FROM documents ORDER BY md5(doc_id::VARCHAR), doc_id LIMIT 50")
def op_sample_hash_order(spark, sf):
    return r.sample_exact(t(spark, sf, "documents").select("doc_id"), 50, "doc_id")


@add("SELECT lang, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY lang ORDER BY md5(doc_id::VARCHAR), doc_id) <= 20")
def op_sample_each_label(spark, sf):
    return r.sample_each(t(spark, sf, "documents").select("lang", "doc_id"), "lang", 20, "doc_id")
