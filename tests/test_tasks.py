"""Samples, networks, scores, streams and upkeep."""

import random
import time
from datetime import datetime, timedelta

import numpy as np

import pytest
from pyspark.sql import functions as F

from tablevec import database as d
from tablevec.operators import extract, solvers
from tablevec.operators import relational as r
from tablevec.operators.weights import Params
from tablevec.spec import COMMERCE, MINI, load_tables
from tablevec.streaming import upkeep as u
from tablevec.tasks import nets, samples, scores


@pytest.mark.parametrize("kind", ["binary", "categories", "regression", "link"])
def test_gradients_against_differences(kind):
    rng = np.random.default_rng(1)
    s = nets.Settings((7, 5), dropout=0.0, l2=0.0, seed=3)
    n_out = 3 if kind == "categories" else 1
    net, x = nets.Net(kind, 6, n_out, s), rng.normal(size=(9, 6))
    y = rng.integers(0, 3, 9) if kind == "categories" else rng.normal(size=9) if kind == "regression" else rng.integers(0, 2, 9).astype(float)
    gw, gb = net.gradients(x, y)
    for params, grads in ((net.w, gw), (net.b, gb)):
        for p, g in zip(params, grads):
            spot = np.unravel_index(int(np.abs(g).argmax()), g.shape)
            keep, diff = p[spot], []
            for h in (1e-6, -1e-6):
                p[spot] = keep + h
                diff.append(net.loss(x, y))
            p[spot] = keep
            assert np.isclose((diff[0] - diff[1]) / 2e-6, g[spot], rtol=1e-3, atol=1e-7)


def test_networks_learn_what_no_line_can_tell():
    rng = np.random.default_rng(2)
    x = rng.choice([-1.0, 1.0], (600, 2)) + rng.normal(0, 0.1, (600, 2))
    y = (x[:, 0] * x[:, 1] > 0).astype(float)
    s = nets.Settings((32,), dropout=0.0, l2=0.0, rate=2e-2, max_epochs=200)
    assert ((nets.train("binary", x[:400], y[:400], s).output(x[400:])[:, 0] > 0.5) == y[400:]).mean() > 0.95
    z = np.concatenate([x, rng.permutation(x)], axis=1)
    same = (np.sign(z[:, 0]) == np.sign(z[:, 2])).astype(float)
    link = nets.train("link", z[:400], same[:400], nets.Settings((24, 16), dropout=0.0, l2=0.0, rate=1e-2, max_epochs=200))
    assert ((link.output(z[400:])[:, 0] > 0.5) == same[400:]).mean() > 0.9


def test_best_weights_are_kept_when_training_stops():
    rng = np.random.default_rng(3)
    x, y = rng.normal(size=(80, 4)), rng.integers(0, 2, 80).astype(float)  # nothing to learn
    net = nets.train("binary", x, y, nets.Settings((64,), rate=5e-2, dropout=0.0, patience=5, max_epochs=80, seed=4))
    order = np.random.default_rng(4).permutation(80)[:8]
    assert net.loss(x[order], y[order]) < 1.0


def test_recurrent_encoder_tells_alphabets_apart():
    rng = np.random.default_rng(5)
    texts = ["".join(rng.choice(list("abcd" if i % 2 else "wxyz"), 20)) for i in range(120)]
    net = nets.Recurrent(2, width=8, length=20).fit(texts[:80], np.array([i % 2 for i in range(80)]), epochs=8)
    assert (net.predict(texts[80:]) == [i % 2 for i in range(80, 120)]).mean() > 0.9


def test_recurrent_encoder_reads_texts_to_their_end():
    rng = np.random.default_rng(7)
    texts = ["".join(rng.choice(list("mnop"), 50)) + "".join(rng.choice(list("abcd" if i % 2 else "wxyz"), 37)) for i in range(120)]
    net = nets.Recurrent(2, width=8, length=20).fit(texts[:80], np.array([i % 2 for i in range(80)]), epochs=12)
    assert (net.predict(texts[80:]) == [i % 2 for i in range(80, 120)]).mean() > 0.9


def test_imputation_counts_ngrams_of_whole_texts(spark, monkeypatch):
    from types import SimpleNamespace

    from tablevec.queries import tasks
    from tablevec.tasks import samples as drawn, workloads

    class Rows:
        def __getattr__(self, name):
            return lambda *a, **k: self

        def count(self):
            return 10

        def withColumn(self, name, column):
            seen.append(str(column))
            return self

    seen = []
    for name, made in (("text_labels", Rows()), ("method_vectors", None), ("_with_vectors", None)):
        monkeypatch.setattr(workloads, name, lambda *a, made=made, **k: made)
    monkeypatch.setattr(workloads, "Stages", lambda *a: SimpleNamespace(keep=lambda x: x))
    monkeypatch.setattr(workloads.d, "database", lambda *a, **k: None)
    monkeypatch.setattr(drawn, "train_test", lambda *a, **k: Rows())
    for name in ("predict", "impute_mode", "impute_ngram", "accuracy"):
        monkeypatch.setattr(scores, name, lambda *a, **k: Rows())
    workloads.run_imputation(None, "x", "lang")
    tasks.impute_ngram_recurrent_lang(None, "x")
    assert len(seen) == 2 and not [c for c in seen if "left" in c.lower() or "substr" in c.lower()]


def test_samples_are_exact_and_reproducible(spark):
    rows = spark.createDataFrame([(i, "a" if i < 30 else "b") for i in range(100)], "k long, label string")
    got = samples.balanced(rows, "k", "label", 20, 3).toPandas()
    assert len(got) == 3 * 40 and (got.groupby(["trial", "label"]).size() == 20).all() and (got.groupby(["trial", "split"]).size() == 20).all()
    again = samples.balanced(rows.repartition(7), "k", "label", 20, 3).toPandas()
    assert set(map(tuple, got.values)) == set(map(tuple, again.values))
    split = samples.train_test(rows, "k", 60, 25, 2).toPandas()
    assert (split.groupby(["trial", "split"]).size().unstack() == [25, 60]).all().all()
    clear = spark.createDataFrame([("x", 1), ("x", 1), ("y", 0), ("y", 1), ("z", None), (None, 1)], "key string, label int")
    assert [tuple(v) for v in samples.without_ambiguity(clear, "key", "label").collect()] == [("x", 1)]


def test_balanced_labels_of_the_query_have_no_cap(spark, tmp_path):
    from tablevec.queries.tasks import sample_balanced_labels

    spark.range(6500).selectExpr("id AS doc_id", "CAST(id % 2 AS INT) AS quality", "0 AS toxic").write.parquet(f"{tmp_path}/labels.parquet")
    got = sample_balanced_labels(spark, str(tmp_path)).groupBy("label", "split").count().toPandas()
    assert sorted(got["count"]) == [1625] * 4


def test_many_rows_of_small_files_are_not_broadcast(spark, monkeypatch):
    from tablevec.plans import stages

    monkeypatch.setattr(stages, "BROADCAST_ROWS", 1000, raising=False)
    kept = stages.Stages(spark, "wide")
    zeros = kept.keep(spark.range(5000).selectExpr("id", "array_repeat(0D, 64) AS vec"))
    few = kept.keep(spark.range(10).toDF("id"))
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan(zeros.select("id", "vec").join(kept.keep(spark.range(5000).toDF("id")), "id"))
    assert "Broadcast" in plan(zeros.join(F.broadcast(few), "id"))


def test_negatives_are_no_links(spark):
    links = spark.createDataFrame([(f"s{i}", f"t{i % 5}") for i in range(40)], "src string, dst string")
    got = {tuple(v) for v in samples.negative_links(links, 60).collect()}
    assert len(got) == 60 and not got & {tuple(v) for v in links.collect()}
    full = spark.createDataFrame([(a, b) for a in "xy" for b in "pq"], "src string, dst string")
    assert samples.negative_links(full, 5).count() == 0


def test_mode_ties_and_spread(spark):
    rows = spark.createDataFrame([(0, "train", "b"), (0, "train", "a"), (1, "train", "c"), (1, "test", "d")], "trial int, split string, label string")
    assert {r["trial"]: r["pred"] for r in scores.impute_mode(rows, "label").collect()} == {0: "a", 1: "c"}
    made = spark.createDataFrame([("t", "m", i, "accuracy", v) for i, v in enumerate([0.2, 0.4, 0.6])], scores.SCORES)
    got = scores.score_spread(made).first()
    assert (got["low"], got["median"], got["high"], got["n"]) == (0.2, 0.4, 0.6, 3) and abs(got["sd"] - 0.2) < 1e-9


def test_trials_are_learned_side_by_side(spark):
    rng = np.random.default_rng(6)
    rows = [("m", t, "train" if i < 60 else "test", str(i), [float(y) + float(rng.normal(0, 0.2)), 1.0], "yes" if y else "no") for t in range(2) for i in range(100) for y in [i % 2]]
    df = spark.createDataFrame(rows, "method string, trial int, split string, item string, features array<double>, label string")
    s = nets.Settings((16,), rate=2e-2, max_epochs=60)
    for got in (scores.accuracy(scores.predict(df, "binary", s), "t"), scores.accuracy(scores.predict(df, "categories", s), "t"), scores.accuracy(scores.probe(df), "t")):
        assert [r["value"] > 0.9 for r in got.collect()] == [True, True]
    numbers = df.withColumn("label", F.get("features", F.lit(0)).cast("string"))
    assert max(r["value"] for r in scores.mean_abs_error(scores.predict(numbers, "regression", nets.Settings((16, 16), rate=1e-2, max_epochs=80)), "t").collect()) < 0.25


def test_ngrams_tell_words_apart(spark):
    rows = [(0, "train" if i < 60 else "test", str(i), "lorem ipsum dolor" if i % 2 else "uno dos tres", "x" if i % 2 else "y") for i in range(100)]
    df = spark.createDataFrame(rows, "trial int, split string, item string, text string, label string")
    for encoder in ("linear", "recurrent"):
        assert scores.accuracy(scores.impute_ngram(df, "text", "label", encoder), "t").first()["value"] > 0.95


def test_late_events_are_dropped_and_streams_equal_batches(spark, tmp_path):
    at = lambda m: datetime(2024, 1, 1) + timedelta(minutes=m)
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    folder = tmp_path / "data"
    first = spark.createDataFrame([(1, at(0), 1, "a", 1.0, "{}"), (2, at(600), 1, "a", 1.0, "{}")], schema).coalesce(1)
    middle = spark.createDataFrame([(5, at(601), 1, "a", 1.0, "{}")], schema).coalesce(1)
    second = spark.createDataFrame([(3, at(5), 1, "a", 1.0, "{}"), (4, at(900), 1, "b", 1.0, "{}")], schema).coalesce(1)
    first.write.parquet(str(folder / "events.parquet"))
    time.sleep(1.1)  # files are taken by their time of change
    middle.write.mode("append").parquet(str(folder / "events.parquet"))
    time.sleep(1.1)
    second.write.mode("append").parquet(str(folder / "events.parquet"))
    every = {(r["event_type"], r["n"]) for r in u.drained(u.windowed_counts(u.event_stream(spark, str(folder)), "tumbling"), "complete").collect()}
    assert every == {("a", 2), ("b", 1)}
    kept = u.drained(u.windowed_counts(u.event_stream(spark, str(folder)), "tumbling", "2 hours")).collect()
    assert [r["n"] for r in kept if r["start"] == at(0)] == [1]  # the event of minute 5 came after minute 600 had passed
    values = u.drained(u.stream_values(u.event_stream(spark, str(folder)), "events", "event_type"))
    assert sorted(r["value"] for r in values.collect()) == ["a", "b"]
    rows = u.event_stream(spark, str(folder)).select(F.col("event_type").alias("src"), F.col("event_id").cast("string").alias("dst"))
    degrees = u.drained(u.running_degrees(rows)).groupBy("src").agg(F.max("degree").alias("n")).collect()
    assert {r["src"]: r["n"] for r in degrees} == {"a": 4, "b": 1}


def test_refresh_reaches_the_fit_from_the_beginning(spark, tiny):
    db, p = d.database(spark, tiny, MINI), Params(2, 1, 1, 0.1)
    fitted = solvers.fit_objective(db.problem, p, 30).vectors
    new_row = db.frames["customer"].limit(1).withColumn("c_name", F.lit("someone new"))
    frames = {**db.frames, "customer": db.frames["customer"].unionByName(new_row)}
    new, warm = u.refresh_vectors(db, fitted, frames, MINI, p, 25)
    cold = solvers.fit_objective(new.problem, p, 40).vectors
    a, b = ({r["node_id"]: np.array(r["vec"]) for r in x.collect()} for x in (warm, cold))
    assert len(a) == db.nodes.count() + 1 and max(np.abs(a[k] - b[k]).max() for k in a) < 1e-4


@pytest.mark.parametrize("table,key,least", [("lineitem", "l_orderkey", 1400), ("part", "p_partkey", 190), ("customer", "c_custkey", 140)])
def test_links_of_new_rows_are_all_that_is_missing(spark, tiny, table, key, least):
    frames = load_tables(spark, tiny, COMMERCE)
    before = {**frames, table: frames[table].where(F.col(key) < least)}
    more = extract.links_of_new_rows(frames, table, frames[table].where(F.col(key) >= least), COMMERCE)
    names = ["rel", "src_category", "src", "dst_category", "dst"]
    both = extract.extract_links(before, COMMERCE).select(names).union(more.select(names)).distinct()
    whole = extract.extract_links(frames, COMMERCE).select(names)
    assert more.count() and not both.exceptAll(whole).count() and not whole.exceptAll(both).count()


def test_new_rows_move_only_what_they_touch(spark, tiny):
    db, p = d.database(spark, tiny, MINI), Params(2, 1, 1, 0.1)
    fitted = solvers.fit_objective(db.problem, p, 5).vectors
    old_row = db.frames["customer"].orderBy("c_custkey").limit(1)
    rows = old_row.unionByName(old_row.withColumn("c_name", F.lit("someone new")))
    new, touched = d.extend(db, "customer", rows.unionByName(rows))
    built = d.build(spark, {**db.frames, "customer": db.frames["customer"].unionByName(rows)}, MINI, db.lexicon)
    for a, b, names in ((new.nodes, built.nodes, ["category", "value"]), (new.links, built.links, ["rel", "src", "dst"]), (new.hits.join(new.nodes, "node_id"), built.hits.join(built.nodes, "node_id"), ["category", "value", "pos", "term"])):
        assert sorted(map(tuple, a.select(names).collect())) == sorted(map(tuple, b.select(names).collect()))
    ids = {r["node_id"] for r in touched.collect()}
    assert len(ids) == 3 and new.problem.links.count() == built.problem.links.count()  # the new name, its segment, its nation
    vectors = lambda x: {r["node_id"]: np.array(r["vec"]) for r in x.collect()}
    before, after = vectors(fitted), vectors(u.local_sweeps(new, fitted, touched, p, 2, hops=0))
    assert len(after) == len(before) + 1 and all((after[k] == before[k]).all() for k in before if k not in ids)
    again, nothing = d.extend(new, "customer", rows)
    assert nothing.isEmpty() and again.nodes.count() == new.nodes.count() and again.links.count() == new.links.count()
    cold = vectors(solvers.fit_objective(new.problem, p, 40).vectors)
    warm = vectors(u.local_sweeps(d.compacted(new), fitted, touched, p, 25, hops=9))
    assert max(np.abs(cold[k] - warm[k]).max() for k in cold) < 1e-4


def test_vectors_are_written_by_column(spark, tiny, tmp_path):
    out = d.run_pipeline(spark, {"folder": tiny, "spec": MINI, "method": "series", "iters": 2, "path": str(tmp_path / "v")})
    back = spark.read.parquet(str(tmp_path / "v"))
    assert back.count() == out.count() and back.where("category = 'region.r_name'").count() == 5


def test_joins_in_time(spark):
    at = lambda s: datetime(2024, 1, 1) + timedelta(seconds=s)
    a = spark.createDataFrame([(1, "u", at(0)), (2, "u", at(100)), (3, "v", at(50))], "id long, by string, ts timestamp")
    b = spark.createDataFrame([(7, "u", at(60)), (8, "u", at(700)), (9, "v", at(0))], "id long, by string, ts timestamp")
    assert {(x["id"], x["id_r"]) for x in r.interval_join(a, b, "by", "ts", 60).collect()} == {(1, 7), (2, 7), (3, 9)}
    assert {(x["id"], x["last_id"]) for x in r.as_of_join(a.withColumnRenamed("id", "k").withColumnRenamed("k", "id"), b, "by", "ts", "id").collect()} == {(1, None), (2, 7), (3, 9)}


def test_scoring_and_distributed_training(spark):
    from tablevec.operators.graph import score_all

    rng = np.random.default_rng(8)
    rows = [(i, [float(i % 2) * 2 - 1 + float(rng.normal(0, 0.1)), 0.5], i % 2) for i in range(200)]
    df = spark.createDataFrame(rows, "node_id long, features array<double>, label int")
    assert scores.train_distributed(df, 2, (4,)).numClasses == 2
    got = {r["node_id"]: r["score"] for r in score_all(df.withColumnRenamed("features", "vec"), [(np.array([[5.0], [0.0]]), np.zeros(1))]).collect()}
    assert all((s > 0.5) == (i % 2 == 1) for i, s in got.items())


def test_sources_and_sinks(spark, tmp_path):
    from tablevec.sources import io

    few = io.load(spark, "/root/testdata/sf0.001", "orders", ["o_orderkey"], "o_totalprice > 1000")
    assert few.columns == ["o_orderkey"]
    io.save(few.withColumn("k", F.col("o_orderkey") % 3), str(tmp_path / "p"), ["k"])
    assert spark.read.parquet(str(tmp_path / "p")).count() == few.count()
    few.limit(5).coalesce(1).write.csv(str(tmp_path / "c"), header=True)
    few.limit(5).coalesce(1).write.json(str(tmp_path / "j"))
    assert io.read_csv(spark, str(tmp_path / "c"), "o_orderkey long").count() == io.read_json_lines(spark, str(tmp_path / "j"), "o_orderkey long").count() == 5


def test_all_free_pairs_are_found_when_all_are_asked(spark):
    rng = random.Random(4)
    every = [(f"s{i}", f"t{j}") for i in range(10) for j in range(10)]
    linked = rng.sample(every, 60)
    links = spark.createDataFrame(linked + linked[:5] + [(None, "t1"), ("s1", None)], "src string, dst string")
    ends = {s for s, _ in linked}, {t for _, t in linked}
    free = {(s, t) for s, t in every if s in ends[0] and t in ends[1]} - set(linked)
    got = [tuple(r) for r in samples.negative_links(links, len(free)).collect()]
    assert len(got) == len(free) and set(got) == free
    assert {tuple(r) for r in samples.negative_links(links, 1000).collect()} == free


def test_only_the_vectors_of_drawn_values_go_on(spark, tiny, monkeypatch):
    from tablevec.tasks import workloads

    db, seen = d.database(spark, tiny), []
    kept = workloads.Stages.keep

    def keep(self, df, **options):
        out = kept(self, df, **options)
        seen.append((self.root, out)) if "vec" in out.columns or "features" in out.columns else None
        return out

    monkeypatch.setattr(workloads.Stages, "keep", keep)
    rows = spark.createDataFrame([("NATION_1", "yes"), ("NATION_3", "no"), ("no nation", "no")], "item string, label string")
    one = workloads.method_vectors(db, ("base", "series"), of=((rows, "nation.n_name"),))
    every = {(r["method"], r["node_id"]): r["features"] for r in workloads.method_vectors(db, ("base", "series")).collect()}
    names = {r["node_id"]: r["value"] for r in db.nodes.where("category = 'nation.n_name'").collect()}
    got = {(r["method"], r["node_id"]): r["features"] for r in one.collect()}
    assert sorted((m, names[n]) for m, n in got) == [(m, n) for m in ("base", "series") for n in ("NATION_1", "NATION_3")]
    assert all(np.allclose(v, every[k]) for k, v in got.items())
    seen.clear()
    made = workloads._with_vectors(rows, db, "nation.n_name", one)
    assert made.count() == 4 and all(df.count() <= 4 for root, df in seen)


def test_samples_of_long_keys_are_drawn_by_digests(spark):
    rows = spark.createDataFrame([(f"{i % 40} " + "x" * 50, None if i % 3 == 0 else f"{i % 3}") for i in range(80)], "k string, label string")
    near = samples.least(samples.trials(rows, 2).withColumn("_place", r.hash_order("trial", "k")), ["trial", "label"], 5)
    assert {(q["trial"], q["label"]): q["count"] for q in near.groupBy("trial", "label").count().collect()} == {(t, c): n for t in (0, 1) for c in (None, "1", "2") for n in [near.where(F.col("trial") == t).where(F.col("label").eqNullSafe(c)).count()] if 5 <= n < 12}
    split = samples.train_test(rows, "k", 6, 3, 2).collect()
    order = samples.trials(rows, 2).withColumn("h", r.hash_order("trial", "k")).toPandas()
    for t in (0, 1):
        first = order[order["trial"] == t].sort_values("h")["k"].tolist()[:9]
        assert sorted(q["k"] for q in split if q["trial"] == t) == sorted(first)
    assert samples.least(rows.withColumn("_place", F.md5("k")), [], 7).count() in (7, 8)
