"""The methods against dense algebra, worked cases and each other."""

from dataclasses import replace
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from tablevec.operators import extract, graph, lexicon, solvers
from tablevec.operators import weights as w
from tablevec.operators.weights import Params
from tablevec.plans import checks
from tablevec.spec import COMMERCE, MINI, ForeignKey, LinkTable, SchemaSpec, infer_text

TOY = [("r", 2, 0), ("r", 3, 1), ("r", 4, 1)]


def problem(spark, base, categories, links, dims=2):
    rows = spark.createDataFrame([(i, c, f"v{i}", [float(x) for x in v], not any(v)) for i, (c, v) in enumerate(zip(categories, base))], "node_id long, category string, value string, vec array<double>, is_oov boolean")
    both = [(r, inv, *((b, a) if inv else (a, b))) for r, a, b in links for inv in (False, True)]
    return solvers.Problem(rows, spark.createDataFrame(both, "rel string, rel_inv boolean, src long, dst long"), dims)


def toy(spark, seed=0):
    base = np.random.default_rng(seed).normal(size=(5, 2))
    return problem(spark, base, ["c", "c", "t", "t", "t"], TOY), base


def dense(base, categories, links, p: Params):
    """H and right-hand side of the objective's stationary point, from the loss itself, and its loss function."""
    n = len(base)
    groups = {}
    for r, a, b in links:
        groups.setdefault((r, False), set()).add((a, b))
        groups.setdefault((r, True), set()).add((b, a))
    k = [len({g for g, e in groups.items() if any(a == i for a, _ in e)}) for i in range(n)]
    cent = {c: np.mean([base[i] for i in range(n) if categories[i] == c], axis=0) for c in set(categories)}
    alpha, beta = np.full(n, float(p.base)), np.array([p.column / (k[i] + 1) for i in range(n)])
    pull, push = np.zeros((n, n)), np.zeros((n, n))
    for e in groups.values():
        src, dst = {a for a, _ in e}, {b for _, b in e}
        delta = p.repel / (max(len(src), len(dst)) * max(k[i] + 1 for i in src | dst))
        for a, b in product(src, dst):
            if (a, b) in e:
                pull[a, b] += p.link / (sum(x == a for x, _ in e) * (k[a] + 1))
            else:
                push[a, b] += delta
    s = pull - push
    both = s + s.T
    h = np.diag(alpha + beta + both.sum(axis=1)) - both
    rhs = alpha[:, None] * base + beta[:, None] * np.array([cent[c] for c in categories])

    def terms(x):
        gap = ((x[:, None, :] - x[None, :, :]) ** 2).sum(axis=2)
        away = ((x - np.array([cent[c] for c in categories])) ** 2).sum(axis=1)
        return (alpha * ((x - base) ** 2).sum(axis=1)).sum(), (beta * away).sum(), (pull * gap).sum(), (push * gap).sum()

    return h, rhs, terms, push


def vectors(fit):
    return np.array([r["vec"] for r in fit.vectors.orderBy("node_id").collect()])


CATEGORIES = ["c", "c", "t", "t", "t"]


@pytest.mark.parametrize("repel", [0, 1, 2])
def test_objective_reaches_the_solution_of_the_linear_system(spark, repel):
    p, base = toy(spark)
    params = Params(2, 1, 3, repel)
    h, rhs, terms, _ = dense(base, CATEGORIES, TOY, params)
    want = np.linalg.solve(h, rhs)
    for update in ("jacobi", "block_seidel"):
        assert np.allclose(vectors(solvers.fit_objective(p, params, 200, update=update)), want, atol=1e-8)
    other = p.base.select("node_id", F.array(F.lit(5.0), F.lit(-7.0)).alias("vec"))
    assert np.allclose(vectors(solvers.fit_objective(p, params, 200, start=other)), want, atol=1e-8)
    got = solvers.objective_loss(p, spark.createDataFrame([(i, [float(a) for a in v]) for i, v in enumerate(want)], "node_id long, vec array<double>"), params).first()
    assert np.allclose([got["base_loss"], got["column_loss"], got["link_loss"], got["nonlink_loss"]], terms(want), atol=1e-8)


def test_large_repulsion_drifts_away(spark):
    p, base = toy(spark, 3)
    steps = lambda r: [s["rel_step"] for s in solvers.fit_objective(p, Params(2, 1, 3, r), 60).history]
    assert steps(2)[-1] < 1e-3 < 0.2 < steps(4)[-1]


def test_each_weight_lowers_its_own_penalty(spark):
    p, base = toy(spark, 5)

    def part(params, term, unit):
        _, _, terms, _ = dense(base, CATEGORIES, TOY, unit)
        return terms(vectors(solvers.fit_objective(p, params, 120)))[term]

    for term, settings in enumerate([[Params(v, 1, 2, 1) for v in (2, 3)], [Params(2, v, 2, 1) for v in (1, 3)], [Params(2, 1, v, 1) for v in (1, 3)]]):
        unit = Params(1, 1, 1, 1)
        assert part(settings[1], term, unit) <= part(settings[0], term, unit) + 1e-9
    assert part(Params(2, 1, 3, 1), 3, Params(1, 1, 1, 1)) >= part(Params(2, 1, 3, 0), 3, Params(1, 1, 1, 1))


def test_kernels_and_ways_agree(spark):
    p, _ = toy(spark, 7)
    for make in (lambda **m: solvers.fit_series(p, Params(1, 0.5, 3, 1), 4, **m), lambda **m: solvers.fit_objective(p, Params(2, 1, 3, 1), 4, **m), lambda **m: solvers.fit_graph_baseline(p, 4, **m)):
        assert np.allclose(vectors(make(kernel="shuffle")), vectors(make(kernel="broadcast")), atol=1e-12)
    assert np.allclose(vectors(solvers.fit_objective(p, Params(2, 1, 3, 1), 3)), vectors(solvers.fit_objective(p, Params(2, 1, 3, 1), 3, nonlinks="bruteforce")))
    assert np.allclose(vectors(solvers.fit_series(p, iters=3)), vectors(solvers.fit_series(p, iters=3, totals="per_node")))


def test_series_rows_have_length_one_or_zero(spark):
    p = problem(spark, [[1, 0], [0, 1], [0, 0], [0, 0]], ["a", "b", "b", "z"], [("r", 0, 1), ("r", 0, 2)])
    for params in (Params(1, 0, 1, 3), Params(1, 0, 3, 1), Params(1, 1, 1, 50)):
        n = np.linalg.norm(vectors(solvers.fit_series(p, params, 6)), axis=1)
        assert np.allclose(n[:3], 1) and n[3] == 0


def test_complete_groups_have_no_repulsion_in_the_objective(spark):
    base = np.random.default_rng(1).normal(size=(4, 2))
    full = [("r", a, b) for a in (0, 1) for b in (2, 3)]
    p = problem(spark, base, ["a", "a", "b", "b"], full)
    assert np.allclose(vectors(solvers.fit_objective(p, Params(1, 0, 2, 0), 5)), vectors(solvers.fit_objective(p, Params(1, 0, 2, 9), 5)))
    assert not np.allclose(vectors(solvers.fit_series(p, Params(1, 0, 2, 0), 2)), vectors(solvers.fit_series(p, Params(1, 0, 2, 3), 2)))


def test_nodes_outside_a_group_feel_nothing_of_it(spark):
    base = np.random.default_rng(2).normal(size=(5, 2))
    p = problem(spark, base, ["a", "a", "b", "b", "a"], [("r", 0, 2), ("r", 1, 3)])
    assert np.allclose(vectors(solvers.fit_objective(p, Params(1, 0, 3, 1), 10))[4], base[4])


def test_equal_vectors_are_a_fixed_point(spark):
    p = problem(spark, [[3.0, 4.0]] * 5, CATEGORIES, TOY)
    assert np.allclose(vectors(solvers.fit_objective(p, Params(2, 1, 3, 1), 20)), [3, 4])
    assert np.allclose(np.abs(vectors(solvers.fit_series(p, Params(3, 1, 3, 0.5), 5))), [0.6, 0.8])


def test_self_groups_and_repeated_strings(spark):
    p = problem(spark, np.random.default_rng(4).normal(size=(3, 2)), ["t"] * 3, [("next", 0, 1), ("next", 1, 2)])
    assert np.allclose(vectors(solvers.fit_objective(p, Params(3, 1, 1, 0.1), 80)), vectors(solvers.fit_objective(p, Params(3, 1, 1, 0.1), 80, update="block_seidel")), atol=1e-8)


def test_graph_baseline_by_hand(spark):
    p = problem(spark, [[1.0, 0.0], [0.0, 1.0]], ["a", "b"], [("r", 0, 1)])
    assert np.allclose(vectors(solvers.fit_graph_baseline(p, 1)), [[0.5, 0.5], [0.5, 0.5]])
    assert np.allclose(vectors(solvers.fit_graph_baseline(p, 60)), [[2 / 3, 1 / 3], [1 / 3, 2 / 3]])
    assert np.allclose(vectors(solvers.fit_graph_baseline(p, 1, update="exact")), [[1 / 3, 2 / 3], [2 / 3, 1 / 3]])


def test_convexity_bounds(spark):
    """The published slack may be positive where curvature is negative; ours never is."""
    base = np.zeros((4, 2))
    match = [("r", 0, 2), ("r", 1, 3)]
    p = problem(spark, base, ["a", "a", "b", "b"], match)
    h, _, _, push = dense(base, ["a", "a", "b", "b"], match, Params(1, 0, 0, 4.0))
    rows = w.convexity_report(p.base, p.links, Params(1, 0, 0, 4.0)).collect()
    assert min(r["slack_stated"] for r in rows) > 0 > np.linalg.eigvalsh(h).min()
    rng = np.random.default_rng(3)
    for _ in range(6):
        links = [("r", a, b) for a in range(3) for b in range(3, 6) if rng.random() < 0.5] or [("r", 0, 3)]
        params, cats = Params(1, rng.random(), 1, rng.random() * 3), ["a"] * 3 + ["b"] * 3
        p = problem(spark, np.zeros((6, 2)), cats, links)
        h, _, _, _ = dense(np.zeros((6, 2)), cats, links, params)
        least = w.convexity_report(p.base, p.links, params).agg(F.min("slack_sufficient")).first()[0]
        assert least <= 0 or np.linalg.eigvalsh(h).min() > 0
    with pytest.raises(ValueError):
        w.warn_if_unsafe(p.base, p.links, Params(1, 0, 1, 99, strict=True))
    with pytest.raises(ValueError):
        w.warn_if_unsafe(p.base, p.links, Params(-1, 0, 1, 0))


# extraction and matching


def _frames(spark):
    a = spark.createDataFrame([(1, "x", "same", 1), (2, "x", "y", 1), (3, None, "same", None), (4, "", "z", 2)], "id long, p string, q string, fk long")
    b = spark.createDataFrame([(1, "same"), (2, "other"), (3, None)], "bid long, r string")
    t = spark.createDataFrame([(1, 1), (1, 1), (2, 3), (3, 2), (None, 1)], "l long, m long")
    return {"a": a, "b": b, "t": t}


SPEC = SchemaSpec({"a": ("p", "q"), "b": ("r",)}, (ForeignKey("a", "fk", "b", "bid"),), (LinkTable("t", "l", "a", "id", "m", "b", "bid"),))


def test_values_links_nulls_and_sets(spark):
    f = _frames(spark)
    assert {tuple(r) for r in extract.extract_values(f, SPEC).collect()} == {("a.p", "x"), ("a.q", "same"), ("a.q", "y"), ("a.q", "z"), ("b.r", "same"), ("b.r", "other")}
    got = sorted((r["rel"], r["src"], r["dst"]) for r in extract.extract_links(f, SPEC).collect())
    assert got == sorted([("row:a.p>a.q", "x", "same"), ("row:a.p>a.q", "x", "y"), ("fk:a.p>b.r", "x", "same"), ("fk:a.q>b.r", "same", "same"), ("fk:a.q>b.r", "y", "same"), ("fk:a.q>b.r", "z", "other"), ("nm:a.p>b.r", "x", "same"), ("nm:a.q>b.r", "same", "same"), ("nm:a.q>b.r", "same", "other")])
    assert not [r for r in extract.extract_links(f, SPEC.without("b.r")).collect() if "b.r" in r["rel"]]
    assert not [r for r in extract.extract_links(f, SPEC.without(relation=("a.q", "b.r"))).collect() if "a.q>b.r" in r["rel"]]
    assert {r["rel"].split(":")[0] for r in extract.extract_links(f, SPEC.only("nm")).collect()} == {"nm"}
    assert infer_text(f) == {"a": ("p", "q"), "b": ("r",), "t": ()}
    with pytest.raises(ValueError):
        extract.extract_values(f, SPEC, unique="per_occurrence")


def test_ids_are_dense_and_ordered(spark):
    df = spark.range(1000).select(F.concat(F.lit("k"), F.format_string("%05d", F.col("id"))).alias("value")).repartition(7)
    got = [r["node_id"] for r in extract.dense_ids(df, ["value"]).orderBy("value").collect()]
    assert got == list(range(1000))


def test_json_lists(spark):
    df = spark.createDataFrame([(1, '[{"k":"a"},{"k":"b"}]'), (2, "[]"), (3, "broken"), (4, None)], "id long, js string")
    got = sorted((r["id"], r["entry"]["k"] if r["entry"] else None) for r in extract.expand_json(df, "js", "struct<k:string>", "id").collect())
    assert got == [(1, "a"), (1, "b"), (2, None), (3, None), (4, None)]


def test_containment_with_short_and_long_passages(spark):
    texts = spark.createDataFrame([("a long text with a passage that is longer than the head of it",), ("short",), ("",)], "src string")
    passages = spark.createDataFrame([("passage that is longer than the head",), ("ort",), ("no such passage in any of the texts here",), ("",)], "dst string")
    assert {tuple(r) for r in extract.containment_links(texts, passages).collect()} == {("a long text with a passage that is longer than the head of it", "passage that is longer than the head"), ("short", "ort")}


LEXICON = [("bank", [1.0, 0.0]), ("account", [0.0, 1.0]), ("bank account", [4.0, 4.0]), ("a b", [1.0, 1.0]), ("b c d", [2.0, 2.0]), ("d", [8.0, 0.0])]


def _lexicon(spark):
    return spark.createDataFrame([(t, t.split(" "), len(t.split(" ")), v) for t, v in LEXICON], "term string, tokens array<string>, n_tokens int, vec array<double>")


@pytest.mark.parametrize("mode", ["trie", "join"])
def test_longest_phrases_win_from_the_left(spark, mode):
    values = ["Bank account", "bank, BANK", "my bank-account account", "a b c d", "nothing here", "account a", "b c"]
    nodes = spark.createDataFrame([(i, "c", v) for i, v in enumerate(values)], "node_id long, category string, value string")
    hits = {}
    for r in sorted(lexicon.match_phrases(nodes, _lexicon(spark), mode).collect(), key=lambda r: (r["node_id"], r["pos"])):
        hits.setdefault(r["node_id"], []).append(r["term"])
    assert hits == {0: ["bank account"], 1: ["bank", "bank"], 2: ["bank account", "account"], 3: ["a b", "d"], 5: ["account"]}
    base = {r["node_id"]: r for r in lexicon.init_vectors(nodes, lexicon.match_phrases(nodes, _lexicon(spark), mode), _lexicon(spark), 2).collect()}
    assert base[2]["vec"] == [2.0, 2.5] and base[4]["vec"] == [0.0, 0.0] and base[4]["is_oov"] and not base[0]["is_oov"]


def test_self_trained_lexicon(spark):
    texts = spark.createDataFrame([("red green blue " * 20,), ("one two three " * 20,)], "text string")
    got = lexicon.train_lexicon(texts, 8).collect()
    assert {r["term"] for r in got} == {"red", "green", "blue", "one", "two", "three"} and all(len(r["vec"]) == 8 for r in got)


# graph and walks


def test_walks_follow_edges_and_do_not_depend_on_partitions(spark):
    p = problem(spark, np.eye(6, 2), ["a", "a", "a", "b", "b", "b"], [("r", 0, 3), ("r", 1, 3), ("r", 2, 4)])
    vertices, edges = graph.build_graph(p.base, p.links)
    assert vertices.where("kind = 'column'").count() == 2
    paths = graph.walks((vertices, edges), 3, 9, 5).collect()
    again = graph.walks((vertices.repartition(7), edges.repartition(5)), 3, 9, 5).collect()
    assert {r["walk_id"]: r["path"] for r in paths} == {r["walk_id"]: r["path"] for r in again}
    known = {(r["src"], r["dst"]) for r in edges.collect()}
    assert all((x, y) in known for r in paths for x, y in zip(r["path"], r["path"][1:])) and len(paths) == 3 * 8


def test_walks_reach_every_neighbour_of_a_hub(spark):
    import hashlib

    leaves = [f"v{i}" for i in range(10_050)]
    vertices = spark.createDataFrame([("hub", "column")] + [(v, "value") for v in leaves[:300]], "vertex string, kind string")
    edges = spark.createDataFrame([e for v in leaves for e in (("hub", v, "category"), (v, "hub", "category"))], "src string, dst string, label string")
    draw = lambda walk, step: int(hashlib.md5(f"1/{walk}/{step}".encode()).hexdigest()[:8], 16)
    nexts = sorted(leaves)
    got = {r["walk_id"]: r["path"] for r in graph.walks((vertices, edges), 1, 3, 1).collect()}
    assert len(got) == 301 and all(got[f"{v}#0"] == [v, "hub", nexts[draw(f"{v}#0", 2) % len(nexts)]] for v in leaves[:300])


def test_combinations_and_neighbours(spark):
    a = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 2.0]), (2, [0.0, 0.0])], "node_id long, vec array<double>")
    assert [r["vec"] for r in graph.combine_vectors(a, a, "concat").orderBy("node_id").collect()][1] == [0.0, 2.0, 0.0, 2.0]
    assert [r["vec"] for r in graph.combine_vectors(a, a, "average").orderBy("node_id").collect()][1] == [0.0, 2.0]
    assert [r["vec"] for r in graph.unit_vectors(a).orderBy("node_id").collect()] == [[1.0, 0.0], [0.0, 1.0], [0.0, 0.0]]
    named = spark.createDataFrame([(0, "c", "x", [1.0, 0.0]), (1, "c", "y", [1.0, 0.1]), (2, "c", "z", [0.0, 1.0])], "node_id long, category string, value string, vec array<double>")
    assert [r["value"] for r in graph.nearest_values(named, "x", 2).collect()] == ["y", "z"]
    assert graph.approximate_nearest(named, [1.0, 0.0], 1).first()["value"] == "x"
    assert graph.analogy(named, "x", "y", "z", 1).count() == 0 and graph.clusters(named, 2).count() == 3


# plans


def test_plans_hold_no_product_and_scans_are_pruned(spark):
    p, _ = toy(spark)
    step = solvers.objective_step(p, Params())
    assert not checks.has_cartesian(solvers.sweep(step, p.base.select("node_id", "vec")))
    frames = {t: spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("customer", "nation", "region")}
    plan = extract.extract_values(frames, MINI)
    assert all("acctbal" not in s for s in checks.read_schema(plan))
    orders = spark.read.parquet("/root/testdata/sf0.001/orders.parquet").where("o_totalprice > 5")
    assert any("GreaterThan(o_totalprice" in f for f in checks.pushed_filters(orders))
    assert "BroadcastHashJoin" in checks.joins(extract.links_fk({**frames, "nation": F.broadcast(frames["nation"])}, COMMERCE.keys[1], MINI))


def _matching(spark):
    """Two links between four nodes; repulsion of the same strength makes denominators of 0 and less."""
    base = [(i, c, f"{c}{i}", [float(i + 1), 1.0], False) for i, c in enumerate("aabb")]
    rows = spark.createDataFrame(base, "node_id long, category string, value string, vec array<double>, is_oov boolean")
    links = spark.createDataFrame([("r", inv, *(p[::-1] if inv else p)) for p in ((0, 2), (1, 3)) for inv in (False, True)], "rel string, rel_inv boolean, src long, dst long")
    return solvers.Problem(rows, links, 2)


@pytest.mark.parametrize("repel", [2.0, 6.0])
def test_kernels_agree_where_a_denominator_is_not_above_zero(spark, repel):
    p, weights = _matching(spark), Params(1, 0, 0, repel)
    found = {}
    for kernel in ("broadcast", "shuffle"):
        with pytest.warns(UserWarning, match="denominator"):
            fit = solvers.fit_objective(p, weights, 2, kernel=kernel)
        found[kernel] = {r["node_id"]: r["vec"] for r in fit.vectors.collect()}
        assert fit.least_denominator == pytest.approx(1 - repel / 2)
        with pytest.raises(ValueError):
            solvers.fit_objective(p, Params(1, 0, 0, repel, strict=True), 2, kernel=kernel)
        with pytest.raises(ValueError, match="denominator"):
            solvers.run(replace(solvers.objective_step(p, weights), strict=True), p.base, 1, kernel)
    assert all(np.allclose(found["broadcast"][k], found["shuffle"][k]) for k in range(4))
    if repel == 2.0:  # no update at all: the vectors stay
        assert all(np.allclose(found["shuffle"][k], [k + 1.0, 1.0]) for k in range(4))


def test_unsafe_weights_warn(spark):
    with pytest.warns(UserWarning, match="convex"):
        solvers.fit_objective(_matching(spark), Params(1, 0, 1, 1.5), 1)


def test_containment_in_long_texts_with_passages_across_pieces(spark):
    import random

    rng = random.Random(5)
    long = "".join(rng.choice("abcdefghij ") for _ in range(3000))
    held = [long[500:530], long[505:560], long[1010:1050], long[-24:], long[-5:], long[:1], long, long + "x", "zz", "", None]
    texts = spark.createDataFrame([(long,), ("é" * 600 + "zz",), ("",), (None,)], "src string")
    got = extract.containment_links(texts, spark.createDataFrame([(p,) for p in held], "dst string"))
    want = {(t, p) for t in (long, "é" * 600 + "zz") for p in held if p and p in t}
    assert {tuple(r) for r in got.collect()} == want and got.count() == len(want)
    assert extract.containment_links(texts, spark.createDataFrame([], "dst string")).count() == 0


def test_as_of_join_over_stretches_against_a_plain_walk(spark):
    import random
    from datetime import datetime, timedelta

    from tablevec.operators import relational as r

    rng, start = random.Random(6), datetime(2024, 1, 1)
    moment = lambda: start + timedelta(hours=rng.randrange(0, 400))
    left = [(i, rng.choice(["hot", "hot", "b", None]), moment()) for i in range(200)]
    right = [(rng.choice(["hot", "b", None]), moment(), rng.choice([None, 1, 2, 3])) for _ in range(60)]
    a = spark.createDataFrame(left, "id long, k string, at timestamp")
    b = spark.createDataFrame(right, "k string, at timestamp, v long")
    got = {x["id"]: x["last_v"] for x in r.as_of_join(a, b, "k", "at", "v").collect()}
    for i, k, at in left:
        known = [(t, v) for key, t, v in right if key == k and t <= at and v is not None]
        assert got[i] == (max(known)[1] if known else None)
    assert len(got) == len(left) and r.as_of_join(a, b.limit(0), "k", "at", "v").where("last_v is not null").count() == 0


def test_start_vectors_without_a_row_of_numbers_for_each_hit(spark, monkeypatch):
    words = _lexicon(spark)
    terms = [r["term"] for r in words.orderBy("term").collect()]
    nodes = spark.createDataFrame([(i, "t.c", " and ".join(terms[(i * k) % len(terms)] for k in range(1 + i % 40)) if i % 7 else "none of it") for i in range(300)], "node_id long, category string, value string")
    hits = lexicon.match_phrases(nodes, words).repartition(3)
    dims = words.selectExpr("size(vec) AS n").first()["n"]
    assert lexicon._sums(hits, words, dims) is not None
    got = {r["node_id"]: r for r in lexicon.init_vectors(nodes, hits, words, dims).collect()}
    monkeypatch.setattr(lexicon, "VECTOR_BYTES", 0)
    assert lexicon._sums(hits, words, dims) is None
    for r in lexicon.init_vectors(nodes, hits, words, dims).collect():
        assert r["is_oov"] == got[r["node_id"]]["is_oov"] and np.allclose(r["vec"], got[r["node_id"]]["vec"], rtol=0, atol=1e-12)
    monkeypatch.undo()
    assert lexicon._sums(hits, words.union(words), dims) is None and lexicon._sums(hits, words, dims + 1) is None


def test_start_vectors_in_one_pass_over_the_values(spark, monkeypatch):
    words = _lexicon(spark)
    values = ["Bank account", "bank, BANK", "my bank-account account", "a b c d", "nothing here", "account a", "b c", "d " * 50 + "a b bank"]
    nodes = spark.createDataFrame([(i, "c", v) for i, v in enumerate(values * 100)], "node_id long, category string, value string")
    got = {r["node_id"]: r for r in lexicon.start_vectors(nodes, words, 2).collect()}
    want = lexicon.init_vectors(nodes, lexicon.match_phrases(nodes, words), words, 2).collect()
    assert len(got) == len(want) == 800
    for r in want:
        assert np.allclose(r["vec"], got[r["node_id"]]["vec"], rtol=0, atol=1e-12) and [r[c] for c in ("category", "value", "is_oov")] == [got[r["node_id"]][c] for c in ("category", "value", "is_oov")]
    assert lexicon.start_vectors(nodes, words, 3) is None
    monkeypatch.setattr(lexicon, "TRIE_TOKENS", 3)
    assert lexicon.start_vectors(nodes, words, 2) is None
