import numpy as np

import corpus_pipeline as cp
from tablevec.llm import decontamination, language_id, near_duplicates, packing, toxicity
from tablevec.llm.common import without_ids


def test_stages_have_the_effect_of_their_operators(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    labels, bench = spark.read.parquet(f"{tiny}/labels.parquet"), spark.read.parquet(f"{tiny}/benchmark.parquet")
    ids = lambda df, c="doc_id": {r[c] for r in df.select(c).collect()}
    for (_, stage), good in zip(
        cp.STAGES[:4],
        [
            lambda d: ids(language_id.identify(d).where("not rejected")),
            lambda d: ids(toxicity.tag(d, labels).where("predicted = 0")),
            lambda d: ids(near_duplicates.near_duplicates(d).where("kept")),
            lambda d: ids(d) - ids(decontamination.find_leaks(d, bench)),
        ],
    ):
        want, kept = good(docs), stage(spark, docs, tiny).cache()
        assert kept.columns == docs.columns and kept.schema == docs.schema
        assert ids(kept) == want and kept.count() == len(want) < docs.count() + 1
        docs = kept
    assert ids(cp.STAGES[4][1](spark, docs, tiny)) == ids(docs)


def test_run_packs_what_is_left(spark, tiny):
    got = cp.run(spark, tiny).toPandas()
    total = got.groupby("sequence_id")["length"].sum()
    assert (total <= packing.CAPACITY).all() and 50 < got["doc_id"].nunique() < 200
    first = got.sort_values(["sequence_id", "offset"]).groupby("sequence_id").first()
    assert (first["offset"] == 0).all()


def test_stages_take_nulls_repeats_extra_columns_and_no_rows(spark, tiny):
    rows = [(1, "plain words of some text in a row " * 3, "en", "s", 5, "a"), (1, "plain words of some text in a row " * 3, "en", "s", 5, "b"), (2, None, None, None, None, "c"), (None, "other words entirely", "en", None, 1, None), (3, "", "en", "s", 0, "d")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string")
    for _, stage in cp.STAGES[:4]:
        assert stage(spark, docs, tiny).columns == docs.columns
        assert stage(spark, docs.limit(0), tiny).count() == 0
    kept = cp.STAGES[2][1](spark, docs, tiny)
    assert {r["doc_id"] for r in kept.collect()} == {1, 2, 3, None}
    assert {r["doc_id"] for r in cp.STAGES[0][1](spark, docs, tiny).collect()} == {1, None}


def test_without_ids_is_an_anti_join(spark):
    docs = spark.createDataFrame([(i if i % 7 else None, str(i)) for i in range(3000)], "doc_id long, text string")
    gone = spark.createDataFrame([(int(i),) for i in np.random.default_rng(1).choice(3000, 400, replace=False)], "id long")
    got = sorted(r["text"] for r in without_ids(docs, "doc_id", gone).collect())
    lost = {r["id"] for r in gone.collect()}
    assert got == sorted(str(i) for i in range(3000) if i % 7 == 0 or i not in lost)
    assert without_ids(docs, "doc_id", gone.limit(0)).count() == 3000


def test_repeated_and_null_ids_are_told_apart_by_row(spark, tiny):
    text = lambda a: " ".join(f"{a}{i}" for i in range(30))
    rows = [
        (5, text("u"), "first"), (5, text("v"), "same id, other text"), (5, text("u"), "first"),
        (9, text("v"), "copy of the other text"), (7, text("w"), "single"), (8, text("w") + " more", "near copy"),
        (None, text("w"), "copy without an id"), (None, text("z"), "no id"), (None, text("z"), "no id"), (None, None, "no text"), (None, None, "no text"),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string, _key string")
    got = cp.STAGES[2][1](spark, docs, tiny)
    assert got.schema == docs.schema
    kept = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["_key"]) for r in got.collect())
    assert kept == [(-1, "no id"), (-1, "no text"), (-1, "no text"), (5, "first"), (7, "single"), (9, "copy of the other text")]


def test_without_ids_with_clashing_names(spark):
    docs = spark.createDataFrame([(1, "a", 3), (2, "b", 4)], "doc_id long, _gone string, _slot long")
    got = without_ids(docs, "doc_id", spark.createDataFrame([(2,)], "id long"))
    assert got.columns == docs.columns and [tuple(r) for r in got.collect()] == [(1, "a", 3)]


def test_run_leaves_only_its_last_stage(spark, tiny, monkeypatch, tmp_path):
    from tablevec.llm import common

    monkeypatch.setattr(common, "shared_folder", lambda spark: str(tmp_path))
    got = cp.run(spark, tiny)
    left = [p for p in tmp_path.iterdir() if any(p.iterdir())]
    assert [p.name.split("-")[0] for p in left] == ["pipeline"] and [p.name for p in left[0].iterdir()] == ["stage4"]
    assert got.count() > 50


def test_a_cluster_without_a_shared_folder_is_an_error(spark, monkeypatch):
    import pytest

    from tablevec.llm import common

    class Context:
        master = "spark://host:7077"

        def getConf(self):
            return {}

    class Session:
        sparkContext = Context()

    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        common.shared_folder(Session())
