import random
import zlib

import numpy as np

from tablevec.llm import language_id as li


def test_trigram_counts_against_plain_python():
    texts = ["The cat. É!", None, "", "12 - 34", "a", "\U0001f600 x漢y"]
    counts, letters = li.trigram_counts(texts)
    for text, row, n in zip(texts, counts, letters):
        clean = "\0" + "".join(c if c.isalpha() else "\0" for c in (text or "").lower()) + "\0"
        grams = [clean[i - 1 : i + 2] for i in range(1, len(clean) - 1) if clean[i] != "\0"]
        assert n == len(grams) == row.sum()
        slots = np.zeros(li.DIMENSIONS, dtype=int)
        for a, b, c in (map(ord, g) for g in grams):
            h = (((a * 0x9E3779B1 + b) % 2**32) * 0x85EBCA6B + c) % 2**32
            slots[((h ^ (h >> 15)) * 0xC2B2AE35 % 2**32) >> 20] += 1
        assert (slots == row).all()


def test_held_out_accuracy_and_whole_table(spark):
    path = "/root/testdata/sf0.01/documents.parquet"
    docs = {r["doc_id"]: r for r in spark.read.parquet(path).collect()}
    got = li.op4_language_id(spark, "/root/testdata/sf0.01").collect()
    assert sorted(r["doc_id"] for r in got) == sorted(docs)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for r in got)
    held = [r for r in got if r["held_out"]]
    assert np.mean([r["lang_pred"] == docs[r["doc_id"]]["lang"] for r in held]) > 0.98
    assert np.mean([r["rejected"] for r in got]) < 0.01


def test_unknown_languages_are_rejected(spark):
    rows = [(r["doc_id"], r["text"], r["lang"]) for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()]
    rng = random.Random(4)
    strange = [(10_000 + i, "".join(rng.choice("абвгдежзийклмн   ") for _ in range(400)), None) for i in range(30)]
    got = li.identify(spark.createDataFrame(rows + strange, "doc_id long, text string, lang string")).collect()
    assert all(r["rejected"] for r in got if r["doc_id"] >= 10_000)


def test_nulls_no_letters_repeats_and_no_rows(spark):
    rows = [(i, "alpha beta gamma", "la") for i in range(20)] + [(i, "uno dos tres", "es") for i in range(20, 40)]
    rows += [(50, None, "es"), (51, "", None), (52, "12 !", "la"), (None, "dos", "es"), (None, "dos", "es"), (53, "tres " * 20000, None)]
    df = spark.createDataFrame([(*r, 1.0) for r in rows], "doc_id long, text string, lang string, score double")
    got = li.identify(df).collect()
    assert len(got) == len(rows)
    by = {r["doc_id"]: r for r in got}
    for k in (50, 51, 52):
        assert (by[k]["lang_pred"], by[k]["score"], by[k]["rejected"]) == ("und", 0.0, True)
    assert by[53]["lang_pred"] == by[25]["lang_pred"] == by[None]["lang_pred"] == "es" and by[3]["lang_pred"] == "la"
    assert li.identify(df.limit(0)).count() == 0
    assert {r["lang_pred"] for r in li.identify(df.withColumn("lang", li.F.lit(None).cast("string"))).collect()} == {"und"}


def test_predictions_against_brute_force(spark):
    """The whole query, with cosines, nearest centroids and rejection worked out text by text in plain Python."""
    import math

    rows = [(r["doc_id"], r["text"], r["lang"]) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    rows += [(5000, None, "en"), (5001, "", "en"), (5002, "42!", None), (5003, "qqq xxq zzx qxz " * 20, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = li.fit(df.where(li.bucket("doc_id", 3) != 1))
    training = [t for k, t, lang in rows if t is not None and lang is not None and zlib.crc32(str(k).encode()) % 3 != 1]

    def slots(text):
        clean = "\0" + "".join(c if c.isalpha() else "\0" for c in (text or "").lower()) + "\0"
        out = {}
        for i in range(1, len(clean) - 1):
            if clean[i] != "\0":
                h = (((ord(clean[i - 1]) * 0x9E3779B1 + ord(clean[i])) % 2**32) * 0x85EBCA6B + ord(clean[i + 1])) % 2**32
                s = ((h ^ (h >> 15)) * 0xC2B2AE35 % 2**32) >> 20
                out[s] = out.get(s, 0) + 1
        return out

    counted = [slots(t) for t in training]
    n = len(training)
    seen = np.zeros(li.DIMENSIONS)
    for c in counted:
        seen[list(c)] += 1
    idf = [math.log((1 + n) / (1 + s)) + 1 for s in seen]
    got = {r["doc_id"]: r for r in li.identify(df).collect()}
    assert len(got) == len(rows)
    for k, text, _ in rows:
        found = slots(text)
        letters = sum(found.values())
        if not letters:
            assert (got[k]["lang_pred"], got[k]["score"], got[k]["rejected"]) == ("und", 0.0, True)
            continue
        v = {s: math.sqrt(c) * idf[s] for s, c in found.items()}
        size = math.sqrt(sum(x * x for x in v.values()))
        cosines = [sum(x * float(c[s]) for s, x in v.items()) / size for c in model.centroids]
        best = max(range(len(cosines)), key=lambda i: cosines[i])
        assert got[k]["lang_pred"] == model.languages[best // li.CENTROIDS]
        assert abs(got[k]["score"] - cosines[best]) < 1e-4
        place = min(math.log2(letters), len(model.usual) - 1)
        low = int(place)
        usual = model.usual[low] + (place - low) * (model.usual[min(low + 1, len(model.usual) - 1)] - model.usual[low])
        assert got[k]["rejected"] == (cosines[best] < li.LEAST_SHARE * usual)
