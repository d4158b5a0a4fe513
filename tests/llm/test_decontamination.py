import random

import numpy as np
from pyspark.sql import functions as F

from tablevec.llm import decontamination as dc


def _least_edits(passage, text):
    """Fewest edits to turn the passage into a part of the text, by the plain table."""
    row = [0] * (len(text) + 1)
    for i, c in enumerate(passage):
        new = [i + 1]
        for j, d in enumerate(text):
            new.append(min(row[j] + (c != d), row[j + 1] + 1, new[j] + 1))
        row = new
    return min(row)


def _edited(rng, text, n):
    text = list(text)
    for _ in range(n):
        at, kind = rng.randrange(len(text)), rng.randrange(3)
        if kind == 0:
            text[at] = rng.choice("xyzqw")
        elif kind == 1:
            del text[at]
        else:
            text.insert(at, rng.choice("xyzqw "))
    return "".join(text)


def _prose(rng, n):
    return " ".join(rng.choice(["the", "and", "stone", "river", "ing", "over", "under", "light", "bread", "window", "quick", "lazy"]) for _ in range(n))


def test_grams_tell_runs_apart():
    codes = np.array([ord(c) for c in "abcabcabd" * 5], dtype=np.uint32)
    for q in (1, 2, 3, 5, 8, 9, 13):
        h = dc.grams(codes, q)
        runs = [tuple(codes[i : i + q]) for i in range(len(codes) - q + 1)]
        assert len(h) == len(runs) and len(set(h.tolist())) == len(set(runs))
        assert all((h[i] == h[j]) == (runs[i] == runs[j]) for i in range(0, len(runs), 3) for j in range(0, len(runs), 4))


def test_alignment_against_the_plain_table():
    rng = random.Random(1)
    for _ in range(200):
        passage = _prose(rng, rng.randrange(2, 9))
        text = _prose(rng, 3) + " " + _edited(rng, passage, rng.randrange(6)) + " " + _prose(rng, 3)
        code = lambda s: np.array([ord(c) for c in s], dtype=np.uint32)
        want, most = _least_edits(passage, text), 6
        got = dc.align(code(passage), code(text), most)
        assert (got is None) == (want > most)
        if got:
            assert got[0] == want == _least_edits(passage, text[got[1] : got[2]])


def test_every_occurrence_within_the_budget_is_found():
    rng = random.Random(2)
    items = [(i, _prose(rng, rng.choice([2, 4, 8, 20, 40, 70]))) for i in range(25)] + [(90, "short"), (91, "  "), (92, "")]
    index = dc.Index(items)
    texts = []
    for i, passage in items[:25]:
        for n in (0, dc.edit_budget(len(passage)) // 2, dc.edit_budget(len(passage))):
            texts.append(_prose(rng, rng.randrange(40)) + " " + _edited(rng, passage, n) + " " + _prose(rng, rng.randrange(40)))
    texts += [_prose(rng, 100) for _ in range(10)] + ["", None, "a short text", "SHORT"]
    found = index.find(texts)
    for text, hits in zip(texts, found):
        codes = "".join(map(chr, dc.fold(text or "")[0]))
        for i, passage in items[:26]:
            want = _least_edits(passage, codes) if codes else len(passage)
            got = [h for h in hits if h[0] == i]
            assert bool(got) == (want <= dc.edit_budget(len(passage))), (passage, text, want)
            if got:
                assert got[0][3] == want


def test_offsets_are_those_of_the_text():
    passage = "Le cœur a ses raisons que la raison ne connaît point du tout, dit-on souvent ici"
    text = "\U0001f600 avant.\n\n" + passage.upper().replace(" ", "  \n") + " après"
    ((hit,),) = dc.Index([(5, passage)]).find([text])
    assert hit[0] == 5 and hit[3] == 0 and text[hit[1] : hit[2]].lower().split() == passage.lower().split()


def test_documents_with_passages(spark):
    path = "/root/testdata/sf0.01"
    docs, bench = spark.read.parquet(f"{path}/documents.parquet"), spark.read.parquet(f"{path}/benchmark.parquet")
    got = dc.find_leaks(docs, bench).collect()
    texts, items = ({r[0]: r[1] for r in x.collect()} for x in (docs.select("doc_id", "text"), bench.select("item_id", "text")))
    exact = {(d, i) for d, t in texts.items() for i, p in items.items() if p in t}
    assert exact and exact <= {(r["doc_id"], r["item_id"]) for r in got if r["edits"] == 0}
    for r in got:
        part = dc.fold(texts[r["doc_id"]][r["start"] : r["end"]])[0]
        assert _least_edits(list(dc.fold(items[r["item_id"]])[0]), list(part)) == r["edits"] <= dc.edit_budget(len(items[r["item_id"]]))


def test_parts_nulls_repeats_and_no_rows(spark, monkeypatch):
    passage = "a passage that is long enough to be found in other texts of this test"
    items = spark.createDataFrame([(1, passage, "q"), (1, passage, "q"), (2, None, "q"), (None, passage[:50], "q"), (3, "", "q")], "item_id long, text string, doc_id string")
    docs = spark.createDataFrame([(7, "x " + passage, 1), (7, "x " + passage, 1), (8, None, 1), (9, "", 1), (None, passage, 1), (10, "word " * 30000 + passage, 1)], "doc_id long, text string, item_id int")
    want = sorted((str(d), str(i)) for d in (7, 7, None, 10) for i in (1, 1, None))
    assert sorted((str(r["doc_id"]), str(r["item_id"])) for r in dc.find_leaks(docs, items).collect()) == want
    monkeypatch.setattr(dc, "MOST_CHARACTERS", 60)
    assert sorted((str(r["doc_id"]), str(r["item_id"])) for r in dc.find_leaks(docs, items).collect()) == want
    assert dc.find_leaks(docs.where(F.lit(False)), items).count() == dc.find_leaks(docs, items.where(F.lit(False))).count() == 0
