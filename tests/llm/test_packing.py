import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tablevec.llm import packing


def _check(rows, capacity):
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for pieces in by.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def _best_fit(lengths, capacity):
    """Plain best fit by decreasing length, one piece at a time."""
    gaps = []
    for n in sorted(lengths, reverse=True):
        fits = [g for g in gaps if g >= n]
        if fits:
            gaps.remove(min(fits))
            gaps.append(min(fits) - n)
        else:
            gaps.append(capacity - n)
    return len(gaps)


def test_plan_places_every_piece_and_is_as_good_as_best_fit():
    rng = random.Random(5)
    for _ in range(150):
        capacity = rng.choice([10, 37, 100])
        lengths = [min(capacity, 1 + int(rng.expovariate(1 / (0.3 * capacity)))) for _ in range(rng.randrange(1, 200))]
        counts = {n: lengths.count(n) for n in lengths}
        plan, got = packing.plan_bins(counts, capacity), {}
        for many, contents in plan:
            assert sum(n * each for n, each in contents) <= capacity
            assert sum(each for n, each in contents if 3 * n > capacity) <= 2
            for n, each in contents:
                got[n] = got.get(n, 0) + many * each
        assert got == counts
        assert sum(m for m, _ in plan) <= _best_fit(lengths, capacity) * 1.1 + 1


def test_pieces_are_the_ids_of_the_library(spark, tiny):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    got = packing.pack_documents(docs).collect()
    assert _check(got, packing.CAPACITY) * packing.CAPACITY < 1.05 * sum(r["length"] for r in got) + packing.CAPACITY
    library = Tokenizer.from_file(packing.default_tokenizer())
    by = {(r["doc_id"], r["piece"]): r for r in got}
    n = 0
    for d in docs.collect():
        ids = np.array(library.encode(d["text"] or "", add_special_tokens=False).ids + [1], dtype="<u4")
        for piece, at in enumerate(range(0, len(ids), packing.CAPACITY)):
            part = ids[at : at + packing.CAPACITY]
            r = by[d["doc_id"], piece]
            assert (r["start"], r["length"], r["ids_crc32"]) == (at, len(part), zlib.crc32(part.tobytes()))
            n += 1
    assert n == len(got)


@pytest.mark.parametrize("text", ["", " ", "A b,c.  D\n\ne\tf\x1cg", "it's 12 don't <|endoftext|> x<|startoftext|>y", "É́ ﬁ İ ΑΣ  z", "a" * 9000, "word. " * 500, "Ünï,cödé;x:", "<|endoftext|>.", "A\x85b\xa0c​d", "İ. İx,"])
def test_chunks_give_the_ids_of_whole_texts(text):
    from tokenizers import Tokenizer

    from tablevec.llm.subwords import ChunkCoder

    path = packing.default_tokenizer()
    want = Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids
    assert np.frombuffer(ChunkCoder(path).ids(text), dtype="<u4").tolist() == want


def test_nulls_hot_lengths_repeats_and_no_rows(spark, monkeypatch):
    monkeypatch.setattr(packing, "RANKED_TOGETHER", 50)
    rows = [(i, "same text", "c") for i in range(700)] + [(7, None, "c"), (7, None, "c"), (None, "", "c")] + [(2000, "long " * 5000, "c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, length string")
    got = packing.pack_documents(docs, capacity=100).collect()
    assert sum(r["length"] for r in got) == 700 * 3 + 3 + 5001
    _check(got, 100)
    assert sorted(r["length"] for r in got if r["doc_id"] == 2000) == [1] + [100] * 50
    assert packing.pack_documents(docs.where(F.lit(False))).count() == 0


def test_sequences_hold_the_ids(spark):
    docs = spark.createDataFrame([(i, f"text {i} " * (i % 30)) for i in range(200)], "doc_id long, text string")
    packed = packing.pack_documents(docs, capacity=64, with_ids=True).cache()
    made = {r["sequence_id"]: r for r in packing.sequences(packed).collect()}
    for r in packed.collect():
        whole = made[r["sequence_id"]]
        assert len(whole["ids"]) == 4 * whole["n_tokens"] <= 256
        assert whole["ids"][4 * r["offset"] : 4 * (r["offset"] + r["length"])] == r["ids"]
