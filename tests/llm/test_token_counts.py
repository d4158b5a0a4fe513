import random

import pytest
from pyspark.sql import functions as F

from tablevec.llm import token_counts as tc


@pytest.fixture(scope="module")
def exact():
    from tokenizers import Tokenizer, models, pre_tokenizers

    vocabulary = tc.read_vocabulary(tc.default_vocabulary())
    made = Tokenizer(models.Unigram(vocabulary, unk_id=0, byte_fallback=True))
    made.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.Split("\n", "isolated"), pre_tokenizers.Metaspace(replacement=tc.SPACE, prepend_scheme="never", split=True)])
    return lambda text: len(made.encode(text, add_special_tokens=False).ids)


def test_counts_are_those_of_the_library(spark, tiny, exact):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    got = {r["doc_id"]: r["n_tokens"] for r in tc.count_tokens(docs).collect()}
    for r in docs.collect():
        assert got[r["doc_id"]] == exact(r["text"] or ""), r["doc_id"]


def test_odd_texts_and_ties(exact):
    counter = tc.Counter(tc.read_vocabulary(tc.default_vocabulary()))
    rng = random.Random(3)
    odd = ["", " ", "  a   b ", "\n\n x\ny", "<unk> <0x41> </s>", "\U0001f600\U0001f600 café 漢字", "x" * 3000, tc.SPACE + "a" + tc.SPACE, "\x00\x01퟿", "é"]
    odd += ["".join(rng.choice("ab \né͸\U0001f600<0x>") for _ in range(rng.randrange(60))) for _ in range(300)]
    for text in odd:
        assert sum(map(counter.__getitem__, tc.parts_of(text))) == exact(text), repr(text)


def test_equal_scores_keep_the_earliest_start():
    from tokenizers import Tokenizer, models

    vocabulary = [("<unk>", -50.0), ("a", -1.0), ("b", -1.0), ("ab", -2.0), ("bc", -2.0), ("abc", -3.0), ("c", -1.0)]
    library, counter = Tokenizer(models.Unigram(vocabulary, unk_id=0, byte_fallback=False)), tc.Counter(vocabulary)
    rng = random.Random(1)
    for _ in range(300):
        text = "".join(rng.choice("abc") for _ in range(rng.randrange(1, 12)))
        assert counter.count(text) == len(library.encode(text).ids), text


def test_nulls_repeats_clashes_and_no_rows(spark):
    rows = [(1, None, "x"), (1, None, "x"), (2, "", "y"), (None, "ab", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_tokens string")
    got = sorted((r["doc_id"] or -1, r["n_tokens"]) for r in tc.count_tokens(docs).collect())
    assert [g for g in got if g[0] > 0] == [(1, 0), (1, 0), (2, 0)] and got[0][1] > 0
    assert tc.count_tokens(docs.where(F.lit(False))).count() == 0
