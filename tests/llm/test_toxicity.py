import itertools
import random
import zlib

import numpy as np

from tablevec.llm import toxicity as tx


def test_chains_against_all_paths_and_plain_walk():
    rng = np.random.default_rng(0)
    lengths = np.array([1, 0, 5, 200, 64, 65, 128, 3])
    e, trans, start, at = rng.normal(size=lengths.sum()) * 3, rng.normal(size=(2, 2)), 0.7, 0
    got = tx.chain_marginals(e, lengths, start, trans)
    for n in lengths[lengths > 0]:
        own = e[at : at + n]
        walked, pairs = tx.forward_backward(own[None], np.ones((1, n), bool), start, trans)
        assert np.allclose(walked[0], got[at : at + n]) and np.isclose(pairs.sum(), n - 1)
        if n <= 5:
            total, ones = 0.0, np.zeros(n)
            for path in itertools.product((0, 1), repeat=int(n)):
                w = np.exp(path[0] * start + np.dot(path, own) + sum(trans[a, b] for a, b in zip(path, path[1:])))
                total, ones = total + w, ones + w * np.array(path)
            assert np.allclose(ones / total, got[at : at + n])
        at += n


def test_padding_changes_nothing():
    rng = np.random.default_rng(1)
    e, trans = rng.normal(size=(3, 9)), rng.normal(size=(2, 2))
    real = np.arange(9) < np.array([[9], [4], [1]])
    m, pairs = tx.forward_backward(e, real, 0.2, trans)
    alone = [tx.forward_backward(e[i : i + 1, :n], np.ones((1, n), bool), 0.2, trans) for i, n in enumerate((9, 4, 1))]
    assert all(np.allclose(m[i, :n], alone[i][0][0]) for i, n in enumerate((9, 4, 1)))
    assert np.allclose(pairs, sum(a[1] for a in alone))


def test_training_gradient_lowers_the_loss():
    rng = np.random.default_rng(2)
    words = rng.integers(1, 40, size=(300, 20)).astype(np.int32)
    labels = (words < 4).astype(np.int32)
    crf = tx.train_field(words, words, words, labels)
    m, _ = tx.forward_backward(crf.emissions(words, words, words), labels >= 0, crf.start, crf.trans)
    assert ((m >= 0.5) == labels).mean() > 0.99


def _rows(n=600):
    rng = random.Random(8)
    plain = ["tree", "house", "river", "stone", "cloud", "grass", "light", "paper", "glass", "sound"]
    bad = ["vileword", "nastyword", "crudeword"]
    docs, labels = [], []
    for i in range(n):
        words, toxic = [rng.choice(plain) for _ in range(rng.randrange(5, 120))], int(rng.random() < 0.3)
        if toxic:
            for _ in range(3):
                words.insert(rng.randrange(len(words)), rng.choice(bad) + rng.choice(["", ",", "."]))
        docs.append((i, " ".join(words), "x"))
        labels.append((i, toxic))
    return docs, labels


def test_held_out_scores_and_offsets(spark):
    docs, labels = _rows()
    got = tx.tag(spark.createDataFrame(docs, "doc_id long, text string, score string"), spark.createDataFrame(labels, "doc_id long, toxic int")).collect()
    truth, texts = dict(labels), {d[0]: d[1] for d in docs}
    assert len(got) == len(docs)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and r["predicted"] == int(r["score"] >= 0.5) for r in got)
    held = [r for r in got if r["held_out"]]
    assert np.mean([r["predicted"] == truth[r["doc_id"]] for r in held]) > 0.97
    for r in held:
        marked = " ".join(texts[r["doc_id"]][s["start"] : s["end"]] for s in r["spans"])
        assert sum(w in texts[r["doc_id"]] for w in ("vileword", "nastyword", "crudeword")) == sum(w in marked for w in ("vileword", "nastyword", "crudeword"))


def test_held_out_labels_are_not_read(spark):
    docs, labels = _rows(200)
    held = {i for i, _ in labels if zlib.crc32(str(i).encode()) % 5 == 0}
    turned = [(i, 1 - y if i in held else y) for i, y in labels]
    frame = spark.createDataFrame(docs, "doc_id long, text string, score string")
    a, b = ({r["doc_id"]: r["score"] for r in tx.tag(frame, spark.createDataFrame(x, "doc_id long, toxic int")).collect()} for x in (labels, turned))
    assert a == b


def test_nulls_conflicts_long_texts_and_no_rows(spark):
    docs, labels = _rows(100)
    docs += [(1000, None, "x"), (1001, "", "x"), (1001, "", "x"), (None, "vileword", "x"), (1002, "tree " * 30000 + "vileword", "x")]
    labels += [(3, 0), (3, 1), (None, 1), (4, None), (5000, 1)]
    frame, known = spark.createDataFrame(docs, "doc_id long, text string, score string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    got = tx.tag(frame, known).collect()
    assert len(got) == len(docs) and all(0 <= r["score"] <= 1 for r in got)
    empty = [r for r in got if r["doc_id"] in (1000, 1001)]
    assert len(empty) == 3 and len({r["score"] for r in empty}) == 1 and all(r["predicted"] == 0 and not r["spans"] for r in empty)
    assert tx.tag(frame.limit(0), known).count() == 0
    assert {r["predicted"] for r in tx.tag(frame, known.limit(0)).collect()} == {0}
    assert len(tx.tag(frame, known.where("toxic = 1")).collect()) == len(docs)
