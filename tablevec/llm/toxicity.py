"""Toxic spans by a linear-chain conditional random field, and document scores from its marginals.

Labels are given for documents only, so tokens are labelled first: a word is a sign if it is in far more toxic than
clean training documents, and the signs in toxic documents are the labelled tokens. The field has two states, learned
weights for the word, its first letters and its neighbours, and learned transitions. Forward-backward gives each
token's probability of being toxic. The tokens at 0.5 or more are the offending offsets; the sum, the largest and the
mean of a document's marginals give its score by a logistic fit on training documents.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import bucket, filter_rows, map_arrow, record_batch, slices, table

#: Bound of the labelled rows that the field is fitted on, for each class.
SAMPLE_PER_CLASS = 6000
#: Of such a document, at most so many stretches with signs and so many others, drawn by hash from its whole text.
HIT_STRETCHES, OTHER_STRETCHES = 8, 2
#: A sign is in this share of the toxic documents at least, and so many times likelier there.
SIGN_SHARE, SIGN_COUNT, SIGN_RATIO = 0.005, 3, 20.0
WORD_BINS, SIDE_BINS = 1 << 18, 1 << 16
STRETCH = 64  # tokens that are trained, or walked, as one row
MOST_KEPT = 100_000
_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32()), ("n_toxic", pa.int64()), ("spans", _SPANS)])
#: A stretch to train on: feature bins of its tokens, and their labels (-1 for no token).
_ROW = np.dtype([("word", "<i4", STRETCH), ("prefix", "<u2", STRETCH), ("side", "<u2", STRETCH), ("label", "i1", STRETCH)])
_EDGES = re.compile(r"^[\W_]+|[\W_]+$")
_CHUNK = re.compile(r"\S+")


def word_of(chunk: str) -> str:
    """A token's word: in lower case, without punctuation at its ends."""
    return chunk.lower() if chunk.isalnum() else _EDGES.sub("", chunk.lower())


def bins_of(word: str) -> tuple[int, int, int]:
    """Feature bins of the word, of its first five letters, and of it as a neighbour; 0 is kept for no word."""
    if not word:
        return 0, 0, 0
    h = zlib.crc32(word.encode("utf-8", "surrogatepass"))
    p = zlib.crc32(b"^" + word[:5].encode("utf-8", "surrogatepass"))
    return 1 + h % (WORD_BINS - 1), 1 + p % (SIDE_BINS - 1), 1 + (h >> 3) % (SIDE_BINS - 1)


@dataclass
class Field:
    """Weights of the toxic state against the clean one; `trans[i, j]` scores a step from state i to j."""

    word: np.ndarray = field(default_factory=lambda: np.zeros(WORD_BINS, np.float32))
    prefix: np.ndarray = field(default_factory=lambda: np.zeros(SIDE_BINS, np.float32))
    before: np.ndarray = field(default_factory=lambda: np.zeros(SIDE_BINS, np.float32))
    after: np.ndarray = field(default_factory=lambda: np.zeros(SIDE_BINS, np.float32))
    bias: float = -3.0
    start: float = 0.0
    trans: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))
    #: Logistic weights: constant, log of 1 + sum, largest, mean.
    document: np.ndarray = field(default_factory=lambda: np.array([-3.0, 0.0, 0.0, 0.0]))

    def emissions(self, words: np.ndarray, prefixes: np.ndarray, sides: np.ndarray) -> np.ndarray:
        """For rows of tokens; row ends have no neighbour."""
        e = self.bias + self.word[words] + self.prefix[prefixes]
        e[:, 1:] += self.before[sides[:, :-1]]
        e[:, :-1] += self.after[sides[:, 1:]]
        return e


def forward_backward(e: np.ndarray, real: np.ndarray, start: float, trans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Marginals of the toxic state for rows of emissions, and the summed pair marginals (2 x 2).

    `real` marks tokens; the unreal ones, at the ends of rows, change nothing.
    """
    n, length = e.shape
    x = np.exp(np.clip(e, -30, 30)).T
    t = np.exp(trans)
    a0, a1 = np.empty((length, n)), np.empty((length, n))
    a0[0], a1[0] = 1.0, x[0] * np.exp(start)
    live = real.T
    for k in range(length):
        if k:
            f0 = a0[k - 1] * t[0, 0] + a1[k - 1] * t[1, 0]
            f1 = (a0[k - 1] * t[0, 1] + a1[k - 1] * t[1, 1]) * x[k]
            a0[k], a1[k] = np.where(live[k], f0, a0[k - 1]), np.where(live[k], f1, a1[k - 1])
        s = a0[k] + a1[k]
        a0[k] /= s
        a1[k] /= s
    b0, b1 = np.ones(n), np.ones(n)
    marginal, pairs = np.empty((length, n)), np.zeros((2, 2))
    for k in range(length - 1, -1, -1):
        z = a0[k] * b0 + a1[k] * b1
        marginal[k] = np.where(live[k], a1[k] * b1 / z, 0.0)
        if k:
            m0, m1 = b0, x[k] * b1
            c = [[a0[k - 1] * t[0, 0] * m0, a0[k - 1] * t[0, 1] * m1], [a1[k - 1] * t[1, 0] * m0, a1[k - 1] * t[1, 1] * m1]]
            total = np.where(live[k], c[0][0] + c[0][1] + c[1][0] + c[1][1], np.inf)
            for i in (0, 1):
                for j in (0, 1):
                    pairs[i, j] += (c[i][j] / total).sum()
            g0 = np.where(live[k], t[0, 0] * m0 + t[0, 1] * m1, b0)
            g1 = np.where(live[k], t[1, 0] * m0 + t[1, 1] * m1, b1)
            s = g0 + g1
            b0, b1 = g0 / s, g1 / s
    return marginal.T, pairs


def chain_marginals(e: np.ndarray, lengths: np.ndarray, start: float, trans: np.ndarray) -> np.ndarray:
    """Marginals of whole chains of any length, laid end to end in `e`.

    Chains are cut into rows of STRETCH tokens. Each row's product of 2 x 2 steps carries messages from row to row, then
    all rows are walked at once with the messages at their ends, which is exact.
    """
    if not len(e):
        return np.zeros(0)
    rows_of = -(-lengths // STRETCH)
    first_row = np.concatenate([[0], np.cumsum(rows_of)[:-1]])
    n_rows = int(rows_of.sum())
    begins = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    at = np.arange(len(e)) - np.repeat(begins, lengths) + np.repeat(first_row, lengths) * STRETCH
    x = np.ones(n_rows * STRETCH)
    live = np.zeros(n_rows * STRETCH, bool)
    x[at], live[at] = np.exp(np.clip(e, -30, 30)), True
    x, live = np.ascontiguousarray(x.reshape(n_rows, STRETCH).T), np.ascontiguousarray(live.reshape(n_rows, STRETCH).T)
    whole = live.all(axis=1)
    t = np.exp(trans)
    head = np.zeros(n_rows, bool)
    head[first_row[rows_of > 0]] = True
    p = [np.ones(n_rows), np.zeros(n_rows), np.zeros(n_rows), np.ones(n_rows)]
    for k in range(STRETCH):
        y = x[k]
        q = [p[0] * t[0, 0] + p[1] * t[1, 0], (p[0] * t[0, 1] + p[1] * t[1, 1]) * y, p[2] * t[0, 0] + p[3] * t[1, 0], (p[2] * t[0, 1] + p[3] * t[1, 1]) * y]
        if k == 0:  # a chain's first token has no step before it: its row starts with the start weight alone
            q = [np.where(head, 1.0, q[0]), np.where(head, y * np.exp(start), q[1]), np.where(head, 1.0, q[2]), np.where(head, y * np.exp(start), q[3])]
        p = q if whole[k] else [np.where(live[k], new, old) for new, old in zip(q, p)]
        if k % 4 == 3:
            s = p[0] + p[1] + p[2] + p[3]
            p = [v / s for v in p]
    f0, f1, b0, b1 = np.full(n_rows, 0.5), np.full(n_rows, 0.5), np.full(n_rows, 0.5), np.full(n_rows, 0.5)
    most = int(rows_of.max())
    by_size = np.argsort(-rows_of, kind="stable")
    size_sorted = -rows_of[by_size]
    for k in range(1, most):  # messages into row k of each chain that has one
        r = first_row[by_size[: np.searchsorted(size_sorted, -k, side="left")]] + k
        v0, v1 = f0[r - 1] * p[0][r - 1] + f1[r - 1] * p[2][r - 1], f0[r - 1] * p[1][r - 1] + f1[r - 1] * p[3][r - 1]
        s = v0 + v1
        f0[r], f1[r] = v0 / s, v1 / s
    for k in range(most - 1, 0, -1):
        r = first_row[by_size[: np.searchsorted(size_sorted, -k, side="left")]] + k
        v0, v1 = p[0][r] * b0[r] + p[1][r] * b1[r], p[2][r] * b0[r] + p[3][r] * b1[r]
        s = v0 + v1
        b0[r - 1], b1[r - 1] = v0 / s, v1 / s
    a0, a1 = np.empty((STRETCH, n_rows)), np.empty((STRETCH, n_rows))
    for k in range(STRETCH):
        g0, g1 = f0 * t[0, 0] + f1 * t[1, 0], (f0 * t[0, 1] + f1 * t[1, 1]) * x[k]
        if k == 0:
            g0, g1 = np.where(head, 1.0, g0), np.where(head, x[0] * np.exp(start), g1)
        if not whole[k]:
            g0, g1 = np.where(live[k], g0, f0), np.where(live[k], g1, f1)
        s = g0 + g1
        f0, f1 = g0 / s, g1 / s
        a0[k], a1[k] = f0, f1
    out = np.empty((STRETCH, n_rows))
    for k in range(STRETCH - 1, -1, -1):
        u = a1[k] * b1
        out[k] = u / (a0[k] * b0 + u)
        m1 = x[k] * b1
        g0, g1 = t[0, 0] * b0 + t[0, 1] * m1, t[1, 0] * b0 + t[1, 1] * m1
        if not whole[k]:
            g0, g1 = np.where(live[k], g0, b0), np.where(live[k], g1, b1)
        s = g0 + g1
        b0, b1 = g0 / s, g1 / s
    return out.T.reshape(-1)[at]


class Tagger(dict):
    """A worker's tokens with their weights; it forgets them between batches once it holds too many."""

    def __init__(self, crf: Field):
        super().__init__()
        self.crf, self.here, self.before, self.after = crf, [], [], []

    def __missing__(self, chunk: str) -> int:
        w, p, s = bins_of(word_of(chunk))
        self[chunk] = at = len(self.here)
        self.here.append(float(self.crf.bias + self.crf.word[w] + self.crf.prefix[p]))
        self.before.append(float(self.crf.before[s]))
        self.after.append(float(self.crf.after[s]))
        return at

    def marginals(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Of all tokens of all texts in a row, and how many tokens each text has."""
        if len(self) > MOST_KEPT:
            self.clear()
            self.here, self.before, self.after = [], [], []
        ids, lengths = [], np.zeros(len(texts), np.int64)
        for k, text in enumerate(texts):
            if text:
                chunks = text.split()
                lengths[k] = len(chunks)
                ids.append(np.fromiter(map(self.__getitem__, chunks), np.int64, len(chunks)))
        if not ids:
            return np.zeros(0), lengths
        at = np.concatenate(ids)
        before, after = np.array(self.before, np.float32)[at], np.array(self.after, np.float32)[at]
        e = np.array(self.here)[at]
        ends = np.cumsum(lengths[lengths > 0])
        before[ends - 1] = 0  # nothing follows the last token of a text, nor precedes the first
        after[np.concatenate([[0], ends[:-1]])] = 0
        e[1:] += before[:-1]
        e[:-1] += after[1:]
        return chain_marginals(e, lengths, self.crf.start, self.crf.trans), lengths


def document_features(p: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Log of 1 + sum, largest and mean of each document's marginals; zeros without tokens."""
    out, some = np.zeros((len(lengths), 3)), lengths > 0
    if len(p):
        begins = np.concatenate([[0], np.cumsum(lengths[some])[:-1]])
        total = np.add.reduceat(p, begins)
        out[some] = np.stack([np.log1p(total), np.maximum.reduceat(p, begins), total / lengths[some]], axis=1)
    return out


def document_scores(crf: Field, p: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(crf.document[0] + document_features(p, lengths) @ crf.document[1:], -30, 30)))


def train_field(words: np.ndarray, prefixes: np.ndarray, sides: np.ndarray, labels: np.ndarray, rounds: int = 6, rate: float = 0.5) -> Field:
    """Maximum likelihood by Adagrad over rows of tokens; label -1 marks no token."""
    crf, rng = Field(), np.random.default_rng(11)
    squares = {k: np.full_like(getattr(crf, k), 1e-2) for k in ("word", "prefix", "before", "after")}
    more = {"bias": 1e-2, "start": 1e-2, "trans": np.full((2, 2), 1e-2)}
    for _ in range(rounds):
        for part in np.array_split(rng.permutation(len(words)), max(1, len(words) // 256)):
            w, p, s, y = words[part], prefixes[part], sides[part], labels[part]
            real, gold = y >= 0, np.maximum(y, 0)
            m, pairs = forward_backward(crf.emissions(w, p, s), real, crf.start, crf.trans)
            g = np.where(real, m - gold, 0.0)
            seen = np.zeros((2, 2))
            both = real[:, 1:]
            np.add.at(seen, (gold[:, :-1][both], gold[:, 1:][both]), 1.0)
            tokens = max(1, real.sum()) / 64
            grads = {"word": (w, g), "prefix": (p, g), "before": (s[:, :-1], g[:, 1:]), "after": (s[:, 1:], g[:, :-1])}
            for name, (index, weight) in grads.items():
                values = getattr(crf, name)
                d = np.bincount(index.ravel(), weights=weight.ravel(), minlength=len(values)) / tokens
                d[0] = 0
                touched = np.flatnonzero(d)
                squares[name][touched] += d[touched] ** 2
                values[touched] -= rate * d[touched] / np.sqrt(squares[name][touched])
                values[touched] *= 1 - 1e-4
            for name, d in (("bias", g.sum() / tokens), ("start", g[:, 0].sum() / tokens), ("trans", (pairs - seen) / tokens)):
                more[name] = more[name] + d**2
                setattr(crf, name, getattr(crf, name) - 0.3 * rate * d / np.sqrt(more[name]))
    return crf


def fit_logistic(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Weights (constant first) by Newton steps with a small penalty."""
    a = np.column_stack([np.ones(len(x)), x])
    w, penalty = np.zeros(a.shape[1]), np.diag([1e-3] + [1e-2] * x.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + penalty, a.T @ (y - p) - penalty @ w)
        w += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-6:
            break
    return w


def _signs_in(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("word", pa.string()), ("toxic", pa.int64()), ("clean", pa.int64())])
    for whole in batches:
        for batch in slices(whole, 0, 2 << 20):
            found: dict[str, list[int]] = {}
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for word in {word_of(c) for c in (text or "").split()}:
                    if word:
                        found.setdefault(word, [0, 0])[0 if toxic else 1] += 1
            yield record_batch(schema, [list(found), [v[0] for v in found.values()], [v[1] for v in found.values()]])


def _drawn(starts: list[int], words: list[str], most: int) -> list[int]:
    """At most so many of a document's stretches, by a hash of their place and first words."""
    return sorted(starts, key=lambda s: (zlib.crc32(f"{s} {' '.join(words[s : s + 3])}".encode("utf-8", "surrogatepass")), s))[:most]


def _stretches(batches: Iterator[pa.RecordBatch], signs: frozenset[str]) -> Iterator[pa.RecordBatch]:
    """Rows of tokens to train on, drawn from whole texts."""
    schema = pa.schema([("tokens", pa.binary())])
    for batch in batches:
        rows = []
        for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            words = [word_of(c) for c in (text or "").split()]
            starts = range(0, len(words), STRETCH)
            hit = {s for s in starts if signs.intersection(words[s : s + STRETCH])}
            for s in _drawn(sorted(hit), words, HIT_STRETCHES) + _drawn([s for s in starts if s not in hit], words, OTHER_STRETCHES):
                row = np.zeros((), dtype=_ROW)
                row["label"] = -1
                for k, word in enumerate(words[s : s + STRETCH]):
                    row["word"][k], row["prefix"][k], row["side"][k] = bins_of(word)
                    row["label"][k] = bool(toxic) and word in signs
                rows.append(row.tobytes())
        yield record_batch(schema, [rows])


def _features_in(batches: Iterator[pa.RecordBatch], crf: Field) -> Iterator[pa.RecordBatch]:
    schema, tagger = pa.schema([("x1", pa.float64()), ("x2", pa.float64()), ("x3", pa.float64()), ("toxic", pa.int32())]), Tagger(crf)
    for whole in batches:
        for batch in slices(whole, 0, 2 << 20):
            x = document_features(*tagger.marginals(batch.column(0).to_pylist()))
            yield record_batch(schema, [x[:, 0], x[:, 1], x[:, 2], batch.column(1)])


def fit(training: DataFrame, labels: DataFrame) -> Field:
    """Learns from documents (doc_id, text) and labels (doc_id, toxic).

    Documents with labels of both kinds are left out, and so are null labels. At most about SAMPLE_PER_CLASS documents
    of each class are used, the same at any size, chosen by a hash of doc_id; equal texts count once, and not at all if
    their labels differ. The bounds SAMPLE_PER_CLASS, HIT_STRETCHES and OTHER_STRETCHES hold for the labelled rows that
    the field is fitted on; signs and document scores come from whole texts.
    """
    spark = training.sparkSession
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("toxic").cast("int").alias("toxic"), F.max("toxic").cast("int").alias("_other"))
    known = known.where((F.col("toxic") == F.col("_other")) & F.col("toxic").isin(0, 1) & (bucket("doc_id", 5) != 0)).select("doc_id", "toxic")
    sizes = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    if len(sizes) < 2:
        crf = Field()
        crf.document[0] = 3.0 if 1 in sizes else -3.0
        return crf
    scale = 1 << 30
    share = F.create_map(*[F.lit(v) for c, n in sizes.items() for v in (c, min(scale, scale * SAMPLE_PER_CLASS // n))])
    picked = known.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(scale)) < F.element_at(share, F.col("toxic"))).limit(4 * SAMPLE_PER_CLASS)
    rows = training.join(F.broadcast(picked), "doc_id").groupBy("text").agg(F.min("toxic").alias("toxic"), F.max("toxic").alias("_other")).where(F.col("toxic") == F.col("_other")).select("text", "toxic").persist()
    try:
        n = {r["toxic"]: r["count"] for r in rows.groupBy("toxic").count().collect()}
        toxic, clean = n.get(1, 0), n.get(0, 0)
        least = max(SIGN_COUNT, SIGN_SHARE * toxic)
        counts = map_arrow(rows, _signs_in, "word string, toxic long, clean long").groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
        ratio = (F.col("toxic") + 0.5) / (toxic + 1) / ((F.col("clean") + 0.5) / (clean + 1))
        signs = frozenset(r["word"] for r in counts.where((F.col("toxic") >= least) & (ratio >= SIGN_RATIO)).select("word").collect())  # bounded by the sample: each is in `least` of its documents
        got = sorted(r["tokens"] for r in map_arrow(rows, lambda b: _stretches(b, signs), "tokens binary").collect())
        t = np.frombuffer(b"".join(got), dtype=_ROW)
        crf = train_field(t["word"], t["prefix"], t["side"], t["label"]) if len(t) else Field()
        shared = spark.sparkContext.broadcast(crf)
        x = map_arrow(rows, lambda b: _features_in(b, shared.value), "x1 double, x2 double, x3 double, toxic int").toPandas().to_numpy()
        crf.document = fit_logistic(x[:, :3], x[:, 3])
        return crf
    finally:
        rows.unpersist()


def _spans(text: str, p: np.ndarray) -> list[dict]:
    """Runs of toxic tokens as code point offsets, with the largest marginal of each."""
    out, last = [], -2
    for k, m in enumerate(_CHUNK.finditer(text)):
        if p[k] >= 0.5:
            if last == k - 1:
                out[-1]["end"], out[-1]["score"] = m.end(), max(out[-1]["score"], float(p[k]))
            else:
                out.append({"start": m.start(), "end": m.end(), "score": float(p[k])})
            last = k
    return out


def _scored(batches: Iterator[pa.RecordBatch], crf: Field) -> Iterator[pa.RecordBatch]:
    tagger = Tagger(crf)
    for whole in batches:
        for batch in slices(whole, 2, 2 << 20):
            texts = batch.column(2).to_pylist()
            p, lengths = tagger.marginals(texts)
            score = document_scores(crf, p, lengths)
            begins = np.concatenate([[0], np.cumsum(lengths)]).astype(int)
            hits = np.add.reduceat(np.append(p >= 0.5, False), np.minimum(begins[:-1], len(p))).astype(int) * (lengths > 0) if len(p) else np.zeros(len(texts), int)
            spans = [_spans(t, p[begins[k] : begins[k + 1]]) if hits[k] else [] for k, t in enumerate(texts)]
            yield record_batch(_OUT, [batch.column(0), batch.column(1), score, (score >= 0.5).astype(np.int32), hits, spans])


def tag(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted, n_toxic and spans of every whole text of (doc_id, text).

    Labels of the fifth of documents whose crc32 leaves 0 are never read. A null or empty text has no tokens, and the
    score that no toxic token gives. With labels of one kind only, or none, all scores are alike. Repeated rows come
    out repeated; other columns are ignored.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (bucket("doc_id", 5) == 0).alias("held_out"), F.col("text").cast("string").alias("text"))
    crf = docs.sparkSession.sparkContext.broadcast(fit(own.where(~F.col("held_out")).select("doc_id", "text"), labels.select("doc_id", "toxic")))
    kind = "doc_id long, held_out boolean, score double, predicted int, n_toxic long, spans array<struct<start:long,end:long,score:double>>"
    return map_arrow(own, lambda batches: _scored(batches, crf.value), kind)


def keep_clean(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of (doc_id, text, ...) whose score is under a half, with all their columns, whatever their names.

    A null or empty text has the score that no toxic token gives. Repeated rows are judged alike and stay repeated.
    With labels of one kind only, or none, and with no rows, see fit.
    """
    training = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(bucket("doc_id", 5) != 0)
    crf = docs.sparkSession.sparkContext.broadcast(fit(training, labels.select("doc_id", "toxic")))

    made: list[Tagger] = []  # each task's own, freed with it

    def decide(texts: list[str | None]) -> np.ndarray:
        if not made:
            made.append(Tagger(crf.value))
        return document_scores(crf.value, *made[0].marginals(texts)) < 0.5

    return filter_rows(docs, decide)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tag(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
