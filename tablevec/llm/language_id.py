"""Language identification by the nearest of several centroids per language, with rejection by distance.

A text is the TF-IDF vector of its hashed character trigrams inside words (word ends count as a character), with the
square root of the counts as TF, scaled to unit length. Document frequencies cover all training documents. The
training vectors of each language, of a bounded sample, are clustered on the sphere; a text gets the language of the
centroid with the largest cosine. A short text lies farther from any centroid than a long one, so the text is rejected
if its cosine is less than a share of what training texts of its length have.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import bucket, filter_rows, map_arrow, record_batch, slices, table

DIMENSIONS = 4096
CENTROIDS = 4
#: Bounds of the sample that is clustered: documents for each language, and in all.
SAMPLE_PER_LANGUAGE, SAMPLE_IN_ALL = 500, 4000
#: A text is rejected below this share of the usual cosine at its length.
LEAST_SHARE = 0.28
UNDETERMINED = "und"
_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("lang_pred", pa.string()), ("score", pa.float64()), ("rejected", pa.bool_())])


@lru_cache(1)
def _letters() -> np.ndarray:
    """For each code point, itself if it is a letter, else 0."""
    return np.fromiter((c if chr(c).isalpha() else 0 for c in range(0x110000)), np.uint32, 0x110000)


def trigram_counts(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """Counts of hashed trigrams (texts x DIMENSIONS) and of letters for each text."""
    parts = [np.frombuffer((t or "").lower().encode("utf-32-le", "surrogatepass"), dtype=np.uint32) for t in texts]
    sizes = np.array([len(p) + 2 for p in parts])
    ends = np.cumsum(sizes)
    codes = np.zeros(ends[-1] + 1 if len(parts) else 1, dtype=np.uint32)
    letters = _letters()
    for p, end in zip(parts, ends):
        codes[end - len(p) - 1 : end - 1] = letters[p]
    at = np.flatnonzero(codes)
    left, here, right = codes[at - 1], codes[at], codes[at + 1]
    hashed = (left * np.uint32(0x9E3779B1) + here) * np.uint32(0x85EBCA6B) + right
    hashed = (hashed ^ (hashed >> np.uint32(15))) * np.uint32(0xC2B2AE35)
    slot = (hashed >> np.uint32(20)).astype(np.int64)
    owner = np.searchsorted(ends, at, side="right")
    found = np.bincount(owner * DIMENSIONS + slot, minlength=len(parts) * DIMENSIONS)
    return found.reshape(len(parts), DIMENSIONS), np.bincount(owner, minlength=len(parts))


def _unit(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    v = np.sqrt(counts, dtype=np.float32) * idf
    return v / np.maximum(np.sqrt(np.einsum("ij,ij->i", v, v)), 1e-12)[:, None]


def _groups(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for batch in slices(whole, column, 1 << 20):
            for start in range(0, batch.num_rows, 128):
                yield batch.slice(start, 128)


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(DIMENSIONS, dtype=np.int64)
    for batch in _groups(batches, 0):
        total += (trigram_counts(batch.column(0).to_pylist())[0] > 0).sum(axis=0)
    slots = np.flatnonzero(total)
    yield record_batch(pa.schema([("slot", pa.int32()), ("n", pa.int64())]), [slots, total[slots]])


def _sampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in _groups(batches, 0):
        counts = trigram_counts(batch.column(0).to_pylist())[0]
        packed = [row.astype("<u4").tobytes() for row in counts]
        yield record_batch(pa.schema([("lang", pa.string()), ("counts", pa.binary())]), [batch.column(1), packed])


@dataclass(frozen=True)
class Model:
    languages: list[str]
    idf: np.ndarray
    centroids: np.ndarray  # languages in a row, each with the same number of centroids
    #: Usual cosine at 2 ** i letters.
    usual: np.ndarray

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        counts, letters = trigram_counts(texts)
        if not self.languages:
            return [UNDETERMINED] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        cosine = (_unit(counts, self.idf) @ self.centroids.T).reshape(len(texts), len(self.languages), -1).max(axis=2)
        best = cosine.argmax(axis=1)
        score = np.where(letters > 0, np.clip(cosine[np.arange(len(texts)), best], 0, 1), 0.0).astype(float)
        usual = np.interp(np.log2(np.maximum(letters, 1)), np.arange(len(self.usual)), self.usual)
        names = [self.languages[b] if n else UNDETERMINED for b, n in zip(best, letters)]
        return names, score, (letters == 0) | (score < LEAST_SHARE * usual)


def _cluster(vectors: np.ndarray, k: int) -> np.ndarray:
    """k-means on the sphere, started at vectors far from each other; fewer distinct vectors repeat a centroid."""
    start = vectors.mean(axis=0)
    centers = [start / max(np.linalg.norm(start), 1e-12)]
    while len(centers) < k:
        centers.append(vectors[(vectors @ np.array(centers).T).max(axis=1).argmin()])
    centers = np.array(centers, dtype=np.float32)
    for _ in range(12):
        nearest = (vectors @ centers.T).argmax(axis=1)
        for j in range(k):
            if (mine := vectors[nearest == j]).size:
                m = mine.mean(axis=0)
                centers[j] = m / max(np.linalg.norm(m), 1e-12)
    return centers


def _usual(sample: list[tuple[str, np.ndarray]], idf: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """Median cosine to the nearest centroid of texts thinned to 2 ** i letters."""
    rng, out = np.random.default_rng(7), []
    docs = [c for _, c in sample][:: max(1, len(sample) // 400)]
    for i in range(21):
        rows = []
        for c in docs:
            n = int(c.sum())
            if n >= 2**i:
                rows.append(rng.multivariate_hypergeometric(c.astype(np.int64), 2**i))
        if len(rows) < 5:
            break
        out.append(float(np.median((_unit(np.array(rows), idf) @ centroids.T).max(axis=1))))
    return np.array(out or [0.0])


def fit(training: DataFrame) -> Model:
    """Learns from (doc_id, text, lang); rows without text or language are left out."""
    rows = training.where(F.col("text").isNotNull() & F.col("lang").isNotNull()).select("text", "lang", "doc_id")
    sizes = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}  # languages, a small set
    if not sizes:
        return Model([], np.zeros(DIMENSIONS), np.zeros((0, DIMENSIONS)), np.zeros(1))
    total = np.zeros(DIMENSIONS)
    for r in map_arrow(rows.select("text"), _frequencies, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).collect():
        total[r["slot"]] = r["n"]
    idf = (np.log((1 + sum(sizes.values())) / (1 + total)) + 1).astype(np.float32)
    each = max(10, min(SAMPLE_PER_LANGUAGE, SAMPLE_IN_ALL // len(sizes)))
    scale = 1 << 30
    share = F.create_map(*[F.lit(x) for lang, n in sizes.items() for x in (lang, min(scale, scale * each // n))])
    chosen = rows.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(scale)) < F.element_at(share, F.col("lang")))
    sample = [(r["lang"], np.frombuffer(r["counts"], dtype="<u4")) for r in map_arrow(chosen.select("text", "lang"), _sampled, "lang string, counts binary").limit(2 * each * len(sizes) + 1000).collect()]  # about `each` rows a language
    sample.sort(key=lambda r: (r[0], r[1].tobytes()))
    languages, centroids = sorted({lang for lang, c in sample if c.any()}), []
    for lang in languages:
        centroids.append(_cluster(_unit(np.array([c for x, c in sample if x == lang and c.any()]), idf), CENTROIDS))
    if not languages:
        return Model([], idf, np.zeros((0, DIMENSIONS)), np.zeros(1))
    stacked = np.concatenate(centroids)
    return Model(languages, idf, stacked, _usual(sample, idf, stacked))


def _predicted(batches: Iterator[pa.RecordBatch], model: Model) -> Iterator[pa.RecordBatch]:
    for batch in _groups(batches, 2):
        yield record_batch(_OUT, [batch.column(0), batch.column(1), *model.predict(batch.column(2).to_pylist())])


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score and rejected for every whole text of (doc_id, text, lang).

    The third of documents whose crc32 leaves 1 is held out of learning. A text that is null or has no letter is
    `und` with score 0, and rejected; a rejected text with letters keeps its nearest language. Repeated rows come out
    repeated; other columns are ignored. Without training rows all are `und`.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"), (bucket("doc_id", 3) == 1).alias("held_out"))
    model = docs.sparkSession.sparkContext.broadcast(fit(own.where(~F.col("held_out"))))
    work = lambda batches: _predicted(batches, model.value)
    return map_arrow(own.select("doc_id", "held_out", "text"), work, "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean")


def keep_identified(docs: DataFrame) -> DataFrame:
    """The rows of (doc_id, text, lang, ...) whose text is not rejected, with all their columns, whatever their names.

    Null and empty texts and texts without letters go, and without training rows all go. Repeated rows are judged alike
    and stay repeated.
    """
    training = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where(bucket("doc_id", 3) != 1)
    model = docs.sparkSession.sparkContext.broadcast(fit(training))
    return filter_rows(docs, lambda texts: np.concatenate([~model.value.predict(texts[k : k + 128])[2] for k in range(0, len(texts), 128)]))


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "documents"))
