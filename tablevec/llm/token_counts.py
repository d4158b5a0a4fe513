"""How many tokens a unigram tokenizer makes of each text, by a Viterbi search that keeps scores and counts only.

The tokenizer: a text is split at line feeds, which stand alone, and before each space, which is written as U+2581;
every part is cut into the vocabulary pieces with the highest sum of scores. Among equal sums the path whose last
piece starts first wins, which is what the public tokenizers library does. A character that no piece covers costs
the lowest score less 10; its UTF-8 bytes count one token each.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import partial

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tablevec.llm.common import map_arrow, record_batch, slices, table

SPACE = "▁"
UNKNOWN_PENALTY = 10.0
_OUT = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("n_parts", pa.int64())])


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def read_vocabulary(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece file; for a file of merge ranks, the log of Zipf's law at the rank.

    Unknown and byte pieces come first with one low score each, so their spellings in a text never win.
    """
    from sentencepiece import SentencePieceProcessor

    model = SentencePieceProcessor(model_file=path)
    ids = range(model.get_piece_size())
    plain = [i for i in ids if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i)) and SPACE not in model.id_to_piece(i)[1:]]
    scores = [model.get_score(i) for i in plain]
    if all(float(s).is_integer() for s in scores):
        total = math.log(sum(1 / (2 - s) for s in scores))
        scores = [-math.log(2 - s) - total for s in scores]
    low = min(scores, default=0.0) - 20
    return [("<unk>", low)] + [(f"<0x{b:02X}>", low) for b in range(256)] + [(model.id_to_piece(i), s) for i, s in zip(plain, scores)]


class Counter(dict):
    """Tokens of a part, kept for up to `most` parts of up to 48 characters."""

    def __init__(self, vocabulary: list[tuple[str, float]], most: int = 500_000):
        import ahocorasick

        super().__init__()
        self.most, self.automaton = most, ahocorasick.Automaton()
        for piece, score in vocabulary:
            self.automaton.add_word(piece, (len(piece), score))
        self.automaton.make_automaton()
        self.unknown = min(s for _, s in vocabulary) - UNKNOWN_PENALTY
        self.single = {p for p, _ in vocabulary if len(p) == 1}
        self[""] = 0

    def count(self, part: str) -> int:
        n, lowest = len(part), -math.inf
        best, pieces = [0.0] * (n + 1), [0] * (n + 1)
        done = 0  # ends up to here are final
        unknown, single = self.unknown, self.single

        def close(upto: int) -> None:
            """Ends that no piece reaches, or reaches worse: the single character is unknown."""
            nonlocal done
            while done < upto:
                done += 1
                c = part[done - 1]
                if c not in single and (found[done] == lowest or best[done - 1] + unknown > found[done]):
                    found[done] = best[done - 1] + unknown
                    pieces[done] = pieces[done - 1] + len(c.encode("utf-8", "surrogatepass"))
                best[done] = found[done]

        found = [lowest] * (n + 1)
        for end, (length, score) in self.automaton.iter(part):  # by end; longest, so earliest start, first
            end += 1
            if done < end - 1:
                close(end - 1)
            start = end - length
            candidate = best[start] + score
            if candidate > found[end]:
                found[end], pieces[end] = candidate, pieces[start] + 1
        close(n)
        return pieces[n]

    def __missing__(self, part: str) -> int:
        out = self.count(part)
        if len(self) < self.most and len(part) <= 48:
            self[part] = out
        return out


def parts_of(text: str) -> list[str]:
    if SPACE in text:
        text = text.replace(SPACE, " ")
    return [p for p in text.replace(" ", " " + SPACE).replace("\n", " \n ").split(" ") if p]


_COUNTERS: dict[str, Counter] = {}


def _counter(path: str) -> Counter:
    if path not in _COUNTERS:
        _COUNTERS[path] = Counter(read_vocabulary(path))
    return _COUNTERS[path]


def _count(batches: Iterator[pa.RecordBatch], path: str) -> Iterator[pa.RecordBatch]:
    counter = _counter(path)
    for whole in batches:
        for batch in slices(whole, 1, 16 << 20):
            tokens, sizes = [], []
            for text in batch.column(1).to_pylist():
                parts = parts_of(text or "")
                tokens.append(sum(map(counter.__getitem__, parts)))
                sizes.append(len(parts))
            yield record_batch(_OUT, [batch.column(0), tokens, sizes])


def count_tokens(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id, n_tokens and n_parts of every whole text; a null or empty text has none.

    Each row is counted for itself, so repeated rows come out repeated, and other columns of `docs` are ignored. There
    is no shuffle.
    """
    work = partial(_count, path=vocabulary or default_vocabulary())
    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), work, "doc_id long, n_tokens long, n_parts long")


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"))
