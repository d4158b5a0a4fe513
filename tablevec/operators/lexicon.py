"""Word vectors for text values: the lexicon, longest-phrase matching, start vectors and column centroids."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tablevec.functions.vectors import tokens, vec_mean, vec_scale, vec_sum, vec_zero

#: Columns whose whole values are phrases of the stand-in lexicon.
PHRASE_COLUMNS = (("region", "r_name"), ("nation", "n_name"), ("part", "p_brand"), ("part", "p_type"), ("customer", "c_mktsegment"), ("orders", "o_orderpriority"), ("orders", "o_orderstatus"), ("lineitem", "l_returnflag"), ("lineitem", "l_linestatus"))
PHRASES_OF_NAMES = 32
#: Most tokens of all terms that go to the workers as a trie; beyond, phrases are matched by a join. A token takes some
#: 300 bytes of a dictionary, so a worker's trie has 60 MB at most.
TRIE_TOKENS = 200_000
#: Most bytes of a lexicon's vectors that go to the workers; beyond, hits are joined with their vectors.
VECTOR_BYTES = 64 << 20
#: Values that a worker holds the tokens of at once.
VALUES_AT_ONCE = 256


def _joined(text: Column | str) -> Column:
    return F.array_join(tokens(text), " ")


def lexicon_from_tables(frames: dict[str, DataFrame], vectors: DataFrame, corpus: DataFrame | None = None) -> DataFrame:
    """A lexicon (term, tokens, n_tokens, vec) for data that comes with vectors but no words.

    First the phrases of small columns, the words of part names and the first of those names as phrases, by term; then
    the corpus's words, most frequent first. The n-th term gets the vector with vec_id n - 1, and terms without one
    are left out, so ids are given to at most as many terms as there are vectors.
    """
    parts = [frames[t].select(c).distinct().select(_joined(c).alias("term")) for t, c in PHRASE_COLUMNS if t in frames]
    if "part" in frames:
        named = frames["part"].select("p_name").distinct()
        parts.append(named.select(F.explode(tokens("p_name")).alias("term")))
        names = named.select(_joined("p_name").alias("term"), F.size(tokens("p_name")).alias("n")).where("n = 2").select("term").distinct()
        parts.append(names.orderBy("term").limit(PHRASES_OF_NAMES))
    first = parts[0]
    for p in parts[1:]:
        first = first.union(p)
    first = first.where("term != ''").distinct().select(F.lit(1).alias("section"), F.lit(0).cast("long").alias("n"), "term")
    if corpus is not None:
        words = corpus.select(F.explode(tokens("text")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n"))
        second = words.join(first.select("term"), "term", "left_anti").select(F.lit(2).alias("section"), "n", "term")
        first = first.union(second)
    top = first.orderBy("section", F.desc("n"), "term").limit(vectors.count())
    ranked = top.withColumn("vec_id", F.row_number().over(Window.orderBy("section", F.desc("n"), "term")).cast("long") - 1)
    found = ranked.join(vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("vec")), "vec_id")
    return found.select("term", F.split("term", " ").alias("tokens"), F.size(F.split("term", " ")).alias("n_tokens"), "vec")


def read_lexicon_text(spark: SparkSession, path: str) -> DataFrame:
    """Lines of a term, whose words are joined by underscores, and its numbers."""
    parts = F.split("value", " ")
    term = F.lower(F.replace(F.get(parts, F.lit(0)), F.lit("_"), F.lit(" ")))
    made = spark.read.text(path).where(F.size(parts) > 2).select(term.alias("term"), F.transform(F.slice(parts, 2, 1 << 20), lambda x: x.cast("double")).alias("vec"))
    return made.select("term", F.split("term", " ").alias("tokens"), F.size(F.split("term", " ")).alias("n_tokens"), "vec")


def train_lexicon(texts: DataFrame, dims: int = 64, seed: int = 1, least: int = 5) -> DataFrame:
    """A lexicon of single words, self-trained on (text)."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    model = Word2Vec(vectorSize=dims, minCount=least, seed=seed, inputCol="words", outputCol="out", numPartitions=texts.rdd.getNumPartitions()).fit(texts.select(tokens("text").alias("words")))
    return model.getVectors().select(F.col("word").alias("term"), F.array("word").alias("tokens"), F.lit(1).alias("n_tokens"), vector_to_array("vector").alias("vec"))


def build_prefixes(lexicon: DataFrame) -> DataFrame:
    """(prefix, is_term): every leading run of tokens of a term; the prefix tree as a table."""
    every = lexicon.select(F.explode(F.transform(F.sequence(F.lit(1), F.col("n_tokens")), lambda n: F.struct(F.array_join(F.slice("tokens", F.lit(1), n), " ").alias("prefix"), (n == F.col("n_tokens")).alias("is_term")))).alias("p"))
    return every.select("p.*").groupBy("prefix").agg(F.max("is_term").alias("is_term"))


def _trie(terms: list[list[str]]) -> dict:
    root: dict = {}
    for term in terms:
        at = root
        for t in term:
            at = at.setdefault(t, {})
        at[""] = " ".join(term)
    return root


def longest_matches(words: list[str], trie: dict) -> list[str]:
    """Left to right, the longest term that starts at each place; then on after it. Places without a term are skipped."""
    out, i = [], 0
    while i < len(words):
        at = trie.get(words[i])
        if at is None:
            i += 1
            continue
        if len(at) == 1 and "" in at:  # no longer term goes on from here
            out.append(at[""])
            i += 1
            continue
        at, best, j = trie, None, i
        while j < len(words) and words[j] in at:
            at, j = at[words[j]], j + 1
            if "" in at:
                best = (j, at[""])
        if best:
            i = best[0]
            out.append(best[1])
        else:
            i += 1
    return out


def match_phrases(nodes: DataFrame, lexicon: DataFrame, mode: str | None = None) -> DataFrame:
    """(node_id, pos, term): the bag of longest lexicon matches of each value, in order.

    'trie' sends the terms, without vectors, to every worker; 'join' finds all runs of tokens that are terms by a join,
    and then takes them greedily. By default the trie is used for terms of up to TRIE_TOKENS tokens together.
    """
    if mode is None:
        mode = "trie" if (lexicon.agg(F.sum("n_tokens")).first()[0] or 0) <= TRIE_TOKENS else "join"
    if mode == "trie":
        trie = nodes.sparkSession.sparkContext.broadcast(_trie([r["tokens"] for r in lexicon.select("tokens").collect()]))

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for k in range(0, batch.num_rows, VALUES_AT_ONCE):
                    some = batch.slice(k, VALUES_AT_ONCE)
                    found = [longest_matches(words, trie.value) for words in some.column(1).to_pylist()]
                    sizes = np.array([len(f) for f in found], dtype=np.int64)
                    place = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                    yield pa.RecordBatch.from_arrays([pa.array(np.repeat(some.column(0).to_numpy(), sizes)), pa.array(place.astype(np.int32)), pa.array(chain.from_iterable(found), pa.string())], names=["node_id", "pos", "term"])

        return nodes.select("node_id", tokens("value").alias("words")).mapInArrow(work, "node_id long, pos int, term string")
    most = lexicon.agg(F.coalesce(F.max("n_tokens"), F.lit(1))).first()[0]
    spans = F.flatten(F.transform(F.sequence(F.lit(1), F.size("words")), lambda i: F.transform(F.sequence(F.lit(1), F.least(F.lit(most), F.size("words") - i + 1)), lambda n: F.struct(i.alias("at"), n.alias("n"), F.array_join(F.slice("words", i, n), " ").alias("term")))))
    runs = nodes.select("node_id", tokens("value").alias("words")).where(F.size("words") > 0).select("node_id", F.explode(spans).alias("s")).select("node_id", "s.*")
    hits = runs.join(lexicon.select("term"), "term").groupBy("node_id", "at").agg(F.max_by(F.struct("at", "n", "term"), "n").alias("h"))
    ordered = hits.groupBy("node_id").agg(F.array_sort(F.collect_list("h")).alias("all"))
    start = F.struct(F.lit(1).alias("next"), F.array().cast("array<string>").alias("out"))
    taken = F.aggregate("all", start, lambda s, h: F.when(h["at"] >= s["next"], F.struct((h["at"] + h["n"]).alias("next"), F.array_append(s["out"], h["term"]).alias("out"))).otherwise(s), lambda s: s["out"])
    return ordered.select("node_id", F.posexplode(taken).alias("pos", "term"))


def start_vectors(nodes: DataFrame, lexicon: DataFrame, dims: int) -> DataFrame | None:
    """What init_vectors gives for the longest matches, in one pass over the values: no hit is ever a row.

    None for a lexicon whose terms or vectors are too many for the workers, or that _shared gives none of.
    """
    if (lexicon.agg(F.sum("n_tokens")).first()[0] or 0) > TRIE_TOKENS:
        return None
    found = _shared(lexicon, dims)
    if found is None:
        return None
    terms, vectors = found
    words = {r["term"]: r["tokens"] for r in lexicon.select("term", "tokens").collect()}
    number = {}
    for i, term in enumerate(terms.to_pylist()):  # a match is named by its tokens, as a hit is
        number[term] = i
    if any(" ".join(t) != term for term, t in words.items()):
        return None
    shared = nodes.sparkSession.sparkContext.broadcast((_trie(list(words.values())), number, vectors))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie, number, v = shared.value
        for batch in batches:
            for k in range(0, batch.num_rows, VALUES_AT_ONCE):
                some = batch.slice(k, VALUES_AT_ONCE)
                mean, oov = np.zeros((some.num_rows, dims)), np.ones(some.num_rows, dtype=bool)
                for i, tokens_of in enumerate(some.column(3).to_pylist()):
                    at = [number[t] for t in longest_matches(tokens_of, trie)]
                    if at:
                        # each vector once, times its hits: long texts repeat few terms
                        times = np.bincount(at)
                        held = np.flatnonzero(times)
                        mean[i], oov[i] = times[held] @ v[held] / len(at), False
                vec = pa.ListArray.from_arrays(pa.array(np.arange(some.num_rows + 1, dtype=np.int32) * dims), pa.array(mean.ravel()))
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), some.column(2), vec, pa.array(oov)], names=["node_id", "category", "value", "vec", "is_oov"])

    return nodes.select("node_id", "category", "value", tokens("value").alias("words")).mapInArrow(work, "node_id long, category string, value string, vec array<double>, is_oov boolean")


def match_tokens(nodes: DataFrame, lexicon: DataFrame) -> DataFrame:
    """(node_id, pos, term): every single token that is a term; the naive alternative."""
    words = nodes.select("node_id", F.posexplode(tokens("value")).alias("pos", "term"))
    return words.join(lexicon.where("n_tokens = 1").select("term"), "term").select("node_id", "pos", "term")


def _shared(lexicon: DataFrame, dims: int) -> tuple[pa.Array, np.ndarray] | None:
    """Terms and their vectors; None for more than VECTOR_BYTES, other dimensions, missing numbers or terms that come twice."""
    if lexicon.count() * dims * 8 > VECTOR_BYTES:
        return None
    table = lexicon.select("term", F.col("vec").cast("array<double>").alias("vec")).toArrow()
    terms, vectors = table.column("term").combine_chunks(), table.column("vec").combine_chunks()
    flat = vectors.flatten()
    if len(terms) == 0 or vectors.null_count or flat.null_count or pc.any(pc.not_equal(pc.list_value_length(vectors), dims)).as_py() or len(terms.unique()) < len(terms):
        return None
    return terms, flat.to_numpy(zero_copy_only=False).reshape(-1, dims)


def _sums(hits: DataFrame, lexicon: DataFrame, dims: int) -> DataFrame | None:
    """(node_id, n, sum): parts of the sums of the hits' vectors, one for each run of a value's hits in a batch.

    A hit stays a name until its vector is added. None for a lexicon that _shared gives none of.
    """
    found = _shared(lexicon, dims)
    if found is None:
        return None
    shared = hits.sparkSession.sparkContext.broadcast(found)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, v = shared.value
        for b in batches:
            at = pc.index_in(b.column(1), value_set=known)
            held = np.flatnonzero(at.is_valid().to_numpy(zero_copy_only=False))
            if not len(held):
                continue
            node, at = b.column(0).to_numpy()[held], at.fill_null(0).to_numpy()[held]
            first = np.flatnonzero(np.concatenate([[True], node[1:] != node[:-1]]))
            total = np.concatenate([np.add.reduceat(v[at[i:j]], first[k : k + 64] - i, axis=0) for k in range(0, len(first), 64) for i, j in [(first[k], first[k + 64] if k + 64 < len(first) else len(at))]])
            n = np.diff(np.append(first, len(at)))
            yield pa.RecordBatch.from_arrays([pa.array(node[first]), pa.array(n), pa.ListArray.from_arrays(pa.array(np.arange(len(first) + 1, dtype=np.int32) * dims), pa.array(total.ravel()))], names=["node_id", "n", "sum"])

    return hits.select("node_id", "term").mapInArrow(work, "node_id long, n long, sum array<double>")


def init_vectors(nodes: DataFrame, hits: DataFrame, lexicon: DataFrame, dims: int) -> DataFrame:
    """(node_id, category, value, vec, is_oov): the mean of the hits' vectors, repeats counted; zero without any hit."""
    parts = _sums(hits, lexicon, dims)
    if parts is None:
        means = hits.join(lexicon.select("term", "vec"), "term").groupBy("node_id").agg(vec_mean("vec", dims).alias("mean"))
    else:
        sums = parts.groupBy("node_id").agg(vec_sum("sum", dims).alias("sum"), F.sum("n").alias("n"))
        means = sums.select("node_id", vec_scale("sum", F.lit(1.0) / F.col("n")).alias("mean"))
    return nodes.join(means, "node_id", "left").select("node_id", "category", "value", F.coalesce("mean", vec_zero(dims)).alias("vec"), F.col("mean").isNull().alias("is_oov"))


def column_centroids(base: DataFrame, dims: int, include_oov: bool = True) -> DataFrame:
    """(category, centroid): the mean start vector of a column, zero starts included by default."""
    rows = base if include_oov else base.where(~F.col("is_oov"))
    means = rows.groupBy("category").agg(vec_mean("vec", dims).alias("centroid"))
    if include_oov:
        return means
    return base.select("category").distinct().join(means, "category", "left").select("category", F.coalesce("centroid", vec_zero(dims)).alias("centroid"))
