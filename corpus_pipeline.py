"""Corpus preparation in five stages, each a function of (spark, docs, sf_dir) that returns a DataFrame.

Every stage but the last returns the columns of its documents. `run` writes each stage's rows as Parquet in the shared
folder and reads them again for the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tablevec.llm import decontamination, language_id, near_duplicates, packing, toxicity
from tablevec.llm.common import Scratch, table


def keep_identified_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has letters and lies near enough to a language's centroids.

    Null and empty texts go; repeated rows are judged alike; other columns stay, whatever their names.
    """
    return language_id.keep_identified(docs)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose toxicity score is under a half.

    Null and empty texts have the score that no toxic token gives; repeated rows are judged alike; other columns stay.
    """
    return toxicity.keep_clean(docs, table(spark, sf_dir, "labels"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents linked by five-word shingles at 0.8 or more, the document of the smallest doc_id.

    Of repeated rows one stays, also if their doc_id is null; rows that share a doc_id but not a text are documents of
    their own. Texts without words stay; other columns stay.
    """
    return near_duplicates.keep_first(docs)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds no benchmark passage.

    Null and empty texts stay; repeated rows are judged alike; other columns stay.
    """
    return decontamination.keep_uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all that is left, with their sequences.

    Null and empty texts are one piece of the end token; repeated rows are pieces of their own. Token ids go along with
    pack_documents(docs, with_ids=True), and packing.sequences lays them out.
    """
    return packing.pack_documents(docs)


STAGES = [
    ("language ID", keep_identified_languages),
    ("toxicity", drop_toxic),
    ("near-duplicates", drop_near_duplicates),
    ("benchmark decontamination", drop_benchmark_leaks),
    ("best-fit packing", pack),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents; what only a stage that is written has read is deleted."""
    scratch, before = Scratch(spark, "pipeline"), None
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        mark = Scratch.mark()
        docs = scratch.keep(stage(spark, docs, sf_dir), f"stage{k}")
        Scratch.drop_since(mark)
        if before:
            scratch.drop(before)
        before = f"stage{k}"
    return docs
