"""A cleaning pipeline over `documents`: five stages, each written as Parquet and read by the next.

Toxic documents go, boilerplate lines are dropped, one document of each group of near-duplicates stays,
benchmark passages are cut out, and what is left is encoded. Every stage but the last returns the
columns of `documents`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from collanom.llm import decontaminate, linededup, pieces, simhash, toxicity
from collanom.llm.common import discard, stored, table


def _counted(docs: DataFrame) -> DataFrame:
    """The column n_chars in step with a changed text."""
    return docs.withColumn("n_chars", F.coalesce(F.char_length("text").cast("long"), F.col("n_chars"))) if "n_chars" in docs.columns else docs


def toxicity_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the learned lexicon scores as toxic go.

    Null and blank texts score as texts without hits, repeated rows alike; long texts are scored whole; an
    empty table stays empty, and with no labels of one class nothing is learned; other columns are kept.
    """
    return toxicity.reject(docs, toxicity.learn(docs, table(spark, sf_dir, "labels")))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that are frequent in their source go.

    A null source is a source of its own; a null text stays null and an empty one empty, blank lines stay;
    repeated rows are documents of their own; a line exactly at the ratio stays; other columns are kept.
    """
    return _counted(linededup.deduplicate(docs))


def simhash_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near-duplicates the document with the smallest id stays.

    Texts without words (null, empty, blank) are one group; null ids come after all others, and rows
    without one are told apart by their texts; of repeated rows one stays; an empty table stays empty;
    other columns are kept as they are.
    """
    return simhash.keep_one(docs)


def benchmark_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Benchmark passages are cut out; documents that are mostly passages go.

    Null and empty texts stay as they are, repeated rows are judged one by one; without items nothing is
    cut; long texts are streamed whole; other columns are kept.
    """
    return _counted(decontaminate.remove(docs, table(spark, sf_dir, "benchmark")))


def sentencepiece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token numbers of every document, and whether they decode to its text.

    Null and empty texts have no tokens; repeated rows are encoded one by one; an empty table gives no
    rows; long texts are encoded whole; other columns than the id are left out.
    """
    return pieces.encode(docs)


STAGES = [
    ("toxicity", toxicity_filter),
    ("line dedup", line_dedup),
    ("SimHash near-dedup", simhash_dedup),
    ("benchmark decontamination", benchmark_decontamination),
    ("SentencePiece encoding", sentencepiece_encoding),
]

#: SQL can express neither the learned lexicon nor the encoding.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table `documents`."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        last, docs = docs, stored(stage(spark, docs, sf_dir))
        discard(last)  # of the stages' tables the one that is read next stays
    return STAGES[-1][1](spark, docs, sf_dir)
