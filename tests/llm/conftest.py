"""Helpers of the text operators' tests."""

from __future__ import annotations

import pytest

#: Nulls, empty and blank texts, ties, repeated rows and a long text.
AWKWARD = [
    (1, None, "en", "a"),
    (2, "", "en", "a"),
    (3, "   \n\t ", "en", None),
    (4, "one", None, "a"),
    (4, "one", None, "a"),
    (None, "a row without an id, of some words", "en", "b"),
    (6, "word " * 60_000, "en", "b"),
    (7, "Ünï cödé \U0001f600 tail", "xx", "b"),
]


@pytest.fixture(scope="session")
def awkward(spark):
    """Awkward rows, with extra columns whose names clash with internal ones."""
    from pyspark.sql import functions as F

    df = spark.createDataFrame(AWKWARD, "doc_id bigint, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long"))
    return df.withColumns({c: F.lit(7) for c in ("fp", "key", "block", "node", "score", "id", "host", "line", "n_words", "bucket", "hashes", "__host", "__lines", "__kept", "__row", "row", "lines", "kept", "h", "n", "c", "c0", "runs", "items", "place", "a", "b")})


@pytest.fixture(scope="session")
def empty(spark):
    return spark.createDataFrame([], "doc_id bigint, text string, lang string, source string, n_chars bigint")


@pytest.fixture(scope="session")
def corpus(spark, sf):
    """The small table's documents as (id, text)."""
    return [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
