"""Line deduplication by site-relative frequency, with DataFrame functions only.

Of the documents of a host, the share that contains a line is the line's frequency there; lines above
the ratio, and in at least `LEAST_DOCS` documents of the host, are boilerplate and are dropped. A line
is known by two independent 64-bit hashes; hosts are compared as they are.

The boilerplate of a host is at most its mean number of lines over the ratio, so it is kept as one
array per host; documents meet their host's array in a join. That table is broadcast if its measured
size is below `BROADCAST_BYTES`; otherwise the join's hot hosts are salted.

Defined results: a null text has no lines and stays null, an empty text is one blank line; blank lines
(only white space) are never boilerplate; a null host is a host of its own; repeated rows are documents
of their own; a line exactly at the ratio stays; an empty table gives no rows; long texts are read whole;
all columns are carried unchanged, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

RATIO = 0.05
LEAST_DOCS = 3
BROADCAST_BYTES = 16 << 20
SALTS = 32


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _key(line: Column) -> Column:
    return F.struct(F.xxhash64(line).alias("a"), F.xxhash64(line, F.lit(1)).alias("b"))


def _blank(line: Column) -> Column:
    return F.length(F.trim(F.regexp_replace(line, r"[\t\r\x0b\f]", " "))) == 0


def boilerplate(docs: DataFrame, ratio: float = RATIO, least: int = LEAST_DOCS, host_col: str = "source", text_col: str = "text") -> DataFrame:
    """(host, n_docs, lines): the keys of the boilerplate lines of every host that has any."""
    source = docs.select(F.col(host_col).alias("host"), F.col(text_col).cast("string").alias("text"))
    totals = source.groupBy("host").agg(F.count("*").alias("n_docs"))
    lines = source.select("host", F.explode(F.array_distinct(_lines(F.col("text")))).alias("line")).where(~_blank(F.col("line")))
    keyed = lines.select("host", F.xxhash64("line").alias("a"), F.xxhash64("line", F.lit(1)).alias("b"))
    counts = keyed.groupBy("host", "a", "b").agg(F.count("*").alias("n")).where(F.col("n") >= least)
    common = counts.join(totals.withColumnRenamed("host", "h"), F.col("host").eqNullSafe(F.col("h"))).where(F.col("n") > F.col("n_docs") * ratio)
    return common.groupBy("host").agg(F.max("n_docs").alias("n_docs"), F.collect_list(F.struct("a", "b")).alias("lines"))


def _joined(rows: DataFrame, ratio: float, least: int) -> DataFrame:
    """(row, host, text) with `kept`, the lines that stay."""
    known = stored(boilerplate(rows, ratio, least, "host", "text")).select(F.col("host").alias("h"), "lines")
    size = known.agg(F.coalesce(F.sum(F.size("lines") * 16 + F.coalesce(F.length("h"), F.lit(0))), F.lit(0)).alias("n")).first()["n"]
    same = F.col("host").eqNullSafe(F.col("h"))
    if size <= BROADCAST_BYTES:
        joined = rows.join(F.broadcast(known), same, "left")
    else:
        salted = known.withColumn("salt_b", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        dealt = rows.withColumn("salt_a", (F.monotonically_increasing_id() % SALTS).cast("int"))
        joined = dealt.join(salted, same & (F.col("salt_a") == F.col("salt_b")), "left")
    stays = F.filter(_lines(F.col("text")), lambda x: _blank(x) | ~F.array_contains(F.col("lines"), _key(x)))
    return joined.withColumn("kept", F.when(F.col("lines").isNull(), _lines(F.col("text"))).otherwise(stays))


def _rows(docs: DataFrame, host_col: str, text_col: str) -> DataFrame:
    """(row, host, text): the columns that the operator reads beside all others, which are in a struct and so clash with nothing."""
    others = [F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns) if c != text_col]
    return docs.select(F.struct(F.lit(0).alias("c"), *others).alias("row"), F.col(f"`{host_col}`").alias("host"), F.col(f"`{text_col}`").cast("string").alias("text"))


def deduplicate(docs: DataFrame, ratio: float = RATIO, least: int = LEAST_DOCS, host_col: str = "source", text_col: str = "text") -> DataFrame:
    """The documents without their hosts' boilerplate lines; all columns are kept as they are."""
    marked = _joined(_rows(docs, host_col, text_col), ratio, least)
    text = F.when(F.col("text").isNotNull(), F.concat_ws("\n", "kept")).cast(docs.schema[text_col].dataType).alias(text_col)
    return marked.select(*[text if c == text_col else F.col(f"row.c{i}").alias(c) for i, c in enumerate(docs.columns)])


def report(docs: DataFrame) -> DataFrame:
    """Per document: lines, dropped lines, and the SHA-256 of the text that stays."""
    lines = F.coalesce(F.size(_lines(F.col("text"))), F.lit(0))
    kept = F.coalesce(F.size("kept"), F.lit(0))
    n = F.when(F.col("text").isNull(), 0).otherwise(lines)
    return _joined(_rows(docs.select("doc_id", "source", "text"), "source", "text"), RATIO, LEAST_DOCS).select(
        F.col("row.c0").alias("doc_id"),
        n.cast("long").alias("n_lines"),
        F.when(F.col("text").isNull(), 0).otherwise(n - kept).cast("long").alias("n_dropped"),
        F.sha2(F.coalesce(F.concat_ws("\n", "kept"), F.lit("")).cast("binary"), 256).alias("kept_sha256"),
    )


#: The same in SQL, by the text of the lines.
SQL = f"""
WITH pages AS (SELECT row_number() OVER () AS r, doc_id, source, text, CASE WHEN text IS NULL THEN [] ELSE string_split(text, chr(10)) END AS lines FROM documents),
hosts AS (SELECT source, count(*) AS n_docs FROM pages GROUP BY source),
each AS (SELECT source, unnest(list_distinct(lines)) AS line FROM pages),
common AS (
  SELECT e.source, e.line FROM each e JOIN hosts h ON e.source IS NOT DISTINCT FROM h.source
  WHERE length(trim(e.line, ' ' || chr(9) || chr(11) || chr(12) || chr(13))) > 0
  GROUP BY e.source, e.line, h.n_docs HAVING count(*) >= {LEAST_DOCS} AND count(*) > h.n_docs * {RATIO}),
sets AS (SELECT source, list(line) AS gone FROM common GROUP BY source),
kept AS (
  SELECT p.doc_id, p.lines, CASE WHEN s.gone IS NULL THEN p.lines ELSE list_filter(p.lines, lambda x: NOT list_contains(s.gone, x)) END AS kept
  FROM pages p LEFT JOIN sets s ON p.source IS NOT DISTINCT FROM s.source)
SELECT doc_id, len(lines)::BIGINT AS n_lines, (len(lines) - len(kept))::BIGINT AS n_dropped,
  sha256(coalesce(array_to_string(kept, chr(10)), '')) AS kept_sha256
FROM kept
"""
