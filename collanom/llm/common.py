"""Helpers shared by the text operators: table access, shared folders, Arrow output."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Text of a block that is hashed and counted together.
BLOCK_BYTES = 8 << 20
#: Text that a worker holds decoded at once.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; the path may be in any store that Spark reads."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """A fresh folder below spark.checkpoint.dir; where that is unset (tests), below a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        context = spark.sparkContext
        if context.getCheckpointDir() is None:
            context.setCheckpointDir(tempfile.mkdtemp(prefix="collanom-"))
        base = context.getCheckpointDir()
    return f"{base.rstrip('/')}/collanom-{uuid.uuid4().hex}"


def stored(df: DataFrame) -> DataFrame:
    """Cuts the lineage: written as Parquet in the shared folder and read again."""
    path = shared_folder(df.sparkSession)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.stored_path = path
    return out


def discard(*frames: DataFrame) -> None:
    """Deletes the files of `stored` tables that nothing reads any more; other frames are left alone."""
    for df in frames:
        if path := df.__dict__.pop("stored_path", None):
            spark = df.sparkSession
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


#: A join doesn't hash a key with more rows than a `HOT_SHARE`th of all (between the two numbers of `HOT_ROWS`); at most `HOT_KEYS` keys have so many.
HOT_SHARE, HOT_ROWS, HOT_KEYS = 500, (200, 10_000), 100_000


def hot_limit(rows: int) -> int:
    """Rows above which a key of a table with so many rows is hot: of up to five million rows at most `HOT_SHARE` keys are."""
    low, high = HOT_ROWS
    return max(low, min(high, rows // HOT_SHARE), rows // HOT_KEYS)


def join_by_hot_key(left: DataFrame, right: DataFrame, key: str, rows: int) -> DataFrame:
    """`left` joined to `right`, which has one row per key and in `n` the number of its rows in `left` (`rows` in all).

    Keys with more than `hot_limit` rows meet in a broadcast: there are at most `HOT_KEYS` of them, so its size
    is bounded whatever the data. The others are hashed, and none of them is large.
    """
    limit = hot_limit(rows)
    found = right.where(F.col("n") > limit).collect()
    if not found:
        return left.join(right.drop("n"), key)
    hot = left.sparkSession.createDataFrame(found, right.schema).drop("n")
    rest = left.join(F.broadcast(hot.select(key)), key, "left_anti")
    return left.join(F.broadcast(hot), key).unionByName(rest.join(right.where(F.col("n") <= limit).drop("n"), key))


def text_bytes(df: DataFrame, text: str = "text") -> int:
    """UTF-8 bytes of a text column over all rows (nulls count as none)."""
    return int(df.agg(F.coalesce(F.sum(F.octet_length(F.col(text))), F.lit(0)).alias("n")).first()["n"])


def slices(batch: pa.RecordBatch, size: int = SLICE_BYTES, text: int = 1) -> Iterator[pa.RecordBatch]:
    """A batch in runs of rows of about `size` text bytes each, so that a worker's memory is bounded."""
    column = batch.column(text)
    if batch.num_rows < 2 or column.nbytes <= size:
        if batch.num_rows:
            yield batch
        return
    half = batch.num_rows // 2
    yield from slices(batch.slice(0, half), size, text)
    yield from slices(batch.slice(half), size, text)


def per_row(
    df: DataFrame,
    make: Callable[[], Callable[[object, str], tuple]],
    schema: str,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """One output row per input row from (id, text); a null text is read as empty.

    `make` is called once per task and gives the function applied to each row; map-only, no shuffle.
    """
    fields = StructType.fromDDL(schema)
    arrow = _arrow_schema(fields)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = make()
        for batch in batches:
            for part in slices(batch):
                rows = [each(i, t or "") for i, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True)]
                columns = list(zip(*rows, strict=True)) if rows else [[] for _ in arrow]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, arrow, strict=True)], schema=arrow)

    source = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return source.mapInArrow(run, fields)


def _arrow_schema(fields) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(fields)
