"""Exact substring deduplication by Rabin-Karp hashes of fixed-length word windows, counted in Spark.

Documents are dealt into blocks of bounded text. A block's windows are hashed by a rolling polynomial
over 64-bit word hashes; the block's distinct hashes (those that occur more than once in it, twice) go
to counting buckets as arrays, 8 bytes a window and a frequent passage once per block. Spark explodes
and counts them there; what occurs more than once goes back to its blocks, where the repeated windows
merge into maximal intervals that are removed. The hot passages, hosts and copies are thereby summed
before they are shuffled.

The bucket is taken from a second polynomial with a base of its own, so two windows are compared only if
both agree: 64 bits and those of the bucket's number. Buckets hold a fixed amount of text and as many
partitions as buckets are made, so tasks don't grow with the data, and of n windows n^2 / 2^65 over the
number of buckets are expected to collide: 5e-7 a bucket.

Defined results: null or empty texts have no words and stay empty; texts shorter than the window are
kept whole; repeated rows are copies of each other and lose what they repeat; ties don't arise; an empty
table gives no rows; a long text is one block's, whole; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BLOCK_BYTES, slices, text_bytes

WINDOW = 35
#: Hashes of about so much text are counted together.
BUCKET_BYTES = 16 << 20
#: Fixed: the odd bases of the two polynomials.
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


def words_of(text: str | None) -> list[bytes]:
    """Words as they are, cut at ASCII white space."""
    return (text or "").encode("utf-8", "surrogatepass").split()


class _Hashes(dict):
    """XXH64 of each word, kept while a block is hashed."""

    def __missing__(self, word: bytes) -> int:
        self[word] = x = xxhash.xxh64_intdigest(word, 7)
        return x


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    np.multiply.accumulate(out, out=out)
    return out


def _rolled(x: np.ndarray, starts: np.ndarray, window: int, base: int) -> np.ndarray:
    """The polynomial hash of every window, mixed."""
    sums = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(x * _powers(base, len(x)), out=sums[1:])
    h = (sums[starts + window] - sums[starts]) * _powers(pow(base, -1, 1 << 64), len(x))[starts]
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    return h


def window_hashes(docs: list[list[bytes]], window: int = WINDOW) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Two hashes of every window, and its place among all words."""
    sizes = np.array([len(w) for w in docs], dtype=np.int64)
    n, seen = int(sizes.sum()), _Hashes()
    if not n or sizes.max() < window:
        return np.empty(0, np.uint64), np.empty(0, np.uint64), np.empty(0, np.int64)
    x = np.fromiter((seen[w] for words in docs for w in words), dtype=np.uint64, count=n)
    ends = np.repeat(np.cumsum(sizes), sizes)
    starts = np.flatnonzero(np.arange(n) + window <= ends)
    return _rolled(x, starts, window, BASES[0]), _rolled(x, starts, window, BASES[1]), starts


def _buckets_of(g: np.ndarray, buckets: int) -> np.ndarray:
    return ((g >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def _hash_block(key: tuple, block: pa.Table, window: int, buckets: int) -> pa.Table:
    """(bucket, block, hashes) rows: distinct hashes by bucket, and once more those that occur twice."""
    parts = [window_hashes([words_of(t) for t in part.column("text").to_pylist()], window)[:2] for batch in block.select(["text"]).combine_chunks().to_batches() for part in slices(batch, text=0)]
    h, g = (np.concatenate([p[i] for p in parts]) if parts else np.empty(0, np.uint64) for i in (0, 1))
    bucket = _buckets_of(g, buckets)
    order = np.lexsort((h, bucket))
    h, bucket = h[order], bucket[order]
    same = np.concatenate(([False], (h[1:] == h[:-1]) & (bucket[1:] == bucket[:-1])))
    # the first two of equal ones stay
    third = same & np.concatenate(([False], same[:-1]))
    h, bucket = h[~third].view(np.int64), bucket[~third]
    cuts = np.searchsorted(bucket, np.arange(buckets + 1))
    rows = [(i, h[a:b]) for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if a < b]
    return pa.table(
        {
            "bucket": pa.array([i for i, _ in rows], pa.int32()),
            "block": pa.array([key[0].as_py()] * len(rows), pa.int32()),
            "hashes": pa.array([v for _, v in rows], pa.list_(pa.int64())),
        }
    )


def removed_words(docs: list[list[bytes]], repeated: list[np.ndarray], window: int, buckets: int) -> list[np.ndarray]:
    """For each document, which of its words lie in a repeated window; `repeated` has the sorted hashes of each bucket."""
    sizes = [len(w) for w in docs]
    h, g, starts = window_hashes(docs, window)
    change = np.zeros(sum(sizes) + 1, np.int64)
    bucket = _buckets_of(g, buckets)
    order = np.argsort(bucket, kind="stable")
    cuts = np.searchsorted(bucket[order], np.arange(buckets + 1))
    for i, known in enumerate(repeated):
        mine = order[cuts[i] : cuts[i + 1]]
        if len(known) and len(mine):
            at = np.minimum(np.searchsorted(known, h[mine]), len(known) - 1)
            hit = starts[mine[known[at] == h[mine]]]
            np.add.at(change, hit, 1)
            np.add.at(change, hit + window, -1)
    gone = np.cumsum(change)[:-1] > 0
    return np.split(gone, np.cumsum(sizes)[:-1]) if sizes else []


def _cut_block(block: pa.Table, answers: pa.Table, window: int, buckets: int, digest: bool) -> pa.Table:
    repeated = [np.empty(0, np.uint64)] * buckets
    for bucket, hashes in zip(answers.column("bucket").to_pylist(), answers.column("hashes"), strict=True):
        repeated[bucket] = np.sort(hashes.values.to_numpy().view(np.uint64))
    out = []
    for batch in block.combine_chunks().to_batches():
        for part in slices(batch, text=batch.schema.get_field_index("text")):
            docs = [words_of(t) for t in part.column("text").to_pylist()]
            gone = removed_words(docs, repeated, window, buckets)
            kept = [b" ".join([w for w, g in zip(words, cut.tolist(), strict=True) if not g] if cut.any() else words) for words, cut in zip(docs, gone, strict=True)]
            last = [hashlib.sha256(k).hexdigest() for k in kept] if digest else [k.decode("utf-8", "surrogatepass") for k in kept]
            out.append(
                pa.table(
                    {
                        "doc_id": part.column("doc_id"),
                        "n_words": pa.array([len(w) for w in docs], pa.int64()),
                        "n_removed": pa.array([int(x.sum()) for x in gone], pa.int64()),
                        "n_intervals": pa.array([int((np.diff(np.concatenate(([0], x.astype(np.int8)))) == 1).sum()) for x in gone], pa.int64()),
                        "kept_sha256" if digest else "kept": pa.array(last, pa.string()),
                    }
                )
            )
    return pa.concat_tables(out) if out else block.select(["doc_id"]).slice(0, 0)


def deduplicate(docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """Per document: doc_id, n_words, n_removed, n_intervals, and the words kept, joined by one space.

    With `digest` the kept text is replaced by its SHA-256 (kept_sha256), made where the text is.
    """
    source = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    size = text_bytes(source)
    blocks, buckets = max(1, -(-size // BLOCK_BYTES)), max(1, -(-size // BUCKET_BYTES))
    # the partition's number parts the copies of one row; it depends on no order within a partition
    dealt = source.withColumn("block", F.pmod(F.xxhash64("doc_id", "text", F.spark_partition_id()), F.lit(blocks)).cast("int"))
    kind = docs.schema[id_col].dataType.simpleString()

    def hashed(key, block):
        return _hash_block(key, block, window, buckets)

    def cut(block, answers):
        return _cut_block(block, answers, window, buckets, digest)

    packed = dealt.groupBy("block").applyInArrow(hashed, "bucket int, block int, hashes array<bigint>")
    # a partition is a bucket, so what follows needs no shuffle until the answers go back to their blocks
    rows = packed.repartitionById(buckets, F.col("bucket")).select("bucket", "block", F.explode("hashes").alias("h"))
    counted = rows.withColumn("n", F.count("*").over(Window.partitionBy("bucket", "h"))).where("n > 1")
    answers = counted.groupBy("bucket", "block").agg(F.collect_set("h").alias("hashes"))
    last = "kept_sha256 string" if digest else "kept string"
    return dealt.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(cut, f"doc_id {kind}, n_words bigint, n_removed bigint, n_intervals bigint, {last}")


def report(docs: DataFrame) -> DataFrame:
    """The digest columns of `deduplicate`."""
    return deduplicate(docs, digest=True)
