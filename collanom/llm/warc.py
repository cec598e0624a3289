"""Web archives: records are written to archive files, read back, and indexed by an external merge.

Every capture becomes one gzip member of an archive. Of captures with equal payloads of at least
`LEAST_PAYLOAD` bytes, the one with the smallest id is a response and the others revisit it. Archives
are rows of a table in the shared folder (name, bytes), so they can live in any store that Spark writes.

Reading back parses and verifies every record and makes each archive's index a locally sorted run. The
runs are cut at splitter keys (URL key, timestamp, id); for every range a loser tree merges the runs'
pieces, so that the ranges, one after another, are a globally ordered capture history. The splitters come
from `SAMPLES` keys a range, chosen by hash from all captures, and only affect how evenly the ranges are
filled; there are as many ranges as captures need, up to `RANGES`, which bounds what the driver sees.

Defined results: a null html is an empty payload; a null url has the empty URL key; repeated rows are
captures of their own (with the smallest id, all are responses); a null id is written as such and sorts
first; captures of one URL and time are ordered by id, then archive and place; an empty table gives no
archives and no rows; a long page is one record, read in bounded pieces; other columns are ignored,
whatever their names.
"""

from __future__ import annotations

import gzip
import hashlib
import re
import zlib
from collections.abc import Callable, Iterable, Iterator
from datetime import UTC, datetime, timedelta
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

LEAST_PAYLOAD = 100
ARCHIVE_BYTES = 4 << 20
#: Captures of a range, and ranges at most (4 keys of each are then sorted on the driver).
RANGE_ROWS, RANGES, SAMPLES = 20_000, 1 << 17, 4
#: Bytes that are read at once.
READ = 1 << 16
#: Rows of revisited payloads up to which their table is broadcast: 100 bytes each; beyond it the join is salted.
BROADCAST_PAYLOADS, SALTS = 200_000, 32
#: Captures without a time of their own are dated this much after the epoch of the crawl, by id.
_CONTROL = re.compile(r"[\x00-\x20\x7f-\x9f\u2028\u2029]")
EPOCH = datetime(2024, 1, 1, tzinfo=UTC)


def url_key(url: str | None) -> str:
    """Sort-friendly form: host labels reversed, scheme, www and fragment dropped, query parameters sorted."""
    if not url:
        return ""
    try:
        parts = urlsplit(url.strip())
        host = re.sub(r"^www\d*\.", "", (parts.hostname or "").lower())
        port = f":{parts.port}" if parts.port and parts.port not in (80, 443) else ""
    except ValueError:
        return url.strip().lower()
    query = "&".join(sorted(filter(None, parts.query.lower().split("&"))))
    return f"{','.join(reversed(host.split('.')))}{port}){parts.path.lower() or '/'}{'?' + query if query else ''}"


def stamp(page: int | None) -> str:
    return (EPOCH + timedelta(seconds=(page or 0) % (1 << 31))).strftime("%Y-%m-%dT%H:%M:%SZ")


def record(page: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One archive record, as a gzip member of its own. A revisit keeps the payload's headers only."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if refers_to is not None else http + payload
    head = {
        "WARC-Type": "response" if refers_to is None else "revisit",
        "WARC-Record-ID": f"<urn:page:{'' if page is None else page}>",
        "WARC-Date": stamp(page),
        "WARC-Target-URI": _CONTROL.sub(lambda m: f"%{ord(m[0]):02X}", url or ""),
        "WARC-Payload-Digest": f"sha256:{digest}",
        "Content-Type": "application/http; msgtype=response",
        "Content-Length": str(len(block)),
    }
    if refers_to is not None:
        head |= {"WARC-Profile": "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "WARC-Refers-To": f"<urn:page:{refers_to}>"}
    raw = b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()).encode("utf-8", "surrogatepass") + b"\r\n" + block + b"\r\n\r\n"
    return gzip.compress(raw, compresslevel=1, mtime=0)


def records(archive: bytes | pa.Buffer) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(offset, length, headers, block) of each record; raises on a record that does not hold together."""
    view, at = memoryview(archive), 0
    while at < len(view):
        member, parts, end = zlib.decompressobj(31), [], at
        while not member.eof:
            if end >= len(view):
                raise ValueError(f"the record at {at} is cut off")
            piece = view[end : end + READ]
            parts.append(member.decompress(piece))
            end += len(piece)
        size = end - at - len(member.unused_data)
        top, _, rest = b"".join(parts).partition(b"\r\n\r\n")
        version, *lines = top.decode("utf-8", "surrogatepass").split("\r\n")
        head = dict(line.split(": ", 1) for line in lines)
        n = int(head["Content-Length"])
        if version != "WARC/1.1" or rest[n:] != b"\r\n\r\n":
            raise ValueError(f"the record at {at} has a wrong length")
        yield at, size, head, rest[:n]
        at += size


def _page(name: str) -> int | None:
    return int(name[10:-1]) if len(name) > 11 else None


def index_entry(archive: str, offset: int, length: int, head: dict[str, str], block: bytes) -> dict:
    """The index line of a record; a response's digest is checked against its payload."""
    http, _, payload = block.partition(b"\r\n\r\n")
    size = int(re.search(rb"Content-Length: (\d+)", http)[1])
    digest = head["WARC-Payload-Digest"].partition(":")[2]
    if head["WARC-Type"] == "response" and (len(payload) != size or hashlib.sha256(payload).hexdigest() != digest):
        raise ValueError(f"the payload at {offset} of {archive} does not match its digest")
    to = head.get("WARC-Refers-To")
    return {
        "url_key": url_key(head["WARC-Target-URI"]),
        "captured": head["WARC-Date"],
        "page_id": _page(head["WARC-Record-ID"]),
        "payload_bytes": size,
        "payload_digest": digest,
        "record_type": head["WARC-Type"],
        "refers_to": _page(to) if to else None,
        "archive": archive,
        "offset": offset,
        "length": length,
    }


_ENTRY = "struct<url_key:string,captured:string,page_id:bigint,payload_bytes:bigint,payload_digest:string,record_type:string,refers_to:bigint,archive:string,offset:bigint,length:bigint>"


def _order(entry: dict) -> tuple:
    page = entry["page_id"]
    return entry["url_key"], entry["captured"], page is not None, page or 0, entry["archive"], entry["offset"]


class LoserTree:
    """k-way merge: every inner node keeps the loser of its match, so a new head plays one path upwards."""

    def __init__(self, runs: list[Iterable], key: Callable = _order) -> None:
        self.key = key
        self.runs = [iter(r) for r in runs]
        self.k = len(self.runs)
        self.heads: list = [None] * self.k
        self.keys: list = [None] * self.k
        for i in range(self.k):
            self._advance(i)
        self.losers = [-1] * self.k
        self.winner = self._play(1) if self.k > 1 else 0

    def _advance(self, i: int) -> None:
        self.heads[i] = next(self.runs[i], None)
        self.keys[i] = None if self.heads[i] is None else self.key(self.heads[i])

    def _before(self, i: int, j: int) -> bool:
        if self.keys[i] is None or self.keys[j] is None:
            return self.keys[j] is None and self.keys[i] is not None
        return (self.keys[i], i) < (self.keys[j], j)

    def _play(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        a, b = self._play(2 * node), self._play(2 * node + 1)
        winner, self.losers[node] = (b, a) if self._before(b, a) else (a, b)
        return winner

    def __iter__(self) -> Iterator:
        while self.k and self.keys[self.winner] is not None:
            yield self.heads[self.winner]
            self._advance(self.winner)
            at, node = self.winner, (self.winner + self.k) // 2
            while node:
                if self._before(self.losers[node], at):
                    at, self.losers[node] = self.losers[node], at
                node //= 2
            self.winner = at


def _with_first(rows: DataFrame) -> DataFrame:
    """The captures with `refers_to`, the smallest id of their payload where that is another one.

    The html is not shuffled where the table of repeated payloads is small; beyond, every payload is dealt
    over `SALTS` keys, so that a popular one is not one task's.
    """
    first = (
        rows.where(F.octet_length("html") >= LEAST_PAYLOAD)
        .groupBy(F.col("digest").alias("d"))
        .agg(F.min("page_id").alias("first"), F.count("*").alias("n"))
        .where("n > 1 and first is not null")
        .drop("n")
    )
    first = stored(first)
    same = F.col("digest") == F.col("d")
    if first.limit(BROADCAST_PAYLOADS + 1).count() <= BROADCAST_PAYLOADS:
        joined = rows.join(F.broadcast(first), same, "left")
    else:
        salted = first.withColumn("salt_d", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        dealt = rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
        joined = dealt.join(salted, same & (F.col("salt") == F.col("salt_d")), "left")
    return joined.select("page_id", "url", "html", "digest", F.when(~F.col("page_id").eqNullSafe(F.col("first")), F.col("first")).alias("refers_to"))


def write(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Archives of all captures: a written table of (archive, content)."""
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))
    dealt = _with_first(rows.withColumn("digest", F.sha2(F.col("html").cast("binary"), 256)))

    def archived(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def done():
            content = b"".join(held)
            return pa.RecordBatch.from_arrays([pa.array([f"{hashlib.sha256(content).hexdigest()[:24]}.warc.gz"]), pa.array([content], pa.binary())], names=["archive", "content"])

        for batch in batches:
            for page, url, html, digest, to in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.append(record(page, url, html.encode("utf-8", "surrogatepass"), digest, to))
                size += len(held[-1])
                if size >= ARCHIVE_BYTES:
                    yield done()
                    held, size = [], 0
        if held:
            yield done()

    return stored(dealt.mapInArrow(archived, "archive string, content binary"))


def _splitters(pages: DataFrame, id_col: str, url_col: str) -> list[tuple]:
    """Keys that cut the order into ranges: of every hash bucket of all captures, the one with the least second hash."""
    ranges = min(RANGES, -(-pages.count() // RANGE_ROWS))
    rows = pages.select(F.col(id_col).cast("long").alias("p"), F.col(url_col).cast("string").alias("u"))
    one = F.min_by(F.struct("p", "u"), F.xxhash64("u", "p", F.lit(1))).alias("one")
    buckets = SAMPLES * max(ranges, 64)
    sample = rows.groupBy(F.pmod(F.xxhash64("p", "u"), F.lit(buckets)).alias("bucket")).agg(one).select("one.p", "one.u").collect()
    keys = sorted((url_key(r["u"]), stamp(r["p"])) for r in sample)
    return sorted({keys[i * len(keys) // ranges] for i in range(1, ranges)})


_ORDER = ("url_key", "captured", "page_id", "archive", "offset")


def merged_order(entries: pa.StructArray, cuts: list[int]) -> list[int]:
    """Places of sorted runs, which lie between the cuts, in their common order."""
    columns = [entries.field(c).to_pylist() for c in _ORDER]

    def run(a: int, b: int) -> Iterator[tuple]:
        for i in range(a, b):
            url, captured, page, archive, offset = (c[i] for c in columns)
            yield (url, captured, page is not None, page or 0, archive, offset), i

    tree = LoserTree([run(a, b) for a, b in zip(cuts, cuts[1:], strict=False)], key=lambda x: x[0])
    return [i for _, i in tree]


def history(archives: DataFrame, splitters: list[tuple]) -> DataFrame:
    """The global index: entries with their range and place, in capture order by (range, place)."""
    from bisect import bisect_right

    known = archives.sparkSession.sparkContext.broadcast(splitters)

    def runs(batches):
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                entries = sorted((index_entry(name, *r) for r in records(content.as_buffer())), key=_order)
                pieces: dict[int, list[dict]] = {}
                for e in entries:
                    pieces.setdefault(bisect_right(known.value, (e["url_key"], e["captured"])), []).append(e)
                kind = pa.list_(pa.struct([(f, pa.int64() if f in ("page_id", "payload_bytes", "refers_to", "offset", "length") else pa.string()) for f in entries[0]]))
                yield pa.RecordBatch.from_arrays([pa.array(list(pieces), pa.int32()), pa.array([name] * len(pieces)), pa.array(list(pieces.values()), kind)], names=["range", "run", "entries"])

    def merged(key, group):
        group = group.sort_by("run").combine_chunks()
        lists = group.column("entries").combine_chunks()
        lists = lists if isinstance(lists, pa.ListArray) else pa.concat_arrays(lists.chunks)
        entries = lists.flatten()
        sizes = [0, *np.cumsum(lists.value_lengths().to_numpy()).tolist()]
        table = pa.Table.from_struct_array(entries.take(pa.array(merged_order(entries, sizes), pa.int64())))
        n = len(table)
        return table.append_column("range", pa.array([key[0].as_py()] * n, pa.int32())).append_column("place", pa.array(range(n), pa.int64()))

    fields = _ENTRY[7:-1].replace(":", " ").replace(",", ", ")
    return archives.mapInArrow(runs, f"range int, run string, entries array<{_ENTRY}>").groupBy("range").applyInArrow(merged, f"{fields}, range int, place bigint")


def report(pages: DataFrame) -> DataFrame:
    """Writes all pages to archives, reads them back and merges their index."""
    found = history(write(pages), _splitters(pages, "page_id", "url"))
    return found.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url_key", "captured", "range", "place")
