"""SimHash near-duplicates: deletion-variant signatures, equality of a variant and verification.

A fingerprint has 64 bits; bit b is set if it is set in over half of the shingle hashes (XXH64,
seed 42). Two fingerprints link at `max_bits` or fewer differing bits. The bits are cut into
`max_bits // 2 + 1` segments, so that in one of them a linked pair differs in at most one bit. For
each bit of each segment the segment with that bit left out is a key; a linked pair shares such a
key, and the distance over all bits is then verified.

Exact copies share a fingerprint and are joined as one, so a group of copies costs one row. A pair
is taken only at the first key that it shares. Keys with over `HOT_KEY` fingerprints are compared in
square tiles, each of which returns a spanning forest of its links instead of all of them.

Defined results: a text without words (or null) has fingerprint zero, linked like any other; repeated
rows are copies; null ids are kept and never name a component unless all its ids are null; equal ids of
different texts name their components alike; an empty table gives no rows; texts of any length are
read whole; other columns are ignored by `components` and carried unchanged by `keep_one`, whatever
their names.
"""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, join_by_hot_key, per_row, stored
from .components import connected_components

SEED = 42
#: Segments of a fingerprint where several fingerprints are used.
PARTS = 3
#: Fingerprints at one key above which the key is compared in tiles.
HOT_KEY = 4096
TILE = 2048
#: Parts of a segment: a text goes to a place for each of them, with the bits of the others.
BLOCKS = 3
#: Rows at one key of several fingerprints up to which keys are compared together.
SHIFTS = 64
#: Rows that a worker compares at once.
BUCKET_ROWS = 1 << 16
#: Rows at one place above which it is compared in tiles of about so many rows.
HOT_PLACE = 1 << 18
_LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))


def fingerprint_set(text: str | None, shingle: int = 4, seeds: int = 1) -> list[int]:
    """Fingerprints as unsigned numbers: the first from the hashes themselves, others from the hashes mixed anew. Words are cut at ASCII white space."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    n = len(words)
    if not n:
        return [0] * seeds
    joined = b" ".join(words)
    if n <= shingle:
        hashes = [xxhash.xxh64_intdigest(joined, SEED)]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=n) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))
        hash_of = xxhash.xxh64_intdigest
        hashes = [hash_of(joined[a:b], SEED) for a, b in zip(starts[: n - shingle + 1].tolist(), ends[shingle - 1 :].tolist(), strict=True)]
    packed = np.array(hashes, dtype="<u8")
    return [_majority(packed if k == 0 else _mixed(packed, k)) for k in range(seeds)]


def _mixed(x: np.ndarray, k: int) -> np.ndarray:
    x = x + np.uint64(k * 0x9E3779B97F4A7C15 & (1 << 64) - 1)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _majority(packed: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    votes = np.zeros(64, dtype=np.int64)
    for at in range(0, len(packed), 65536):
        votes += np.unpackbits(packed[at : at + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(packed), bitorder="little").view("<u8")[0])


def fingerprint(text: str | None, shingle: int = 4) -> int:
    return fingerprint_set(text, shingle)[0]


def fingerprints(docs: DataFrame, shingle: int = 4, seeds: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fps) with the fingerprints as signed longs of the same bits; map-only."""
    kind = docs.schema[id_col].dataType.simpleString()

    def make():
        def each(doc, text):
            return doc, [x - (1 << 64) if x >> 63 else x for x in fingerprint_set(text, shingle, seeds)]

        return each

    return per_row(docs, make, f"doc_id {kind}, fps array<bigint>", id_col, text_col)


def segments(n: int) -> list[tuple[int, int]]:
    """(first bit, width) of n segments."""
    edges = [round(i * 64 / n) for i in range(n + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:], strict=False)]


def _part(bits: Column, first: int, width: int) -> Column:
    return F.shiftrightunsigned(bits, first).bitwiseAND(F.lit((1 << width) - 1).cast("long"))


def _key(first: int, width: int, bit: int) -> Column:
    """The segment without one bit, below the bit's number and the seed's: one long per variant."""
    others = F.lit(~(1 << (bit - first))).cast("long")
    return _part(F.col("fp"), first, width).bitwiseAND(others).bitwiseOR(F.lit(bit << 54).cast("long")).bitwiseOR(F.shiftleft(F.col("seed").cast("long"), 60))


def _first_shared(x: Column, cut: list[tuple[int, int]]) -> Column:
    """The bit whose variant is the first that a pair shares, from the pair's differing bits x."""
    out = F.lit(-1)
    for first, width in reversed(cut):
        part = _part(x, first, width)
        out = F.when(part == 0, F.lit(first)).when(F.bit_count(part) == 1, F.bit_count(part - 1) + first).otherwise(out)
    return out


def links(distinct: DataFrame, max_bits: int = 4, parts: int | None = None, hot_key: int = HOT_KEY) -> DataFrame:
    """Links (seed, a, b) between different fingerprints of a table with one row per (seed, fp); seeds are 0 to 7.

    All links of keys with up to `hot_key` fingerprints, a spanning forest of those of other keys: what
    hangs together is always the same. With `max_bits // 2 + 1` parts (the default) no link is missed. Fewer parts make rarer keys; then a
    pair is found if one of its parts differs in at most one bit.
    """
    cut = segments(parts or max(2, max_bits // 2 + 1))
    variants = F.array(*[_key(first, width, bit) for first, width in cut for bit in range(first, first + width)])
    rows = distinct.select("seed", "fp", F.explode(variants).alias("key")).select("fp", "key")
    hot = stored(_hot_keys(distinct, cut, hot_key))
    some_hot = bool(hot.head(1))
    cool = rows.join(hot, "key", "left_anti") if some_hot else rows
    a, b = cool.select(F.col("fp").alias("a"), F.col("key").alias("key_a")), cool.select(F.col("fp").alias("b"), F.col("key").alias("key_b"))
    x = F.col("a").bitwiseXOR(F.col("b"))
    first = _first_shared(x, cut) == F.shiftrightunsigned("key_a", 54).bitwiseAND(F.lit(63).cast("long"))
    seed = F.shiftrightunsigned("key_a", 60).cast("int").alias("seed")
    # both sides are some 64 rows a fingerprint, of which Spark's estimate knows nothing: it would broadcast them
    pairs = a.hint("merge").join(b.hint("merge"), (F.col("key_a") == F.col("key_b")) & (F.col("a") < F.col("b")) & (F.bit_count(x) <= max_bits) & first).select(seed, "a", "b")
    return pairs.unionByName(_tiled(rows, hot, max_bits)) if some_hot else pairs


def _hot_keys(distinct: DataFrame, cut: list[tuple[int, int]], hot_key: int) -> DataFrame:
    """(key, count): every key with over `hot_key` fingerprints, and a bound of their number.

    A key holds the fingerprints of two whole segments; so only segments with over half as many are
    looked at, a row a segment instead of one a variant.
    """
    whole = F.array(*[F.struct(F.lit(i).alias("part"), _part(F.col("fp"), first, width).alias("value")) for i, (first, width) in enumerate(cut)])
    counts = distinct.select("seed", F.explode(whole).alias("w")).groupBy("seed", "w.part", "w.value").count().where(F.col("count") * 2 > hot_key)
    keys = None
    for i, (first, width) in enumerate(cut):
        of = counts.where(F.col("part") == i).select("seed", "count", F.shiftleft("value", first).alias("fp"))
        own = of.select("count", F.explode(F.array(*[_key(first, width, bit) for bit in range(first, first + width)])).alias("key"))
        keys = own if keys is None else keys.unionByName(own)
    return keys.groupBy("key").agg((F.max("count") * 2).alias("count"))


def _tiled(rows: DataFrame, hot: DataFrame, max_bits: int) -> DataFrame:
    """Links at the hot keys: each key's fingerprints fall in parts, and each two parts are one task's tile."""
    parts = F.ceil(F.col("count") / TILE).cast("int")
    dealt = rows.join(hot, "key").select("key", "fp", parts.alias("n"), F.pmod(F.xxhash64("fp"), parts).cast("int").alias("part"))
    tiles = dealt.select("key", "fp", "part", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("other")).select("key", "fp", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"))

    def forest(key, group):
        fps = np.unique(group.column("fp").to_numpy()).view(np.uint64)
        root = np.arange(len(fps))
        edges = []

        def top(v):
            while root[v] != v:
                root[v] = root[root[v]]
                v = root[v]
            return v

        for i in range(len(fps)):
            for j in (np.flatnonzero(np.bitwise_count(fps[i + 1 :] ^ fps[i]) <= max_bits) + i + 1).tolist():
                p, q = top(i), top(j)
                if p != q:
                    root[q] = p
                    edges.append((i, j))
        signed = fps.view(np.int64)
        at = np.array(edges, dtype=np.int64).reshape(-1, 2)
        return pa.table({"seed": pa.array([key[0].as_py() >> 60] * len(at), pa.int32()), "a": signed[at[:, 0]], "b": signed[at[:, 1]]})

    return tiles.groupBy("key", "i", "j").applyInArrow(forest, "seed int, a bigint, b bigint")


def allowed_bits(similarity: float, bits: int, spare: float = 2.0) -> int:
    """Differing bits of two texts whose shingles have this Jaccard index: the mean and some standard deviations."""
    p = math.acos(min(1.0, 2 * similarity / (1 + similarity))) / math.pi
    return int(bits * p + spare * math.sqrt(bits * p * (1 - p)))


def _bucket_forest(fps: np.ndarray, k: int, max_bits: int, total_bits: int) -> list[tuple[int, int]]:
    """A spanning forest of the verified links of one bucket, as rows (i, j).

    A row outside the largest group is held against all rows of other groups and is then done; rows that
    have become one group need no look at each other. So a group of near copies costs its size, and
    strangers cost their number times the size.
    """
    comp = np.arange(len(fps))
    left = comp.copy()
    edges = []
    while True:
        sizes = np.bincount(comp[left])
        if np.count_nonzero(sizes) < 2:
            return edges
        at = int(np.argmax(comp[left] != np.argmax(sizes)))
        i, left = int(left[at]), np.delete(left, at)
        near = left[comp[left] != comp[i]]
        near = near[np.bitwise_count(fps[near, k] ^ fps[i, k]) <= max_bits]
        near = near[np.bitwise_count(fps[near] ^ fps[i]).sum(axis=1, dtype=np.int64) <= total_bits]
        others, first = np.unique(comp[near], return_index=True)
        edges += [(i, int(j)) for j in near[first]]
        comp[np.isin(comp, others)] = comp[i]


def blocks() -> list[tuple[int, int, int, int]]:
    """(segment's first bit and width, first bit and width of the part that has the wildcard) of all places of a fingerprint."""
    out = []
    for first, width in segments(PARTS):
        cuts = [first + round(i * width / BLOCKS) for i in range(BLOCKS + 1)]
        out += [(first, width, a, b - a) for a, b in zip(cuts, cuts[1:], strict=False)]
    return out


def _places(fp: Column) -> Column:
    """Where a fingerprint is compared: for every block of every segment, the segment's other bits below the block's number.

    All variants of a segment whose wildcard lies in the block meet there, so they are made after the
    shuffle: nine rows a fingerprint go through it instead of one a variant.
    """
    found = []
    for number, (first, width, at, size) in enumerate(blocks()):
        others = ((1 << width) - 1) & ~(((1 << size) - 1) << (at - first))
        found.append(_part(fp, first, width).bitwiseAND(F.lit(others).cast("long")).bitwiseOR(F.lit(number << 40).cast("long")))
    return F.array(*found)


def _place_links(place: np.ndarray, fps: np.ndarray, k: int, max_bits: int, total_bits: int) -> list[tuple[int, int]]:
    """Verified links of rows ordered by place, as rows (i, j): every pair that shares a variant there, or a forest of a large bucket."""
    found = []
    own = np.ascontiguousarray(fps[:, k])
    number = place >> 40
    for code, (_, _, at, size) in enumerate(blocks()):
        low, high = np.searchsorted(number, [code, code + 1])
        if high - low < 2:
            continue
        rows = np.arange(low, high)
        part = (own[low:high] >> np.uint64(at) & np.uint64((1 << size) - 1)).astype(np.int64)
        here = np.concatenate(([0], np.cumsum(place[low + 1 : high] != place[low : high - 1])))
        for bit in range(size):
            key = here << size | part & ~(1 << bit)
            order = np.argsort(key, kind="stable")
            ordered, rank = key[order], rows[order]
            starts = np.flatnonzero(np.concatenate(([True], ordered[1:] != ordered[:-1])))
            counts = np.diff(np.append(starts, len(ordered)))
            for a, n in zip(starts[counts > SHIFTS].tolist(), counts[counts > SHIFTS].tolist(), strict=True):
                held = rank[a : a + n]
                if bit and (part[held - low] == part[held[0] - low]).all():
                    continue  # seen at the block's first bit
                found += [(int(held[i]), int(held[j])) for i, j in _bucket_forest(fps[held], k, max_bits, total_bits)]
            bucket = np.repeat(np.arange(len(starts)), counts)
            some = np.flatnonzero(np.repeat((counts > 1) & (counts <= SHIFTS), counts))
            for d in range(1, SHIFTS):
                some = some[some + d < len(ordered)]
                some = some[bucket[some] == bucket[some + d]]
                if not len(some):
                    break
                i, j = rank[some], rank[some + d]
                # rows that agree in the whole block meet at each of its variants and are looked at once
                fresh = (part[i - low] != part[j - low]) | (bit == 0)
                i, j = i[fresh], j[fresh]
                near = np.bitwise_count(own[i] ^ own[j]) <= max_bits
                i, j = i[near], j[near]
                close = np.bitwise_count(fps[i] ^ fps[j]).sum(axis=1, dtype=np.int64) <= total_bits
                found += zip(i[close].tolist(), j[close].tolist(), strict=True)
    return found


class _Forest:
    """Union of nodes; says which links join anything new."""

    def __init__(self) -> None:
        self.root: dict = {}

    def top(self, v):
        root = self.root
        while (up := root.get(v, v)) != v:
            root[v] = root.get(up, up)
            v = up
        return v

    def join(self, a, b) -> bool:
        p, q = self.top(a), self.top(b)
        if p == q:
            return False
        self.root[q] = p
        return True


def _forests(links_: DataFrame) -> DataFrame:
    """Of links (a, b) those that join anything new in their task: what hangs together stays the same, and a group keeps links by its members and not by its pairs."""

    def run(batches):
        forest = _Forest()
        for batch in batches:
            fresh = [forest.join(a, b) for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)]
            yield batch.filter(pa.array(fresh, pa.bool_()))

    return links_.select("a", "b").mapInArrow(run, "a bigint, b bigint")


def _compared(placed: DataFrame, seeds: int, k: int, max_bits: int, total_bits: int) -> DataFrame:
    """Links (a, b) between nodes of (place, node, p0, p1, ..): pairs of a place that share a variant of seed k there, within `max_bits` in seed k and `total_bits` over all seeds. A task returns a spanning forest of its links."""

    def run(batches):
        forest, held, n = _Forest(), [], 0

        def out(columns):
            place, node, fps = columns[0], columns[1], np.stack(columns[2:], axis=1).view(np.uint64)
            fresh = [(a, b) for i, j in _place_links(place, fps, k, max_bits, total_bits) if forest.join(a := int(node[i]), b := int(node[j]))]
            at = np.array(fresh, dtype=np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array(at[:, 0]), pa.array(at[:, 1])], names=["a", "b"])

        for batch in batches:
            held.append([c.to_numpy() for c in batch.columns])
            n += batch.num_rows
            last = held[-1][0]
            if n >= BUCKET_ROWS and last[0] != last[-1]:  # what follows the last place's first row is kept for the next round
                cut = int(np.searchsorted(last, last[-1]))
                tail = [c[cut:] for c in held[-1]]
                held[-1] = [c[:cut] for c in held[-1]]
                yield out([np.concatenate(c) for c in zip(*held, strict=True)])
                held, n = [tail], len(tail[0])
        if n:
            yield out([np.concatenate(c) for c in zip(*held, strict=True)])

    names = ["place", "node", *[f"p{i}" for i in range(seeds)]]
    return placed.select(*names).repartition("place").sortWithinPartitions("place").mapInArrow(run, "a bigint, b bigint")


def _compared_tiles(placed: DataFrame, hot: DataFrame, seeds: int, k: int, max_bits: int, total_bits: int) -> DataFrame:
    """The same at the hot places (place, n): their nodes fall in parts, and each two parts are one task's tile."""
    parts = F.ceil(F.col("n") / HOT_PLACE).cast("int")
    dealt = placed.join(F.broadcast(hot), "place").withColumn("m", parts).withColumn("i", F.pmod(F.xxhash64("node"), F.col("m")).cast("int"))
    tiles = dealt.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("m") - 1)))
    names = [f"p{i}" for i in range(seeds)]
    tiles = tiles.select("place", "node", *names, F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"))

    def tile(group):
        place, node = group.column("place").to_numpy(), group.column("node").to_numpy()
        fps = np.stack([group.column(c).to_numpy() for c in names], axis=1).view(np.uint64)
        forest = _Forest()
        fresh = [(a, b) for i, j in _place_links(place, fps, k, max_bits, total_bits) if forest.join(a := int(node[i]), b := int(node[j]))]
        at = np.array(fresh, dtype=np.int64).reshape(-1, 2)
        return pa.table({"a": at[:, 0], "b": at[:, 1]})

    return tiles.groupBy("place", "i", "j").applyInArrow(tile, "a bigint, b bigint")


def _node_links(nodes: DataFrame, seeds: int, max_bits: int, total_bits: int, hot_place: int = HOT_PLACE) -> DataFrame:
    """Links (a, b) between nodes (node, fps) of several fingerprints, as many as groups need and not as many as pairs.

    At every variant of every seed all nodes are compared: those within `max_bits` in that seed and within
    `total_bits` over all seeds link. A place (14 bits) with more than `hot_place` nodes is split into tiles;
    at most nodes times nine over `hot_place` places are hot.
    """
    wide = stored(nodes.select("node", *[F.col("fps")[i].alias(f"p{i}") for i in range(seeds)]))
    every = F.array(*[F.struct(F.lit(k).alias("k"), _places(F.col(f"p{k}")).alias("places")) for k in range(seeds)])
    counts = wide.select(F.explode(every).alias("s")).select("s.k", F.explode("s.places").alias("place")).groupBy("k", "place").agg(F.count("*").alias("n"))
    hot = stored(counts.where(F.col("n") > hot_place))
    heated = {r["k"] for r in hot.select("k").distinct().collect()}
    each = []
    for k in range(seeds):  # a seed at a time: the rows of one are shuffled and gone before those of the next
        placed = wide.withColumn("place", F.explode(_places(F.col(f"p{k}"))))
        if k in heated:
            own = hot.where(F.col("k") == k).select("place", "n")
            cool = placed.join(F.broadcast(own.select("place")), "place", "left_anti")
            found = _compared(cool, seeds, k, max_bits, total_bits).unionByName(_compared_tiles(placed, own, seeds, k, max_bits, total_bits))
        else:
            found = _compared(placed, seeds, k, max_bits, total_bits)
        each.append(stored(found))
    links_ = stored(reduce(DataFrame.unionByName, each))
    discard(wide, hot, *each)
    return links_


def _grouped(docs: DataFrame, shingle: int, max_bits: int, seeds: int, similarity: float | None, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame, int]:
    """Fingerprinted rows (doc_id, fps, node), written; (node, first_id, n, root) of their nodes, written; and the number of rows."""
    marked = stored(fingerprints(docs, shingle, seeds, id_col, text_col).withColumn("node", F.col("fps")[0] if seeds == 1 else F.xxhash64("fps")))
    nodes = stored(marked.groupBy("node").agg(F.min("doc_id").alias("first_id"), F.min("fps").alias("fps"), F.count("*").alias("n")))
    if seeds == 1:
        found = stored(_forests(links(nodes.select(F.lit(0).alias("seed"), F.col("node").alias("fp")), max_bits)))
    else:
        found = _node_links(nodes, seeds, max_bits, allowed_bits(similarity or 0.8, 64 * seeds))
    roots = connected_components(found).withColumnRenamed("node", "linked")  # of linked nodes only
    discard(found)
    joined = nodes.join(roots, F.col("node") == F.col("linked"), "left").select("node", "first_id", "n", F.coalesce("root", "node").alias("root"))
    return marked, stored(joined), int(nodes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])


def components(docs: DataFrame, shingle: int = 4, max_bits: int = 4, seeds: int = 1, similarity: float | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp, component_id): the smallest id reachable over links, copies included.

    With one seed, texts link at `max_bits` or fewer differing bits of their fingerprints. With several
    and a `similarity`, every text has as many independent fingerprints; a pair that shares a deletion
    variant of one of them, within `max_bits`, links if the bits of all of them differ by no more than
    those of texts of that similarity do. All pairs are compared at every variant, and links are returned
    as forests, so a large group of near copies costs no more links than it has members.
    """
    marked, nodes, rows = _grouped(docs, shingle, max_bits, seeds, similarity, id_col, text_col)
    least = nodes.groupBy("root").agg(F.min("first_id").alias("component_id"), F.count("*").alias("n"))
    named = join_by_hot_key(nodes.withColumnRenamed("n", "copies"), least, "root", rows).select("node", F.col("copies").alias("n"), "component_id")
    return join_by_hot_key(marked, named, "node", rows).select("doc_id", F.col("fps")[0].alias("fp"), "component_id")


def report(docs: DataFrame) -> DataFrame:
    """The digest columns of `components`."""
    hexed = F.lpad(F.lower(F.hex("fp")), 16, "0")
    return components(docs).select("doc_id", hexed.alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, shingle: int = 5, max_bits: int = 16, seeds: int = 6, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group of near-duplicates: of those with the smallest id, the one with the smallest hash of its text; null ids come last.

    The search is probabilistic: a pair is seen if in one of the seeds' segments it differs in at most one
    bit, which of pairs at the similarity itself 95 in 100 do.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    row = F.struct(F.col(id_col).isNull().alias("no_id"), F.col(id_col).alias("id"), F.xxhash64(text).alias("text"))
    name = "__row" if "__row" not in docs.columns else f"__row_{len(''.join(docs.columns))}"
    marked, nodes, _ = _grouped(docs.select(row.alias("row"), F.col(text_col).alias("text")), shingle, max_bits, seeds, similarity, "row", "text")
    kept = stored(nodes.groupBy("root").agg(F.min("first_id").alias(name)).select(name))
    once = docs.withColumn(name, row).join(kept, name, "left_semi")
    repeated = stored(marked.groupBy(F.col("doc_id").alias(name)).count().where("count > 1").select(name).join(kept, name, "left_semi"))
    if repeated.head(1):  # rows of the same id and text: one of them
        once = once.join(repeated, name, "left_anti").unionByName(once.join(repeated, name, "left_semi").dropDuplicates([name]))
    return once.select(*docs.columns)
