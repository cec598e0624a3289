"""Benchmark decontamination with a generalised suffix automaton over test-item words.

The automaton holds every word sequence that occurs inside an item. A document is streamed word by
word while the longest suffix that the automaton knows is tracked; wherever that length reaches the
window (or the whole of an item that is shorter), the words of the window are hit, and the state of the
window names the items that hold it.

Items of more than `SHARD_BYTES` of text make several automata; documents pass them one after another,
with a written table between, so a worker holds one automaton whatever the number of items.

Defined results: null or empty text has no words; items without words never match; repeated rows of
either table are judged one by one, repeated item ids count once, a null item id is hit but not named; an
empty item table hits nothing, an empty document table gives no rows; long texts are streamed whole.
Extra columns are ignored by `find` and carried unchanged by `remove`, whatever their names.
"""

from __future__ import annotations

import hashlib
import re
from array import array
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, stored

WINDOW = 10
#: Items of more text than this are indexed in several automata; one takes about 40 times its text.
SHARD_BYTES = 4 << 20
#: Fixed: bytes that are part of a word after lower-casing A-Z (digits, letters, everything beyond ASCII).
WORD_BYTES = frozenset(range(0x30, 0x3A)) | frozenset(range(0x61, 0x7B)) | frozenset(range(0x80, 0x100))
_FOLD = bytes(x if x in WORD_BYTES else 0x20 for x in (b + 32 if 65 <= b <= 90 else b for b in range(256)))
_SPANS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased words; splitting works on UTF-8 bytes because every separator is ASCII."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()


class SuffixAutomaton:
    """Generalised suffix automaton: sequences are added one after another, each from the root.

    Most states have one edge, which lies in two arrays; only those with more have a table of their own.
    """

    def __init__(self) -> None:
        self.symbol, self.target = array("i", [-1]), array("i", [-1])
        self.more: dict[int, dict[int, int]] = {}
        self.link, self.length = array("i", [-1]), array("i", [0])

    def step(self, state: int, symbol: int) -> int:
        """The state that the symbol leads to, or -1."""
        if self.symbol[state] == symbol:
            return self.target[state]
        return self.more[state].get(symbol, -1) if state in self.more else -1

    def _lead(self, state: int, symbol: int, to: int) -> None:
        if self.symbol[state] in (-1, symbol):
            self.symbol[state], self.target[state] = symbol, to
        else:
            self.more.setdefault(state, {})[symbol] = to

    def _state(self, length: int, link: int) -> int:
        for part, value in ((self.symbol, -1), (self.target, -1), (self.length, length), (self.link, link)):
            part.append(value)
        return len(self.link) - 1

    def _split(self, parent: int, symbol: int) -> int:
        """The child of `parent` by `symbol`, cloned if it also ends longer sequences."""
        child = self.step(parent, symbol)
        if self.length[child] == self.length[parent] + 1:
            return child
        clone = self._state(self.length[parent] + 1, self.link[child])
        self.symbol[clone], self.target[clone] = self.symbol[child], self.target[child]
        if child in self.more:
            self.more[clone] = dict(self.more[child])
        self.link[child] = clone
        while parent >= 0 and self.step(parent, symbol) == child:
            self._lead(parent, symbol, clone)
            parent = self.link[parent]
        return clone

    def add(self, sequence: Iterable[int]) -> None:
        last = 0
        for symbol in sequence:
            if self.step(last, symbol) >= 0:
                last = self._split(last, symbol)
                continue
            new, at = self._state(self.length[last] + 1, 0), last
            while at >= 0 and self.step(at, symbol) < 0:
                self._lead(at, symbol, new)
                at = self.link[at]
            if at >= 0:
                self.link[new] = self._split(at, symbol)
            last = new

    def walk(self, sequence: Iterable[int]) -> Iterator[tuple[int, int]]:
        """For each position, the state and the length of the longest known sequence that ends there."""
        state = matched = 0
        symbols, targets, links, lengths, more = self.symbol, self.target, self.link, self.length, self.more
        for symbol in sequence:
            while True:
                to = targets[state] if symbols[state] == symbol else more[state].get(symbol, -1) if state in more else -1
                if to >= 0 or not state:
                    break
                state = links[state]
                matched = lengths[state]
            if to >= 0:
                state, matched = to, matched + 1
            yield state, matched

    def lengths(self, sequence: Iterable[int]) -> list[int]:
        return [n for _, n in self.walk(sequence)]

    def shortened(self, state: int, size: int) -> int:
        """The state of the last `size` symbols of a sequence that the state ends."""
        while self.length[self.link[state]] >= size:
            state = self.link[state]
        return state


class ItemIndex:
    """Vocabulary, automaton, and the items of every window of a set of test items.

    A window is known by its size and the state of its words, so nothing is kept per window but its items.
    """

    def __init__(self, items: Iterable[tuple[object, str | None]], window: int = WINDOW) -> None:
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        self.automaton = SuffixAutomaton()
        names: dict[str | None, int] = {}
        texts = []
        for item, text in items:
            ids = array("i", [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words_of(text)])
            if ids:
                self.automaton.add(ids)
                texts.append((names.setdefault(None if item is None else str(item), len(names)), ids))
        self.names = list(names)
        self.sizes = sorted({min(window, len(ids)) for _, ids in texts})
        #: by size: the first item of a state's window, and the others where there are more
        self.first = {size: array("i", [-1]) * len(self.automaton.link) for size in self.sizes}
        self.others: dict[tuple[int, int], set[int]] = {}
        for item, ids in texts:
            size = min(window, len(ids))
            first = self.first[size]
            for state, matched in self.automaton.walk(ids):
                if matched >= size:
                    at = self.automaton.shortened(state, size)
                    if first[at] < 0:
                        first[at] = item
                    elif first[at] != item:
                        self.others.setdefault((size, at), set()).add(item)

    def match(self, words: list[bytes]) -> tuple[np.ndarray, set]:
        """Which words are hit, and the names of the items whose windows occur."""
        n = len(words)
        hit, found = np.zeros(n, dtype=bool), set()
        if not self.sizes or n < self.sizes[0]:
            return hit, set()
        ids = np.fromiter(map(self.vocabulary.get, words, _minus(n)), dtype=np.int64, count=n)
        # a match lies within a run of known words
        edges = np.flatnonzero(np.diff(np.concatenate(([False], ids >= 0, [False])).view(np.int8)))
        least = self.sizes[0]
        for a, b in zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True):
            if b - a < least:
                continue
            for i, (state, matched) in enumerate(self.automaton.walk(ids[a:b].tolist()), a + 1):
                if matched < least:
                    continue
                for size in self.sizes:
                    if matched < size:
                        break
                    at = self.automaton.shortened(state, size)
                    if (item := self.first[size][at]) >= 0:
                        hit[i - size : i] = True
                        found.add(item)
                        found |= self.others.get((size, at), set())
        return hit, {self.names[i] for i in found} - {None}


class _minus:
    """As many -1 as words, for map()."""

    def __init__(self, n: int) -> None:
        self.n = n

    def __iter__(self):
        from itertools import repeat

        return repeat(-1, self.n)


def _shards(items: DataFrame, item_col: str, text_col: str) -> Iterator[list[tuple[object, str]]]:
    """The item table, fetched part by part; at least one part, which may be empty."""
    shard: list[tuple[object, str]] = []
    held, any_ = 0, False
    for row in items.select(F.col(item_col).alias("i"), F.col(text_col).cast("string").alias("t")).toLocalIterator():
        shard.append((row["i"], row["t"]))
        held += len((row["t"] or "").encode("utf-8", "surrogatepass"))
        if held >= SHARD_BYTES:
            yield shard
            shard, held, any_ = [], 0, True
    if shard or not any_:
        yield shard


def _runs(hit: np.ndarray) -> list[list[int]]:
    edges = np.flatnonzero(np.diff(np.concatenate(([False], hit, [False])).view(np.int8))).tolist()
    return [list(x) for x in zip(edges[::2], edges[1::2], strict=True)]


def _passed(rows: DataFrame, index: ItemIndex, finish: Callable | None = None) -> DataFrame:
    """Rows (row, text, n, items, runs) after a pass over the automaton of one shard; `finish` gives the text that is left, or says that the row goes."""
    shared = rows.sparkSession.sparkContext.broadcast(index)

    def run(batches):
        own = shared.value
        for batch in batches:
            for part in slices(batch):
                texts, sizes, names, runs = part.column(1).to_pylist(), [], [], []
                for text, known, before in zip(texts, part.column(3).to_pylist(), part.column(4).to_pylist(), strict=True):
                    words = words_of(text)
                    hit, found = own.match(words)
                    for a, b in before:
                        hit[a:b] = True
                    sizes.append(len(words))
                    names.append(sorted(found.union(known)))
                    runs.append(_runs(hit) if hit.any() else [])
                done = [texts, sizes, names, runs]
                kept = None
                if finish:
                    cuts = [finish(t, r) for t, r in zip(texts, runs, strict=True)]
                    done[0], kept = [t for _, t in cuts], pa.array([k for k, _ in cuts], pa.bool_())
                out = pa.RecordBatch.from_arrays([part.column(0), *(pa.array(v, f.type) for v, f in zip(done, list(part.schema)[1:], strict=True))], schema=part.schema)
                yield out.filter(kept) if finish else out

    return rows.mapInArrow(run, rows.schema)


def _marked(docs: DataFrame, items: DataFrame, window: int, text_col: str, item_col: str, item_text: str, finish: Callable | None = None) -> DataFrame:
    """(row, text, n, items, runs): other columns as a struct, text, words, the items found and the hit word runs; one pass per shard of the items."""
    others = [F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns) if c != text_col]
    none = F.array().cast("array<array<bigint>>")
    rows = docs.select(F.struct(F.lit(0).alias("c"), *others).alias("row"), F.col(f"`{text_col}`").cast("string").alias("text"), F.lit(0).cast("long").alias("n"), F.array().cast("array<string>").alias("items"), none.alias("runs"))
    last = None
    for shard in _shards(items, item_col, item_text):
        if last is not None:
            rows = stored(_passed(rows, ItemIndex(last, window)))
        last = shard
    return _passed(rows, ItemIndex(last, window), finish)


def find(
    docs: DataFrame, items: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text"
) -> DataFrame:
    """Per document: words, hit words, the items found, and the hit word runs as [start, end) pairs."""
    marked = _marked(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), items, window, "text", item_col, item_text)
    n_hit = F.aggregate("runs", F.lit(0).cast("long"), lambda n, r: n + r[1] - r[0])
    return marked.select(F.col("row.c0").alias("doc_id"), F.col("n").alias("n_words"), n_hit.alias("n_hit"), "items", "runs")


def digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()


def report(docs: DataFrame, items: DataFrame, window: int = WINDOW) -> DataFrame:
    """The digest columns of `find`."""
    return find(docs, items, window).select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items").cast("binary"), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
        F.coalesce(F.array_max(F.transform("runs", lambda r: r[1] - r[0])), F.lit(0)).alias("longest_run"),
    )


def cut(text: str | None, runs: list[list[int]], max_span: int, max_coverage: float) -> tuple[bool, str | None]:
    """Whether a document stays, and its text without hit runs of `max_span` words or more."""
    if not text or not runs:
        return True, text
    places = [m.span() for m in _SPANS.finditer(text.translate(_LOWER))]
    if sum(b - a for a, b in runs) > max_coverage * len(places):
        return False, text
    kept, at = [], 0
    for a, b in runs:
        if b - a >= max_span:
            kept.append(text[at : places[a][0]])
            at = places[b - 1][1]
    return True, "".join([*kept, text[at:]])


def remove(docs: DataFrame, items: DataFrame, window: int = WINDOW, max_span: int = WINDOW, max_coverage: float = 0.5, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The documents with contaminated runs of at least `max_span` words cut out of the text.

    A document of which more than `max_coverage` of the words are hit goes altogether. Runs shorter
    than `max_span` come only from items that are shorter than the window; they stay unless the
    caller lowers the limit. All columns are kept as they are.
    """
    left = _marked(docs, items, window, text_col, item_col, item_text, lambda text, runs: cut(text, runs, max_span, max_coverage))
    kind = docs.schema[text_col].dataType
    return left.select(*[F.col("text").cast(kind).alias(c) if c == text_col else F.col(f"row.c{i}").alias(c) for i, c in enumerate(docs.columns)])
