"""SentencePiece encoding and decoding over a word lattice.

A text becomes words: runs of spaces (written as the space sign) with the letters that follow, and line
ends by themselves; no piece goes over a word's edge. The lattice of a word has an edge for every
substring, up to the longest piece, that is in the piece table; a Viterbi pass over its places keeps one
best path to each. What is best depends on the model:

* unigram models: the path of the greatest sum of scores.
* byte-pair models: their scores are ranks of merges and don't add up; a sum of ranks gives other pieces
  than the model does. But merges never cross a border of the result, so pieces are the model's result if
  and only if every two neighbours are that of their own joint text. Exactly one path to each place is:
  the pass keeps it, asking of an edge whether its piece may follow the last piece of the path to its
  beginning. The answers are kept.

In the query words are encoded inside map tasks, each distinct word of a task once. `encode_vocabulary`
is the relational form: explode substrings, equi-join to the piece table, group edges by word, fold with
Spark's higher-order aggregate (for byte-pair models with the pairs that may meet joined too).

Characters without a piece fall back to byte pieces. Decoding joins the pieces and drops the first
space; every text without the space sign itself is decoded exactly.

Defined results: null and empty texts have no tokens and decode to the empty text; repeated rows are
encoded one by one; of unigram paths with equal sums the one whose last pieces begin first; an empty
table gives no rows; long texts are encoded whole, long words too, in memory proportional to them; other
columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slices

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
#: Words that a task keeps encoded.
KEPT_WORDS = 200_000
#: Pairs of pieces whose answer a task keeps.
KEPT_PAIRS = 400_000
_NONE = float("-inf")
#: In place of a piece: no path yet, the beginning, a character without a piece.
_OPEN, _BEGIN, _RAW = -3, -2, -1
_WORDS = re.compile(r" *[^ \n]+| +|\n")


@dataclass
class PieceTable:
    """Pieces with their numbers and scores; `byte_base` is the number of the piece for byte 0."""

    pieces: list[str]
    scores: list[float]
    byte_base: int
    merges: bool
    ids: dict[str, int] = field(default_factory=dict)
    longest: int = 0
    rank: dict[str, float] = field(default_factory=dict)
    reached: dict[str, int] = field(default_factory=dict)

    def __post_init__(self) -> None:
        first = 0 if self.byte_base < 0 else self.byte_base + 256
        self.ids = {p: i for i, p in enumerate(self.pieces) if i >= first}
        self.longest = max(map(len, self.ids), default=1)
        self.rank = {p: self.scores[i] for p, i in self.ids.items()}
        # pieces that merging makes of their own text; others are in no result
        self.reached = {p: i for p, i in self.ids.items() if not self.merges or merged(p, self) == [p]}

    def bytes_of(self) -> list[bytes]:
        """What each piece stands for when a text is decoded."""
        low = self.byte_base
        return [bytes([i - low]) if 0 <= low <= i < low + 256 else b"" if low >= 0 and i < low else p.replace(SPACE, " ").encode() for i, p in enumerate(self.pieces)]


def load(path: str = MODEL) -> PieceTable:
    """The table of a model file; whether its scores are merge ranks is read from them."""
    import os

    import sentencepiece

    if not os.path.exists(path):
        raise FileNotFoundError(f"no model file at {path}; give its path")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = range(model.get_piece_size())
    scores = [model.get_score(i) for i in n]
    base = next((i for i in n if model.is_byte(i)), -1)
    ranks = [s for i, s in enumerate(scores) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i))]
    return PieceTable([model.id_to_piece(i) for i in n], scores, base, merges=all(s == int(s) for s in ranks))


def _fallback(sign: str, table: PieceTable) -> list[int]:
    return [table.byte_base + b for b in sign.encode("utf-8", "surrogatepass")] if table.byte_base >= 0 else [0]


def merged(word: str, table: PieceTable) -> list[str]:
    """The pieces that merging leads to: again and again the neighbours whose joint piece ranks highest, the first of equals."""
    parts, rank = list(word), table.rank.get
    joint = [rank(a + b, _NONE) for a, b in zip(parts, parts[1:], strict=False)]
    while joint and (top := max(joint)) > _NONE:
        i = joint.index(top)
        parts[i] += parts.pop(i + 1)
        del joint[i]
        if i < len(joint):
            joint[i] = rank(parts[i] + parts[i + 1], _NONE)
        if i:
            joint[i - 1] = rank(parts[i - 1] + parts[i], _NONE)
    return parts


class Lattice:
    """The pieces of words by a pass over their lattices: edges come from an Aho-Corasick automaton of the pieces, by their ends, the longest first."""

    def __init__(self, table: PieceTable) -> None:
        self.table = table
        automaton = ahocorasick.Automaton()
        for piece, i in table.reached.items():
            automaton.add_word(piece, (i, len(piece)))
        if len(automaton):
            automaton.make_automaton()
        self.automaton = automaton
        self.young: dict[int, bool] = {}
        self.old: dict[int, bool] = {}
        self.fold = self.neighbours if table.merges else self.sums

    def edges(self, word: str) -> Iterator[tuple[int, tuple[int, int]]]:
        """(last place, (piece, length)) of every edge."""
        return self.automaton.iter(word) if len(self.automaton) else iter(())

    def may_follow(self, pair: int) -> bool:
        """Whether merging leaves the two pieces of a pair (first << 20 | second) apart."""
        known = self.old.get(pair)
        if known is None:
            a, b = self.table.pieces[pair >> 20], self.table.pieces[pair & 0xFFFFF]
            known = merged(a + b, self.table) == [a, b]
        if len(self.young) >= KEPT_PAIRS // 2:
            self.old, self.young = self.young, {}
        self.young[pair] = known
        return known

    def neighbours(self, word: str) -> list[int]:
        """Byte-pair models: to each place the one path whose neighbours may all meet."""
        n = len(word)
        last, begin = [_OPEN] * (n + 1), [0] * (n + 1)
        last[0], closed = _BEGIN, 0
        for end, (x, size) in self.edges(word):
            j = end + 1
            if last[j] != _OPEN:
                continue
            while closed < end:  # places without a path are passed by a character without a piece
                closed += 1
                if last[closed] == _OPEN:
                    last[closed], begin[closed] = _RAW, closed - 1
            a = last[j - size]
            if a >= 0:
                pair = a << 20 | x
                ok = self.young.get(pair)
                if not (self.may_follow(pair) if ok is None else ok):
                    continue
            last[j], begin[j] = x, j - size
        for j in range(closed + 1, n + 1):
            if last[j] == _OPEN:
                last[j], begin[j] = _RAW, j - 1
        return self._path(word, last, begin)

    def sums(self, word: str, unknown: float = -1e6) -> list[int]:
        """Unigram models: to each place the path of the greatest sum; of equal ones the one whose last piece begins first."""
        n, scores = len(word), self.table.scores
        by_end: dict[int, list[tuple[int, int]]] = {}
        for end, edge in self.edges(word):
            by_end.setdefault(end + 1, []).append(edge)
        best, last, begin = [0.0] * (n + 1), [_RAW] * (n + 1), [0] * (n + 1)
        for j in range(1, n + 1):
            ways = [(best[j - size] + scores[x], size, x) for x, size in by_end.get(j, ())]
            if not any(size == 1 for _, size, _ in ways):
                ways.append((best[j - 1] + unknown, 1, _RAW))
            best[j], size, last[j] = max(ways)
            begin[j] = j - size
        return self._path(word, last, begin)

    def _path(self, word: str, last: list[int], begin: list[int]) -> list[int]:
        out, j = [], len(word)
        while j:
            i = begin[j]
            if last[j] >= 0:
                out.append(last[j])
            else:
                out += reversed(_fallback(word[i:j], self.table))
            j = i
        return out[::-1]


class Encoder:
    """Token numbers of texts as 4-byte numbers; words are kept in two generations, so memory is bounded."""

    def __init__(self, table: PieceTable) -> None:
        self.fold = Lattice(table).fold
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.plain = table.bytes_of()

    def word(self, word: str) -> bytes:
        if (x := self.young.get(word)) is None:
            x = self.old.get(word)
            if x is None:
                x = np.array(self.fold(word.replace(" ", SPACE)), "<i4").tobytes()
            if len(self.young) >= KEPT_WORDS // 2:
                self.old, self.young = self.young, {}
            self.young[word] = x
        return x

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        words = _WORDS.findall(" " + text)
        known = self.young.get
        return b"".join([known(w) or self.word(w) for w in words])

    def decode(self, ids: bytes) -> str:
        raw = b"".join(map(self.plain.__getitem__, np.frombuffer(ids, "<i4").tolist()))
        return raw[1:].decode("utf-8", "surrogatepass") if raw[:1] == b" " else raw.decode("utf-8", "surrogatepass")


def encode(docs: DataFrame, path: str = MODEL, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids, ids_sha256, exact): token numbers of every text; `exact` says that they decode to it.

    Map-only; the piece table is broadcast (its size is the model's, whatever the data). The digest is
    over the numbers as 4-byte little-endian integers.
    """
    shared = docs.sparkSession.sparkContext.broadcast(load(path))
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        own = Encoder(shared.value)
        for batch in batches:
            for part in slices(batch, 2 << 20):
                texts = part.column(1).to_pylist()
                blobs = [own.encode(t) for t in texts]
                sizes = np.array([len(b) // 4 for b in blobs], np.int64)
                flat = pa.array(np.frombuffer(b"".join(blobs), "<i4"), pa.int32())
                ids = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)), flat)
                same = [own.decode(b) == (t or "") for b, t in zip(blobs, texts, strict=True)]
                sums = [hashlib.sha256(b).hexdigest() for b in blobs]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes), ids, pa.array(sums, pa.string()), pa.array(same, pa.bool_())], names=["doc_id", "n_tokens", "ids", "ids_sha256", "exact"])

    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"doc_id {kind}, n_tokens bigint, ids array<int>, ids_sha256 string, exact boolean")


def decode(tokens: DataFrame, path: str = MODEL, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(doc_id, text) of token numbers; null numbers give a null text."""
    shared = tokens.sparkSession.sparkContext.broadcast(load(path))
    kind = tokens.schema[id_col].dataType.simpleString()

    def run(batches):
        own = Encoder(shared.value)
        for batch in batches:
            texts = [None if x is None else own.decode(np.array(x, "<i4").tobytes()) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return tokens.select(F.col(id_col), F.col(ids_col).cast("array<int>")).mapInArrow(run, f"doc_id {kind}, text string")


def piece_frame(spark: SparkSession, table: PieceTable) -> DataFrame:
    """The piece table as (piece, id, score)."""
    return spark.createDataFrame([(p, i, float(table.scores[i])) for p, i in table.reached.items()], "piece string, id int, score double")


def lattice(words: DataFrame, pieces: DataFrame, longest: int, byte_base: int, unknown: float = -1e6) -> DataFrame:
    """(word, edges): substrings of bounded length that are pieces, and byte edges for single signs that aren't."""
    n = F.char_length("word")
    spans = F.flatten(F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.transform(F.sequence(F.lit(1), F.least(F.lit(longest), n - i)), lambda size: F.struct(i.alias("begin"), (i + size).alias("end")))))
    cut = words.where(n > 0).select("word", F.explode(spans).alias("s")).select("word", "s.begin", "s.end", F.expr("substring(word, s.begin + 1, s.end - s.begin)").alias("piece"))
    joined = cut.join(F.broadcast(pieces), "piece", "left").where(F.col("id").isNotNull() | (F.col("end") - F.col("begin") == 1))
    code = F.hex(F.encode("piece", "utf-8"))
    raw = F.transform(F.sequence(F.lit(1), F.length(code), F.lit(2)), lambda k: F.conv(F.substr(code, k, F.lit(2)), 16, 10).cast("int") + byte_base)
    ids = F.when(F.col("id").isNotNull(), F.array("id")).otherwise(raw if byte_base >= 0 else F.array(F.lit(0)))
    edge = F.struct("end", "begin", F.coalesce("score", F.lit(unknown)).alias("score"), F.coalesce("id", F.lit(_RAW)).alias("id"), ids.alias("ids"))
    return joined.groupBy("word").agg(F.sort_array(F.collect_list(edge)).alias("edges"))


def _fold(edges_: Column, n: Column) -> Column:
    """Best (score, ids) at each place of a word, edge by edge in order of their ends: the greatest sum."""
    nothing = F.struct(F.lit(None).cast("double").alias("score"), F.array().cast("array<int>").alias("ids"))
    begin = F.struct(F.lit(0.0).alias("score"), F.array().cast("array<int>").alias("ids"))
    start = F.transform(F.sequence(F.lit(0), n), lambda k: F.when(k == 0, begin).otherwise(nothing))

    def step(state: Column, edge: Column) -> Column:
        came = F.get(state, edge["begin"])
        total = came["score"] + edge["score"]
        better = lambda old: old["score"].isNull() | (total > old["score"])
        return F.transform(state, lambda old, k: F.when((k == edge["end"]) & better(old), F.struct(total.alias("score"), F.concat(came["ids"], edge["ids"]).alias("ids"))).otherwise(old))

    return F.aggregate(edges_, start, step, lambda state: F.element_at(state, -1)["ids"])


def _fold_pairs(edges_: Column, apart: Column, n: Column) -> Column:
    """The one path (last piece, ids) to each place whose neighbours may all meet; `apart` has the word's pairs that may."""
    nothing = F.struct(F.lit(_OPEN).alias("last"), F.array().cast("array<int>").alias("ids"))
    begin = F.struct(F.lit(_BEGIN).alias("last"), F.array().cast("array<int>").alias("ids"))
    start = F.transform(F.sequence(F.lit(0), n), lambda k: F.when(k == 0, begin).otherwise(nothing))

    def step(state: Column, edge: Column) -> Column:
        came = F.get(state, edge["begin"])
        meets = (came["last"] < 0) | (edge["id"] < 0) | F.array_contains(apart, came["last"].cast("long") * (1 << 20) + edge["id"])
        ok = (came["last"] != _OPEN) & meets & (F.get(state, edge["end"])["last"] == _OPEN)
        return F.transform(state, lambda old, k: F.when((k == edge["end"]) & ok, F.struct(edge["id"].alias("last"), F.concat(came["ids"], edge["ids"]).alias("ids"))).otherwise(old))

    return F.aggregate(edges_, start, step, lambda state: F.element_at(state, -1)["ids"])


def encode_vocabulary(words: DataFrame, table: PieceTable, unknown: float = -1e6) -> DataFrame:
    """(word, ids) of a table of different words by Spark's own operators; for byte-pair models the distinct pairs of pieces that may meet are joined to their words."""
    found = lattice(words, piece_frame(words.sparkSession, table), table.longest, table.byte_base, unknown)
    n = F.char_length("word")
    if not table.merges:
        return found.select("word", _fold(F.col("edges"), n).alias("ids"))
    shared = words.sparkSession.sparkContext.broadcast(table)
    meeting = F.flatten(F.transform("edges", lambda a: F.transform(F.filter("edges", lambda b: (b["begin"] == a["end"]) & (a["id"] >= 0) & (b["id"] >= 0)), lambda b: a["id"].cast("long") * (1 << 20) + b["id"])))
    pairs = found.select("word", F.explode(F.array_distinct(meeting)).alias("pair"))

    def kept(batches):
        own = Lattice(shared.value)
        for batch in batches:
            yield batch.filter(pa.array([own.may_follow(p) for p in batch.column(0).to_pylist()], pa.bool_()))

    apart = pairs.join(pairs.select("pair").distinct().mapInArrow(kept, "pair bigint"), "pair").groupBy("word").agg(F.collect_list("pair").alias("apart"))
    none = F.array().cast("array<bigint>")
    return found.join(apart, "word", "left").select("word", _fold_pairs(F.col("edges"), F.coalesce("apart", none), n).alias("ids"))


def report(docs: DataFrame) -> DataFrame:
    """Token counts, digests and the round trip of every text."""
    return encode(docs).select("doc_id", "n_tokens", "ids_sha256", "exact")
