"""Toxicity by a weighted lexicon, matched with Aho-Corasick after folding look-alikes.

Texts are lower-cased; look-alike letters of other scripts become Latin ones, digits and signs that stand
for letters in a word become those letters, and everything that is not a letter parts words. The lexicon
holds whole words and word beginnings whose documents are toxic far more often than chance explains
(a likelihood-ratio test). A word counts once, with the heaviest entry that matches it; words inside an
exception phrase don't count. Exceptions are learned too: two-word phrases with a lexicon word whose
documents are no more often toxic than others. The sum, and the sum over the logarithm of the length, go
through a logistic curve.

The lexicon is learned from at most `SAMPLE` labelled rows of each class, those with the smallest hash
of the id; rows whose key falls in the held-out fold are never used. Every document is scored.

Defined results: null and empty texts score as a text without hits; repeated label rows count once (the
higher label); labels other than 0 and 1, and null ones, are not used; without usable labels of both
classes every score is the share of toxic labels (0 if there are none); of entries with equal ratios the
first in order of letters; an empty table gives no rows; long texts are scored whole; other columns are
ignored by `score` and carried unchanged by `reject`, whatever their names.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import per_row, slices, stored

#: Labelled rows of each class from which the lexicon is learned, at most.
SAMPLE = {1: 6000, 0: 9000}
ENTRIES = 20_000
FOLDS = 5
#: Least likelihood ratio (twice the log) and least log odds of an entry.
LEAST_RATIO, LEAST_ODDS = 30.0, 2.0
#: Letters of a word beginning, from and to.
PREFIX = (4, 9)
#: Harmless documents that an exception phrase needs, and exceptions at most.
LEAST_HARMLESS, EXCEPTIONS = 3, 5_000
#: Letters of other scripts that look like Latin ones, and what digits and signs stand for.
HOMOGLYPHS = str.maketrans("аеорсухіјѕԁһӏкмтвнοαιρυνετκηχωσɑɡıｌ", "aeopcyxijsdhlkmtbhoaipuvetknxwsagil")
DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i"}
#: Digits and signs inside a word, and such ones (but no exclamation mark) at its beginning or end.
_AS_LETTERS = re.compile(r"(?<=[^\W\d_])[0134578@$!]+(?=[^\W\d_])|(?<![^\W_])[0134578@$]+(?=[^\W\d_])|(?<=[^\W\d_])[0134578@$]+(?![^\W_])")
_LETTERS = str.maketrans(DIGITS)
_APART = re.compile(r"[\W\d_]+")
_FOREIGN = re.compile("[ɡɑıͰ-ԯａ-ｚ​-‏­]")
_HIDDEN = re.compile("[​-‏­]")


def fold(text: str | None) -> str:
    """Lower-case words parted by single spaces, with a space at either end."""
    t = (text or "").lower()
    if _FOREIGN.search(t):
        t = "".join(chr(ord(c) - 0xFEE0) if "ａ" <= c <= "ｚ" else c for c in _HIDDEN.sub("", t)).translate(HOMOGLYPHS)
    t = _AS_LETTERS.sub(lambda m: m[0].translate(_LETTERS), t)
    return f" {_APART.sub(' ', t).strip()} "


@dataclass(frozen=True)
class Lexicon:
    """Entries begin with a space; those that also end with one are whole words, others are beginnings."""

    entries: dict[str, float]
    exceptions: tuple[str, ...] = ()
    curve: tuple[float, float, float] = (0.0, 0.0, 0.0)

    def matcher(self):
        found = ahocorasick.Automaton()
        for entry, weight in self.entries.items():
            found.add_word(entry, (len(entry), weight))
        for phrase in self.exceptions:
            found.add_word(f" {phrase} ", (len(phrase) + 2, None))
        if len(found):
            found.make_automaton()
        return found


def hits(folded: str, matcher) -> tuple[float, int]:
    """Sum of the weights of hit words, and their number."""
    if not len(matcher):
        return 0.0, 0
    best: dict[int, float] = {}
    harmless: list[tuple[int, int]] = []
    for end, (size, weight) in matcher.iter(folded):
        start = end - size + 1
        if weight is None:
            harmless.append((start, end))
        elif weight > best.get(start, 0.0):
            best[start] = weight
    for at, end in harmless:
        while 0 <= at < end:
            best.pop(at, None)
            at = folded.find(" ", at + 1)
    return sum(best.values()), len(best)


def measures(text: str | None, matcher) -> tuple[float, float]:
    folded = fold(text)
    total, _ = hits(folded, matcher)
    return math.log1p(total), total / (1.0 + math.log1p(folded.count(" ") - 1))


def probability(x: tuple[float, float], curve: tuple[float, float, float]) -> float:
    z = curve[0] + curve[1] * x[0] + curve[2] * x[1]
    return 1 / (1 + math.exp(-max(-500.0, min(500.0, z))))


def held_out(doc_id: Column) -> Column:
    """Rows that are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % FOLDS == 0, F.lit(True))


def _features(text: str | None) -> set[str]:
    words = set(fold(text).split())
    low, high = PREFIX
    return {f" {w} " for w in words} | {f" {w[:n]}" for w in words for n in range(low, min(high, len(w)) + 1)}


def _group(text: str | None) -> int:
    """The least hash of a text's five-word runs: near copies mostly share it, and count once."""
    words = (text or "").split()
    return min((xxhash.xxh64_intdigest(" ".join(words[i : i + 5])) for i in range(max(1, len(words) - 4))), default=0) >> 1


def training_rows(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str) -> DataFrame:
    """(y, text, same) of the bounded sample; of texts with the same least hash one is kept."""
    usable = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    known = usable.groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).cast("int").alias("y"))
    picked = [known.where(F.col("y") == y).orderBy(F.xxhash64("id"), "id").limit(n) for y, n in SAMPLE.items()]
    sample = F.broadcast(stored(picked[0].unionByName(picked[1])))  # at most the sum of SAMPLE rows of two numbers
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(sample, "id")

    def grouped(batches):
        for batch in batches:
            for part in slices(batch):
                same = [_group(t) for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(same, pa.int64())], names=["y", "text", "same"])

    return rows.select("y", "text").mapInArrow(grouped, "y int, text string, same bigint").groupBy("same", "y").agg(F.max("text").alias("text"))


def learn(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", id_col: str = "doc_id", text_col: str = "text") -> Lexicon:
    """The lexicon and its curve; entries and sample are bounded, so both fit on the driver."""
    rows = stored(training_rows(docs, labels, id_col, text_col, label_col))
    size = {r["y"]: r["n"] for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    pos, neg = size.get(1, 0), size.get(0, 0)
    if not pos or not neg:
        share = pos / (pos + neg) if pos else 0.0
        return Lexicon({}, curve=(500.0 if share == 1 else -500.0, 0.0, 0.0))

    def counted(batches):
        for batch in batches:
            for part in slices(batch, 1 << 20):
                counts = Counter(), Counter()
                for y, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    counts[y].update(_features(text))
                keys = list(counts[0].keys() | counts[1].keys())
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([counts[1][k] for k in keys], pa.int64()), pa.array([counts[0][k] for k in keys], pa.int64())], names=["entry", "p", "n"])

    totals = rows.select("y", "text").mapInArrow(counted, "entry string, p bigint, n bigint").groupBy("entry").agg(F.sum("p").alias("p"), F.sum("n").alias("n"))
    share = pos / (pos + neg)
    both = F.col("p") + F.col("n")
    ratio = 2 * (F.col("p") * F.log(F.col("p") / (both * share)) + F.when(F.col("n") > 0, F.col("n") * F.log(F.col("n") / (both * (1 - share)))).otherwise(0.0))
    odds = F.log((F.col("p") + 0.5) / (pos + 1)) - F.log((F.col("n") + 0.5) / (neg + 1))
    chosen = totals.where("p > 0").withColumn("ratio", ratio).withColumn("odds", odds).where((F.col("ratio") >= LEAST_RATIO) & (F.col("odds") >= LEAST_ODDS))
    found = {r["entry"]: (r["p"], r["odds"]) for r in chosen.orderBy(F.desc("ratio"), "entry").limit(ENTRIES).collect()}
    entries = _telling(found)
    exceptions = _exceptions(rows, Lexicon(entries), pos, neg)
    lexicon = Lexicon(entries, exceptions)

    def measured(batches):
        matcher = lexicon.matcher()
        for batch in batches:
            for part in slices(batch):
                found = [measures(t, matcher) for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array([m[k] for m in found], pa.float64()) for k in (0, 1))], names=["y", "a", "b"])

    sample = rows.select("y", "text").mapInArrow(measured, "y int, a double, b double").toPandas().sort_values(["y", "a", "b"])
    return Lexicon(entries, exceptions, _curve(sample[["a", "b"]].to_numpy(), sample["y"].to_numpy()))


def phrases(folded: str, matcher) -> set[str]:
    """Two-word phrases with a word that the lexicon hits."""
    if not len(matcher):
        return set()
    starts = {end - size + 1 for end, (size, _) in matcher.iter(folded)}
    out = set()
    for at in starts:
        left = folded.rfind(" ", 0, at)
        right = folded.find(" ", at + 1)
        beyond = folded.find(" ", right + 1)
        if left >= 0:
            out.add(folded[left + 1 : right])
        if beyond >= 0:
            out.add(folded[at + 1 : beyond])
    return out


def _exceptions(rows: DataFrame, lexicon: Lexicon, pos: int, neg: int) -> tuple[str, ...]:
    """Phrases that are harmless: in `LEAST_HARMLESS` documents labelled so, and in toxic ones no more often than chance has it."""

    def counted(batches):
        matcher = lexicon.matcher()
        for batch in batches:
            for part in slices(batch, 1 << 20):
                counts = Counter(), Counter()
                for y, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    counts[y].update(phrases(fold(text), matcher))
                every = list(counts[0].keys() | counts[1].keys())
                yield pa.RecordBatch.from_arrays([pa.array(every, pa.string()), pa.array([counts[1][k] for k in every], pa.int64()), pa.array([counts[0][k] for k in every], pa.int64())], names=["phrase", "p", "n"])

    totals = rows.select("y", "text").mapInArrow(counted, "phrase string, p bigint, n bigint").groupBy("phrase").agg(F.sum("p").alias("p"), F.sum("n").alias("n"))
    rare = (F.col("p") + 0.5) / (pos + 1) <= (F.col("n") + 0.5) / (neg + 1)
    chosen = totals.where((F.col("n") >= LEAST_HARMLESS) & rare).orderBy(F.desc("n"), "phrase").limit(EXCEPTIONS)
    return tuple(sorted(r["phrase"] for r in chosen.select("phrase").collect()))


def _telling(found: dict[str, tuple[int, float]], share: float = 0.9) -> dict[str, float]:
    """Without beginnings whose toxic documents a longer entry explains: "tras" where "trash" is all there is to it."""
    longer: dict[str, int] = {}
    for entry, (docs, _) in found.items():
        for n in range(PREFIX[0] + 1, len(entry)):
            longer[entry[:n]] = max(longer.get(entry[:n], 0), docs)
    return {e: odds for e, (docs, odds) in found.items() if longer.get(e, 0) < share * docs}


def _curve(x: np.ndarray, y: np.ndarray, penalty: float = 0.05) -> tuple[float, float, float]:
    """Ridge-penalised logistic regression by Newton steps."""
    z = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(3)
    ridge = np.diag([1e-6, penalty, penalty])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge, z.T @ (y - p) - ridge @ w)
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    return tuple(float(v) for v in w)


def score(docs: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) of every document; map-only."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)
    kind = docs.schema[id_col].dataType.simpleString()

    def make():
        own = shared.value
        matcher = own.matcher()
        return lambda i, t: (i, probability(measures(t, matcher), own.curve))

    return per_row(docs, make, f"doc_id {kind}, score double", id_col, text_col)


def report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Scores of all documents, with the fold and the decision."""
    scored = score(docs, learn(docs, labels))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def reject(docs: DataFrame, lexicon: Lexicon, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """The documents that score below the threshold, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)
    at = docs.columns.index(text_col)

    def run(batches):
        own = shared.value
        matcher = own.matcher()
        for batch in batches:
            for part in slices(batch, text=at):
                yield part.filter(pa.array([probability(measures(t, matcher), own.curve) < threshold for t in part.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
