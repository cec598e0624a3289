"""Secret scanning: all rules in one combined deterministic automaton and one pass over the bytes.

Every rule has a trigger (the shortest text that proves a match) and a whole pattern. The triggers of
all rules are compiled together by subset construction and minimised into one transition array.
A batch of texts is scanned in lanes that advance together, one table look-up per byte and lane;
lanes begin behind bytes after which the automaton is in its start state whatever came before. At a
trigger the rule's reversed automaton finds where the match began and its whole pattern where it ends.

Matches of a kind are leftmost and do not overlap; a match that fails the rule's length is dropped but
has consumed its text. Offsets are code points, ends exclusive.

Defined results: null and empty texts have no spans; repeated rows are scanned one by one; matches of
several kinds at one place are listed in the order of the kinds; an empty table gives no rows; long texts
are scanned whole; other columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .automata import Dfa, compile_rules, parse, reverse
from .common import slices

LANES = 2048


@dataclass(frozen=True)
class Rule:
    """`least` counts bytes of the whole match, or of its last part if `tail`."""

    kind: str
    trigger: str
    whole: str
    least: int
    tail: bool = False
    base: bool = True


#: Fixed patterns of the kinds, in the order in which they are listed.
_KEY, _VALUE = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?""", "[A-Za-z0-9+/_.=-]"
RULES = (
    Rule("assign", _KEY + _VALUE, _KEY + _VALUE + "+", 6, tail=True),
    Rule("access", r"AKIA[A-Z0-9]", r"AKIA[A-Z0-9]+", 20),
    Rule("hex", r"[0-9a-f]{24}", r"[0-9a-f]+", 24),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]", r"gh[pousr]_[A-Za-z0-9]+", 40, base=False),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9]", r"xox[abprs]-[A-Za-z0-9-]+", 20, base=False),
    Rule("google", r"AIza[A-Za-z0-9_-]", r"AIza[A-Za-z0-9_-]+", 39, base=False),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{4}", r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 30, base=False),
    Rule("pem", r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----", r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----", 27, base=False),
)


@dataclass
class Scanner:
    rules: tuple[Rule, ...]

    def __post_init__(self) -> None:
        triggers = [parse(r.trigger) for r in self.rules]
        self.dfa: Dfa = compile_rules(triggers, anywhere=True)
        self.back = [compile_rules([reverse(t)], anywhere=False) for t in triggers]
        self.whole = [compile_rules([parse(r.whole)], anywhere=False) for r in self.rules]
        self.width = self.dfa.table.shape[1]
        self.flat = np.ascontiguousarray(self.dfa.table * self.width).reshape(-1)
        ends = self.dfa.accepts
        self.rising = (ends[self.dfa.table] & ~ends[:, None]).reshape(-1).astype(np.uint8 if len(self.rules) <= 8 else np.int32)
        resets = (self.dfa.table == 0).all(axis=0)
        self.resets = resets[self.dfa.classes]
        if not self.resets[10]:
            raise ValueError("a rule goes on over a line end, which parts the texts of a batch")

    def events(self, data: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Places at which a trigger is completed, in order, and the rules' bits."""
        n = len(data)
        raw = np.frombuffer(data, np.uint8)
        safe = np.flatnonzero(self.resets[raw]) + 1
        lanes = min(LANES, max(1, n // 256))
        wanted = np.arange(1, lanes) * (n // lanes)
        cuts = np.searchsorted(safe, wanted)
        begins = np.unique(np.concatenate(([0], safe[cuts[cuts < len(safe)]])))
        begins = begins[begins < n]
        sizes = np.diff(np.append(begins, n))
        order = np.argsort(-sizes, kind="stable")
        begins, sizes = begins[order], sizes[order]
        classes = self.dfa.classes[raw]
        at, state = begins.copy(), np.zeros(len(begins), dtype=np.int32)
        alive = np.searchsorted(-sizes, -np.arange(1, int(sizes[0]) + 1 if n else 1), side="right")
        places, bits = [], []
        for m in alive.tolist():
            at, state = at[:m], state[:m]
            cell = state + classes[at]
            risen = self.rising[cell]
            if risen.any():
                hit = np.flatnonzero(risen)
                places.append(at[hit])
                bits.append(risen[hit])
            state = self.flat[cell]
            at = at + 1
        if not places:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        where, what = np.concatenate(places), np.concatenate(bits)
        order = np.argsort(where, kind="stable")
        return where[order], what[order]

    def matches(self, data: bytes, events: list[tuple[int, int]], begin: int) -> Iterator[tuple[int, int, int]]:
        """(start, end, rule) of one text's spans; `begin` is where the text begins in the data."""
        consumed = [begin] * len(self.rules)
        for place, bits in events:
            for k, rule in enumerate(self.rules):
                if not bits >> k & 1 or place < consumed[k]:
                    continue
                first, times = self.back[k].run(data, place, -1, consumed[k] - 1)
                if not times:
                    continue
                start = first + 1
                end, times = self.whole[k].run(data, start)
                if not times:
                    continue
                consumed[k] = end
                if (times if rule.tail else end - start) >= rule.least:
                    yield start, end, k

    def scan(self, texts: list[str | None]) -> list[list[tuple[int, int, int]]]:
        """Spans of every text as (start, end, rule number), ordered by start and rule."""
        raws = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        data = b"\n".join(raws) + b"\n"
        ends = np.cumsum([len(r) + 1 for r in raws])
        where, what = self.events(data)
        out: list[list[tuple[int, int, int]]] = [[] for _ in texts]
        owner = np.searchsorted(ends, where, side="right")
        cuts = np.flatnonzero(np.diff(owner)) + 1
        for places, bits, owners in zip(np.split(where, cuts), np.split(what, cuts), np.split(owner, cuts), strict=True):
            if not len(places):
                continue
            i = int(owners[0])
            begin = int(ends[i]) - len(raws[i]) - 1
            spans = sorted((s - begin, e - begin, k) for s, e, k in self.matches(data, list(zip(places.tolist(), bits.tolist(), strict=True)), begin))
            if spans and not raws[i].isascii():
                points = np.concatenate(([0], np.cumsum((np.frombuffer(raws[i], np.uint8) & 0xC0) != 0x80)))
                spans = [(int(points[s]), int(points[e]), k) for s, e, k in spans]
            out[i] = sorted(spans, key=lambda x: (x[0], x[2]))
        return out


@cache
def scanner(rules: tuple[Rule, ...] = RULES) -> Scanner:
    """The compiled automata, once per worker."""
    return Scanner(rules)


def find(docs: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans): every secret as (kind, begin, end)."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        own = scanner(rules)
        arrow = None
        for batch in batches:
            for part in slices(batch):
                arrow = arrow or pa.schema([("doc_id", part.schema.field(0).type), ("spans", pa.list_(pa.struct([("kind", pa.string()), ("begin", pa.int64()), ("end", pa.int64())])))])
                spans = [[{"kind": rules[k].kind, "begin": s, "end": e} for s, e, k in x] for x in own.scan(part.column(1).to_pylist())]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(spans, arrow.field(1).type)], schema=arrow)

    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"doc_id {kind}, spans array<struct<kind:string,begin:bigint,end:bigint>>")


def report(docs: DataFrame) -> DataFrame:
    """The digest columns of `find`, made where the spans are; map-only."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    base = {k for k, r in enumerate(RULES) if r.base}

    def run(batches):
        own = scanner()
        for batch in batches:
            for part in slices(batch):
                found = own.scan(part.column(1).to_pylist())
                lines = [",".join(f"{RULES[k].kind}:{s}:{e}" for s, e, k in x) for x in found]
                sums = [hashlib.sha256(",".join(f"{RULES[k].kind}:{s}:{e}" for s, e, k in x if k in base).encode()).hexdigest() for x in found]
                counts = [pa.array([sum(k == n for _, _, k in x) for x in found], pa.int64()) for n in range(3)]
                yield pa.RecordBatch.from_arrays([part.column(0), *counts, pa.array(sums, pa.string()), pa.array(lines, pa.string())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return docs.select("doc_id", F.col("text").cast("string")).mapInArrow(run, f"doc_id {kind}, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string")
