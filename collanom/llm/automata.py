"""Byte automata: small regular expressions to nondeterministic, then minimal deterministic automata.

Syntax: literals, `\\xHH`, `\\` before a sign, classes with ranges, `(a|b)`, `?`, `*`, `+`, `{n}`, `{m,n}`,
and `(?i:...)` for ASCII letters of either case. Patterns work on UTF-8 bytes.
"""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np

Node = tuple


class _Parser:
    def __init__(self, pattern: str) -> None:
        self.s, self.at, self.fold = pattern, 0, False

    def peek(self) -> str:
        return self.s[self.at : self.at + 1]

    def take(self) -> str:
        self.at += 1
        return self.s[self.at - 1]

    def either(self) -> Node:
        branches = [self.sequence()]
        while self.peek() == "|":
            self.take()
            branches.append(self.sequence())
        return branches[0] if len(branches) == 1 else ("or", branches)

    def sequence(self) -> Node:
        parts = []
        while self.peek() not in ("", "|", ")"):
            parts.append(self.repeat(self.atom()))
        return ("seq", parts)

    def repeat(self, one: Node) -> Node:
        while (c := self.peek()) and c in "?*+{":
            self.take()
            if c == "{":
                end = self.s.index("}", self.at)
                low, _, high = self.s[self.at : end].partition(",")
                self.at = end + 1
                least, most = int(low), int(high or low)
                one = ("seq", [one] * least + [("opt", one)] * (most - least))
            else:
                one = {"?": ("opt", one), "*": ("star", one), "+": ("seq", [one, ("star", one)])}[c]
        return one

    def byte(self) -> int:
        c = self.take()
        if c != "\\":
            return ord(c)
        c = self.take()
        if c == "x":
            self.at += 2
            return int(self.s[self.at - 2 : self.at], 16)
        return ord(c)

    def cased(self, bytes_: set[int]) -> Node:
        return ("set", frozenset(bytes_ | {b ^ 32 for b in bytes_ if 65 <= b & ~32 <= 90} if self.fold else bytes_))

    def atom(self) -> Node:
        if self.peek() == "(":
            self.take()
            held = self.fold
            if self.s.startswith("?i:", self.at):
                self.at, self.fold = self.at + 3, True
            inner = self.either()
            self.fold = held
            self.take()
            return inner
        if self.peek() == "[":
            self.take()
            found: set[int] = set()
            while self.peek() != "]":
                low = self.byte()
                if self.peek() == "-" and self.s[self.at + 1] != "]":
                    self.take()
                    found.update(range(low, self.byte() + 1))
                else:
                    found.add(low)
            self.take()
            return self.cased(found)
        return self.cased({self.byte()})


def parse(pattern: str) -> Node:
    return _Parser(pattern).either()


def reverse(node: Node) -> Node:
    """The expression of the reversed words."""
    kind, inner = node
    if kind == "set":
        return node
    if kind == "seq":
        return (kind, [reverse(x) for x in reversed(inner)])
    return (kind, [reverse(x) for x in inner]) if kind == "or" else (kind, reverse(inner))


class _Nfa:
    def __init__(self) -> None:
        self.free: list[list[int]] = []
        self.on: list[tuple[frozenset[int], int] | None] = []

    def state(self) -> int:
        self.free.append([])
        self.on.append(None)
        return len(self.free) - 1

    def build(self, node: Node, begin: int) -> int:
        kind, inner = node
        if kind == "set":
            end = self.state()
            self.on[begin] = (inner, end)
            return end
        if kind == "seq":
            for x in inner:
                entry = self.state()
                self.free[begin].append(entry)
                begin = self.build(x, entry)
            return begin
        end = self.state()
        for x in inner if kind == "or" else [inner]:
            entry = self.state()
            self.free[begin].append(entry)
            out = self.build(x, entry)
            self.free[out].append(entry if kind == "star" else end)
            if kind == "star":
                self.free[out].append(end)
        if kind != "or":
            self.free[begin].append(end)
        return end

    def closure(self, states: Iterable[int]) -> frozenset[int]:
        found, stack = set(states), list(states)
        while stack:
            for t in self.free[stack.pop()]:
                if t not in found:
                    found.add(t)
                    stack.append(t)
        return frozenset(found)


@dataclass
class Dfa:
    """Transition array over byte classes; state 0 is the start. `accepts` has a bit per pattern; `dead` is -1 if there is none."""

    classes: np.ndarray
    table: np.ndarray
    accepts: np.ndarray
    dead: int

    def __post_init__(self) -> None:
        self.rows = self.table.tolist()
        self.ends = self.accepts.tolist()
        self.class_of = bytes(self.classes.tolist())

    def run(self, data: bytes, begin: int, step: int = 1, stop: int | None = None) -> tuple[int, int]:
        """From `begin`, the last place (exclusive) at which it accepts, and at how many places it does."""
        state, at, last, times = 0, begin, -1, 0
        stop = (len(data) if step > 0 else -1) if stop is None else stop
        while at != stop:
            state = self.rows[state][self.class_of[data[at]]]
            if state == self.dead:
                break
            at += step
            if self.ends[state]:
                last, times = at, times + 1
        return last, times


def compile_rules(nodes: list[Node], anywhere: bool) -> Dfa:
    """One minimal automaton for all patterns; with `anywhere` a match may begin at every byte."""
    nfa = _Nfa()
    start = nfa.state()
    final: dict[int, int] = {}
    for bit, node in enumerate(nodes):
        entry = nfa.state()
        nfa.free[start].append(entry)
        final[nfa.build(node, entry)] = 1 << bit
    # bytes that no set tells apart form a class
    sets = list(dict.fromkeys(on[0] for on in nfa.on if on))
    marks = [tuple(b in s for s in sets) for b in range(256)]
    kinds = {m: i for i, m in enumerate(dict.fromkeys(marks))}
    classes = np.array([kinds[m] for m in marks], dtype=np.uint8)
    sample = [marks.index(m) for m in kinds]
    first = nfa.closure([start])
    known, rows, order = {first: 0}, [], [first]
    for now in order:
        row = []
        for b in sample:
            to = nfa.closure([on[1] for s in now if (on := nfa.on[s]) and b in on[0]] + ([start] if anywhere else []))
            if to not in known:
                known[to] = len(order)
                order.append(to)
            row.append(known[to])
        rows.append(row)
    accepts = [0] * len(order)
    for i, states in enumerate(order):
        for s in states:
            accepts[i] |= final.get(s, 0)
    return _minimal(np.array(rows), np.array(accepts), classes, -1 if anywhere else known.get(frozenset(), -1))


def _minimal(table: np.ndarray, accepts: np.ndarray, classes: np.ndarray, dead: int) -> Dfa:
    """Partition refinement until no class of states is split."""
    group = np.unique(accepts, return_inverse=True)[1]
    while True:
        finer = np.unique(np.column_stack([group, group[table]]), axis=0, return_inverse=True)[1].reshape(-1)
        if finer.max() == group.max():
            break
        group = finer
    # number the groups in order of their first state, so that the start is 0
    _, first = np.unique(group, return_index=True)
    rank = np.empty(len(first), dtype=np.int64)
    rank[np.argsort(first)] = np.arange(len(first))
    of, heads = rank[group], np.sort(first)
    return Dfa(classes, of[table[heads]].astype(np.int32), accepts[heads].astype(np.int32), int(of[dead]) if dead >= 0 else -1)
