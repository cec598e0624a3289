"""Format-preserving pseudonyms: validated numbers and dates are permuted within their format.

Each kind of value is a number in a finite set; a keyed Feistel network, walked until it lands in the
set again, permutes the set. The same value thus gets the same pseudonym in every document, pseudonyms
are valid values of the same format (check digits, calendar, numbering plan), and whoever has the key can
invert them. Separators stay where they were, so that the spellings of a value stay linked: dates in any
order of their parts, telephone numbers with and without separators, +1 numbers with and without the code.

Where a candidate fails its validation shorter ones that begin there are tried (a card number may be
followed by other digits), then what begins later. Days up to the 12th are permuted among themselves and
so are the others, so a date that can only be read month first gives one that can only be read so.

Defined results: null texts stay null, empty ones empty; values that fail their validation (check
digits, ranges, calendar) are left alone; where several kinds or lengths fit the first in the order of
`KINDS` and `CARD_SIZES` is taken; a date of two small numbers is read day first; repeated rows get equal
results; an empty table gives no rows; long texts are read whole; other columns are ignored, whatever
their names.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Callable
from datetime import date
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

#: Only for tests and demonstrations; give a secret key in production.
DEMO_KEY = b"collanom demonstration key"
ROUNDS = 8
KINDS = ("email", "ip", "date", "ssn", "phone", "card", "iban")
#: Digits of a card number, as they are tried where more digits follow.
CARD_SIZES = (16, 15, 14, 13, 19, 18, 17)
#: Fixed: candidates of each kind, tried in this order; validation follows.
FORMS = {
    "email": r"[A-Za-z0-9._%+-]{1,64}@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,24}",
    "ip": r"\d{1,3}(?:\.\d{1,3}){3}",
    "date": r"\d{4}-\d{2}-\d{2}|\d{2}[/.]\d{2}[/.]\d{4}",
    "ssn": r"\d{3}-\d{2}-\d{4}",
    "phone": r"\+\d{1,3}[ .-]?(?:\(\d{2,4}\)|\d{2,4})(?:[ .-]?\d{2,4}){2,4}|(?:\(\d{3}\) ?|\d{3}[ .-])\d{3}[ .-]\d{4}",
    "card": r"\d(?:[ -]?\d){12,18}",
    "iban": r"[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,4})?",
}
#: Fixed: what may not stand before and after a candidate.
_BEFORE = {k: r"(?<!\w)" for k in KINDS} | {"email": r"(?<![A-Za-z0-9._%+-])", "ip": r"(?<![\w.])"}
_AFTER = {k: r"(?!\w)" for k in KINDS} | {"email": "", "ip": r"(?!\w|\.\d)"}
PATTERN = re.compile("|".join(f"{_BEFORE[k]}(?P<{k}>{FORMS[k]}){_AFTER[k]}" for k in KINDS), re.ASCII)
_OWN = {k: (re.compile(f"{_BEFORE[k]}(?:{FORMS[k]})", re.ASCII), re.compile(_AFTER[k], re.ASCII)) for k in KINDS}
#: Signs of a value of any kind but the first, at most.
LONGEST = 50
#: Fixed: two-digit country calling codes; 1 and 7 have one digit, all others three.
_TWO = frozenset((20, 27, 30, 31, 32, 33, 34, 36, 39, 40, 41, 43, 44, 45, 46, 47, 48, 49, 51, 52, 53, 54, 55, 56, 57, 58, 60, 61, 62, 63, 64, 65, 66, 81, 82, 84, 86, 90, 91, 92, 93, 94, 95, 98))
_LOW, _HIGH = date(1900, 1, 1).toordinal(), date(2099, 12, 31).toordinal()
#: Days of the range up to the 12th of their month, and the others.
_DAYS = tuple([d for d in range(_LOW, _HIGH + 1) if (date.fromordinal(d).day <= 12) is small] for small in (True, False))


def country_code(digits: str) -> str:
    """The country calling code that an international number begins with."""
    return digits[:1] if digits[0] in "17" else digits[:2] if int(digits[:2]) in _TWO else digits[:3]


def _plan(national: str) -> bool:
    """Whether ten digits are a number of the +1 plan: neither area nor exchange begins with 0 or 1."""
    return national[0] > "1" and national[3] > "1"


class Permutation:
    """A keyed permutation of range(size): a Feistel network over enough bits, cycle-walked."""

    def __init__(self, key: bytes, kind: str, size: int) -> None:
        self.size = size
        self.half = max(1, ((size - 1).bit_length() + 1) // 2)
        self.mask = (1 << self.half) - 1
        self.secret = hashlib.blake2b(f"{kind}:{size}".encode(), key=key[:64], digest_size=32).digest()

    def _round(self, i: int, x: int) -> int:
        data = x.to_bytes((self.half + 7) // 8, "big")
        return int.from_bytes(hashlib.blake2b(data, key=self.secret, salt=bytes([i]), digest_size=min(64, self.half // 8 + 8)).digest(), "big") & self.mask

    def _once(self, x: int, order) -> int:
        a, b = x >> self.half, x & self.mask
        for i in order:
            a, b = b, a ^ self._round(i, b)
        return b << self.half | a

    def apply(self, x: int) -> int:
        while (x := self._once(x, range(ROUNDS))) >= self.size:
            pass
        return x

    def invert(self, x: int) -> int:
        while (x := self._once(x, range(ROUNDS - 1, -1, -1))) >= self.size:
            pass
        return x


def luhn_digit(body: str) -> int:
    """The check digit that makes body + digit valid."""
    total = sum(d if i % 2 else (2 * d if d < 5 else 2 * d - 9) for i, d in enumerate(map(int, reversed(body))))
    return -total % 10


def _iban_check(country: str, body: str) -> str:
    return f"{98 - int(''.join(str(int(c, 36)) for c in body + country) + '00') % 97:02d}"


def _lay(shape: str, signs: str) -> str:
    """The signs put where the shape has letters and digits."""
    it = iter(signs)
    return "".join(next(it) if c.isalnum() else c for c in shape)


class Pseudonyms:
    """Permutes values of every kind under one key."""

    def __init__(self, key: bytes = DEMO_KEY, backwards: bool = False) -> None:
        self.key, self.backwards = key, backwards
        self.of = lru_cache(maxsize=4096)(lambda kind, size: Permutation(key, kind, size))
        self.known = lru_cache(maxsize=65536)(self._value)

    def number(self, kind: str, x: int, size: int) -> int:
        p = self.of(kind, size)
        return p.invert(x) if self.backwards else p.apply(x)

    def within(self, kind: str, x: int, size: int, fits: Callable[[int], bool]) -> int:
        """The permutation walked until it is among the numbers that fit, which it thereby permutes."""
        while not fits(x := self.number(kind, x, size)):
            pass
        return x

    def mixed(self, kind: str, signs: str) -> str:
        """Letters and digits permuted as one number of mixed base; other signs stay."""
        bases = [(10, "0") if c.isdigit() else (26, "a") if c.islower() else (26, "A") for c in signs]
        x = size = 0
        size = 1
        for c, (base, zero) in zip(signs, bases, strict=True):
            x, size = x * base + ord(c) - ord(zero), size * base
        x = self.number(f"{kind}:{''.join(z for _, z in bases)}", x, size)
        out = []
        for base, zero in reversed(bases):
            x, digit = divmod(x, base)
            out.append(chr(ord(zero) + digit))
        return "".join(reversed(out))

    def value(self, kind: str, text: str) -> str | None:
        """The pseudonym, or None if the value isn't a valid one of its kind."""
        return self.known(kind, text)

    def _value(self, kind: str, text: str) -> str | None:
        digits = re.sub(r"\D", "", text)
        if kind == "email":
            local, _, host = text.partition("@")
            signs = "".join(c for c in local if c.isalnum())
            return f"{_lay(local, self.mixed('email', signs))}@{host}" if signs else None
        if kind == "ip":
            parts = [int(p) for p in text.split(".")]
            if max(parts) > 255 or any(p != str(int(p)) for p in text.split(".")):
                return None
            x = self.number("ip", int.from_bytes(bytes(parts), "big"), 1 << 32)
            return ".".join(map(str, x.to_bytes(4, "big")))
        if kind == "date":
            return self._date(text)
        if kind == "ssn":
            area, group, serial = int(digits[:3]), int(digits[3:5]), int(digits[5:])
            if area in (0, 666) or area > 899 or not group or not serial:
                return None
            areas = area - 1 - (area > 666)
            x = self.number("ssn", (areas * 99 + group - 1) * 9999 + serial - 1, 898 * 99 * 9999)
            x, serial = divmod(x, 9999)
            areas, group = divmod(x, 99)
            area = areas + 1 + (areas + 1 >= 666)
            return f"{area:03d}-{group + 1:02d}-{serial + 1:04d}"
        if kind == "phone":
            return self._phone(text, digits)
        if kind == "card":
            if not 13 <= len(digits) <= 19 or int(digits[-1]) != luhn_digit(digits[:-1]):
                return None
            body = f"{self.number('card', int(digits[:-1]), 10 ** (len(digits) - 1)):0{len(digits) - 1}d}"
            return _lay(text, body + str(luhn_digit(body)))
        signs = text.replace(" ", "")
        country, check, body = signs[:2], signs[2:4], signs[4:]
        if not 15 <= len(signs) <= 34 or check != _iban_check(country, body):
            return None
        body = self.mixed("iban", body)
        return _lay(text, country + _iban_check(country, body) + body)

    def _date(self, text: str) -> str | None:
        if text[4] == "-":
            forms = ((text[:4], text[5:7], text[8:], "%Y-%m-%d"),)
        else:
            day_first, month_first = f"%d{text[2]}%m{text[5]}%Y", f"%m{text[2]}%d{text[5]}%Y"
            forms = ((text[6:], text[3:5], text[:2], day_first), (text[6:], text[:2], text[3:5], month_first))
        for y, m, d, form in forms:
            try:
                day = date(int(y), int(m), int(d))
            except ValueError:
                continue
            if not _LOW <= day.toordinal() <= _HIGH:
                return None
            days = _DAYS[day.day > 12]
            to = days[self.number(f"date{day.day > 12:d}", bisect_left(days, day.toordinal()), len(days))]
            return date.fromordinal(to).strftime(form)
        return None

    def _phone(self, text: str, digits: str) -> str | None:
        code = country_code(digits) if text[0] == "+" else "1"
        national = digits[len(code) :] if text[0] == "+" else digits
        if not 7 <= len(national) <= 12 or text[0] != "+" and not _plan(national):
            return None
        size = 10 ** len(national)
        wide = lambda x: f"{x:0{len(national)}d}"
        if code == "1" and len(national) == 10:
            # numbers of the plan and others each among themselves, so that a number without the code is still seen
            same = _plan(national)
            x = self.within("phone1", int(national), size, lambda x: _plan(wide(x)) == same)
        else:
            x = self.number(f"phone{code}", int(national), size)
        return _lay(text, (code if text[0] == "+" else "") + wide(x))

    def _another(self, text: str, start: int) -> tuple[str, int, str] | None:
        """The first valid value (kind, end, pseudonym) that begins at `start` and ends at a word's end, by kinds, then by length."""
        ends = [i for i in range(min(start + LONGEST, len(text)), start + 6, -1) if not _word(text, i) and _word(text, i - 1)]
        for kind in KINDS:
            whole, after = _OWN[kind]
            found = [i for i in ends if whole.fullmatch(text, start, i) and after.match(text, i)]
            if kind == "card":
                found.sort(key=lambda i: CARD_SIZES.index(sum(c.isdigit() for c in text[start:i])))
            for i in found:
                if (new := self.value(kind, text[start:i])) is not None:
                    return kind, i, new
        return None

    def rewrite(self, text: str | None) -> tuple[str | None, list[tuple[str, int, int]]]:
        """The text with pseudonyms, and (kind, start, end) of every value in the text as it was."""
        if not text:
            return text, []
        out, spans, at, pos = [], [], 0, 0
        while m := PATTERN.search(text, pos):
            kind, start, end = m.lastgroup, m.start(), m.end()
            new = self.value(kind, m[0])
            if kind == "card" or new is None:
                kind, end, new = self._another(text, start) or (kind, end, None)
            if new is None:
                pos = start + 1
                continue
            out += [text[at:start], new]
            at = pos = end
            spans.append((kind, start, end))
        return ("".join([*out, text[at:]]) if spans else text), spans


def _word(text: str, i: int) -> bool:
    """Whether there is an ASCII letter, digit or low line at a place."""
    return i < len(text) and text[i].isascii() and (text[i].isalnum() or text[i] == "_")


def pseudonymise(docs: DataFrame, key: bytes = DEMO_KEY, id_col: str = "doc_id", text_col: str = "text", make: Callable[[bytes], Pseudonyms] = Pseudonyms) -> DataFrame:
    """(doc_id, n_values, one count per kind, spans, text): texts with every value replaced; map-only."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        own = make(key)
        for batch in batches:
            for part in slices(batch):
                done = [own.rewrite(t) for t in part.column(1).to_pylist()]
                counts = [pa.array([sum(k == x for x, _, _ in s) for _, s in done], pa.int64()) for k in KINDS]
                lines = [",".join(f"{k}:{a}:{b}" for k, a, b in s) for _, s in done]
                columns = [part.column(0), pa.array([len(s) for _, s in done], pa.int64()), *counts, pa.array(lines, pa.string()), pa.array([t for t, _ in done], pa.string())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_values", *(f"n_{k}" for k in KINDS), "spans", "text"])

    fields = ", ".join(f"n_{k} bigint" for k in KINDS)
    return docs.select(F.col(id_col), F.col(text_col).cast("string")).mapInArrow(run, f"doc_id {kind}, n_values bigint, {fields}, spans string, text string")
