"""Decontamination, toxicity, secrets and pseudonyms against plain versions."""

from __future__ import annotations

import collections
import datetime
import hashlib
import ipaddress
import math
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from collanom.llm import decontaminate, pii, queries, secrets, toxicity
from collanom.llm.automata import compile_rules, parse

WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def plain_matches(docs, items, window=10):
    windows = collections.defaultdict(set)
    for item, text in items:
        w = WORDS.findall(lower(text))
        k = min(window, len(w))
        for i in range(len(w) - k + 1) if w else []:
            windows[tuple(w[i : i + k])].add(item)
    out = {}
    for doc, text in docs:
        w = WORDS.findall(lower(text))
        hit, found = np.zeros(len(w), bool), set()
        for k in {len(x) for x in windows}:
            for i in range(len(w) - k + 1):
                if x := windows.get(tuple(w[i : i + k])):
                    hit[i : i + k] = True
                    found |= x
        out[doc] = len(w), int(hit.sum()), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit.any())
    return out


def test_decontamination_query(spark, sf, corpus):
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    want = plain_matches(corpus, items)
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in queries.op3_decontamination(spark, sf).collect()}
    assert got == want
    assert any(v[4] for v in want.values())


def test_decontamination_random_and_short_items(spark):
    rng = random.Random(3)
    word = lambda: rng.choice("ab cd ef Gh é1".split())
    items = [(i, " ".join(word() for _ in range(rng.choice([0, 1, 3, 4, 9])))) for i in range(6)] + [(6, None), (7, "Ab ab"), (7, "ab ab")]
    docs = [(i, " - ".join(word() for _ in range(rng.randint(0, 40)))) for i in range(60)]
    got = decontaminate.report(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string"), 4).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in got} == plain_matches(docs, items, 4)


def test_suffix_automaton_lengths():
    rng = random.Random(5)
    for _ in range(30):
        items = [[rng.randint(0, 2) for _ in range(rng.randint(1, 8))] for _ in range(3)]
        text = [rng.randint(0, 3) for _ in range(20)]
        automaton = decontaminate.SuffixAutomaton()
        for i in items:
            automaton.add(i)
        known = {tuple(x[a:b]) for x in items for a in range(len(x)) for b in range(a + 1, len(x) + 1)}
        want = [max((k for k in range(i + 2) if tuple(text[i + 1 - k : i + 1]) in known or k == 0), default=0) for i in range(len(text))]
        assert automaton.lengths(text) == want


def test_decontamination_removes_spans(spark, awkward, empty):
    items = spark.createDataFrame([(1, "a b c d e f g h i j k l")], "item_id bigint, text string")
    docs = spark.createDataFrame([(1, "Start here, x. A b c d e f g h i j k l! The end of it all, so it goes on for many more words here."), (2, "a b c d e f g h i j k l"), (3, None)], "doc_id bigint, text string")
    out = {r["doc_id"]: r["text"] for r in decontaminate.remove(docs, items).collect()}
    assert out == {1: "Start here, x. ! The end of it all, so it goes on for many more words here.", 3: None}
    assert decontaminate.remove(awkward, items).columns == awkward.columns
    assert decontaminate.remove(awkward, items).count() == awkward.count()
    assert decontaminate.report(awkward, items.limit(0)).agg(F.sum("n_hit")).first()[0] == 0
    assert decontaminate.report(empty, items).count() == 0


def test_decontamination_in_shards(spark, monkeypatch):
    """Items of several automata, passed one after another, give what one automaton gives."""
    rng = random.Random(6)
    word = lambda: rng.choice("ab cd ef gh ij kl".split())
    items = [(None if i == 3 else i % 9, " ".join(word() for _ in range(rng.choice([2, 4, 9, 20])))) for i in range(12)]
    docs = [(i, " ".join(word() for _ in range(rng.randint(0, 60))), i) for i in range(50)]
    d, t = spark.createDataFrame(docs, "doc_id bigint, text string, row bigint"), spark.createDataFrame(items, "item_id bigint, text string")
    whole = sorted(map(repr, decontaminate.report(d, t, 4).collect()))
    left = sorted(map(repr, decontaminate.remove(d, t, 4).collect()))
    monkeypatch.setattr(decontaminate, "SHARD_BYTES", 30)
    assert len(list(decontaminate._shards(t, "item_id", "text"))) >= 3
    assert sorted(map(repr, decontaminate.report(d, t, 4).collect())) == whole
    assert sorted(map(repr, decontaminate.remove(d, t, 4).collect())) == left
    named = {x for r in decontaminate.find(d, t, 4).collect() for x in r["items"]}
    assert named and "None" not in named


def test_secret_automaton_is_minimal_and_right():
    dfa = compile_rules([parse("ab+"), parse("(?i:x)[0-9]{2}")], anywhere=True)
    state, seen = 0, []
    for b in b"zabbX12ab":
        state = dfa.rows[state][dfa.class_of[b]]
        seen.append(dfa.ends[state])
    assert seen == [0, 0, 1, 1, 0, 0, 2, 0, 1]
    assert compile_rules([parse("a|a"), parse("a")], anywhere=False).table.shape[0] == 3


ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)


def plain_secrets(text):
    text = text or ""
    found = [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    found += [(m.start(), m.end(), 1) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    found += [(m.start(), m.end(), 2) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return sorted(found, key=lambda x: (x[0], x[2]))


def test_secrets_random():
    rng = random.Random(1)
    parts = ["token", "password", "passwd", "secret", "api_key", "APIKEY", "=", ":", " ", '"', "'", "abc", "AKIA", "AK", "ABCDEFGH12345678", "deadbeef", "0123456789abcdef", "é", "\n", "x", "ghp_", "a" * 20, "/+=", "Token"]
    texts = ["".join(rng.choices(parts, k=rng.randint(0, 40))) for _ in range(4000)] + [None, "", "e" * 100_000, "token=" + "v" * 50_000]
    for text, spans in zip(texts, secrets.scanner().scan(texts), strict=True):
        assert [s for s in spans if s[2] < 3] == plain_secrets(text)


def test_secrets_query(spark, sf, corpus, awkward, empty):
    kinds = ("assign", "access", "hex")
    want = {}
    for doc, text in corpus:
        spans = plain_secrets(text)
        want[doc] = (*(sum(k == n for _, _, k in spans) for n in range(3)), hashlib.sha256(",".join(f"{kinds[k]}:{s}:{e}" for s, e, k in spans).encode()).hexdigest())
    assert {r["doc_id"]: tuple(r)[1:5] for r in queries.op9_secret_scan(spark, sf).collect()} == want
    assert secrets.report(awkward).count() == awkward.count()
    assert secrets.find(empty).count() == 0


def test_permutation_is_a_bijection():
    for size in (1, 2, 10, 97, 1000):
        p = pii.Permutation(b"k", "x", size)
        image = [p.apply(i) for i in range(size)]
        assert sorted(image) == list(range(size))
        assert [p.invert(i) for i in image] == list(range(size))


def test_pseudonyms_keep_their_format():
    own, back = pii.Pseudonyms(b"key"), pii.Pseudonyms(b"key", backwards=True)
    text = "card 4111 1111 1111 1111, again 4111111111111111; 10.0.0.255; +1 (555) 010-9999; 078-05-1120; 2024-02-29 or 31/12/1999; mail joe.b7@example.org; GB82 WEST 1234 5698 7654 32. Not: 4111111111111112, 2023-02-30, 300.1.1.1, 666-12-1234"
    new, spans = own.rewrite(text)
    assert [k for k, _, _ in spans] == ["card", "card", "ip", "phone", "ssn", "date", "date", "email", "iban"]
    assert back.rewrite(new)[0] == text
    a, b = re.findall(r"\d{4} \d{4} \d{4} \d{4}|\d{16}", new)[:2]
    assert a.replace(" ", "") == b
    assert int(b[-1]) == pii.luhn_digit(b[:-1])
    assert new.endswith("Not: 4111111111111112, 2023-02-30, 300.1.1.1, 666-12-1234")
    iban = re.search(r"GB\d\d[A-Z0-9 ]+", new)[0].strip().replace(" ", "")
    assert int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1
    assert own.rewrite(None) == (None, []) and own.rewrite("") == ("", [])


def test_pseudonyms_of_shortened_and_other_spellings():
    own, back = pii.Pseudonyms(b"key"), pii.Pseudonyms(b"key", backwards=True)
    new = own.rewrite("pay 4111 1111 1111 1111 123 now")[0]
    assert re.fullmatch(r"pay (\d{4} ){4}123 now", new) and "4111 1111" not in new
    assert own.rewrite("order 123 4111 1111 1111 1111.")[1] == [("card", 10, 29)]
    digits = lambda t: re.sub(r"\D", "", own.rewrite(t)[0])
    assert digits("+44 20 7946 0958") == digits("+442079460958") == digits("+44-20-7946-0958")
    assert digits("+44 20 7946 0958").startswith("44")
    assert digits("+1 (555) 234-4567") == "1" + digits("(555) 234-4567") == "1" + digits("555-234-4567") == "1" + digits("555 234.4567")
    assert own.rewrite("155-234-4567 or 555-134-4567 or 555-23-4567x")[1] == []
    days = [own.rewrite(t)[0] for t in ("1990-12-25", "25/12/1990", "12/25/1990", "25.12.1990")]
    y, m, d = days[0].split("-")
    assert days[1:] == [f"{d}/{m}/{y}", f"{m}/{d}/{y}", f"{d}.{m}.{y}"] and int(d) > 12
    assert own.rewrite("13/25/1990 and 31/04/2001 and 00/01/2000")[1] == []
    for t in ("12/25/1990 05/04/2003 2001-01-01", "call (555) 234-4567 or +1 (555) 010-9999 or +442079460958", "4111 1111 1111 1111 123"):
        assert back.rewrite(own.rewrite(t)[0])[0] == t


class PlainScanner:
    """The same contract from one end: every start and every end, each kind by its own validation."""

    TWO = set("20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split())

    def email(self, t):
        local, at, host = t.partition("@")
        parts = host.split(".")
        ok = at and 0 < len(local) <= 64 and set(local) <= self.LOCAL and len(parts) > 1 and all(p and set(p) <= self.HOST for p in parts)
        return bool(ok) and parts[-1].isalpha() and 2 <= len(parts[-1]) <= 24 and any(c.isalnum() for c in local)

    LOCAL = set("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
    HOST = LOCAL - set("._%+")

    def ip(self, t):
        try:
            ipaddress.IPv4Address(t)
        except ValueError:
            return False
        return True

    def date(self, t):
        forms = ["%Y-%m-%d"] if t[4:5] == "-" else [f"%d{t[2:3]}%m{t[5:6]}%Y", f"%m{t[2:3]}%d{t[5:6]}%Y"] if t[2:3] in ("/", ".") and t[5:6] in ("/", ".") else []
        for form in forms if len(t) == 10 and sum(c.isdigit() for c in t) == 8 else []:
            try:
                return 1900 <= datetime.datetime.strptime(t, form).year <= 2099
            except ValueError:
                continue
        return False

    def ssn(self, t):
        return bool(re.fullmatch(r"(?!000|666|9)\d{3}-(?!00)\d\d-(?!0000)\d{4}", t, re.ASCII))

    def phone(self, t):
        digits = "".join(c for c in t if c.isdigit())
        if t[:1] != "+":
            return bool(re.fullmatch(r"(\([2-9]\d\d\) ?|[2-9]\d\d[ .-])[2-9]\d\d[ .-]\d{4}", t, re.ASCII))
        shape = re.fullmatch(r"\+\d{1,3}[ .-]?(\(\d{2,4}\)|\d{2,4})([ .-]?\d{2,4}){2,4}", t, re.ASCII)
        code = 1 if digits[:1] in ("1", "7") else 2 if digits[:2] in self.TWO else 3
        return bool(shape) and 7 <= len(digits) - code <= 12

    def card(self, t):
        digits = [int(c) for c in t if c.isdigit()]
        if not re.fullmatch(r"\d([ -]?\d){12,18}", t, re.ASCII):
            return False
        return sum(sum(divmod(2 * d, 10)) if i % 2 else d for i, d in enumerate(reversed(digits))) % 10 == 0

    def iban(self, t):
        signs = t.replace(" ", "")
        if not re.fullmatch(r"[A-Z]{2}\d\d( ?[A-Z0-9]{4}){2,7}( ?[A-Z0-9]{1,4})?", t, re.ASCII) or not 15 <= len(signs) <= 34:
            return False
        return int("".join(str(int(c, 36)) for c in signs[4:] + signs[:4])) % 97 == 1

    def spans(self, text):
        out, at, n = [], 0, len(text)
        word = [c.isascii() and (c.isalnum() or c == "_") for c in text] + [False]
        while at < n:
            found, c = None, text[at]
            email = c in self.LOCAL and (at == 0 or text[at - 1] not in self.LOCAL) and "@" in text[at : at + 66]
            other = (at == 0 or not word[at - 1]) and (c in "+(" or c in self.LOCAL and (c.isdigit() or c.isupper()))
            if not email and not other:
                at += 1
                continue
            for kind in pii.KINDS:
                if kind == "email":
                    fits = [i for i in range(min(n, at + 140), at, -1) if self.email(text[at:i])] if email else []
                else:
                    near = [i for i in range(min(n, at + 50), at + 6, -1) if not word[i] and word[i - 1]] if other and (kind != "ip" or text[at - 1 : at] != ".") else []
                    fits = [i for i in near if getattr(self, kind)(text[at:i]) and (kind != "ip" or not re.match(r"\.\d", text[i : i + 2], re.ASCII))]
                    if kind == "card":
                        fits.sort(key=lambda i: pii.CARD_SIZES.index(sum(c.isdigit() for c in text[at:i])))
                if fits:
                    found = (kind, at, fits[0])
                    break
            if found:
                out.append(found)
                at = found[2]
            else:
                at += 1
        return out


def test_pseudonyms_query_against_a_plain_scanner(spark, sf, corpus, awkward, empty):
    back, texts, plain = pii.Pseudonyms(backwards=True), dict(corpus), PlainScanner()
    rows = queries.op7_pii_pseudonyms(spark, sf).collect()
    assert len(rows) == len(corpus) and sum(r["n_values"] for r in rows) > 50
    for r in rows:
        assert r["spans"] == ",".join(f"{k}:{a}:{b}" for k, a, b in plain.spans(texts[r["doc_id"]] or ""))
        assert back.rewrite(r["text"])[0] == texts[r["doc_id"]]
        assert r["n_values"] == 0 or r["text"] != texts[r["doc_id"]]
    assert pii.pseudonymise(awkward).count() == awkward.count()
    assert pii.pseudonymise(empty).count() == 0


def test_pseudonyms_of_random_digits_against_a_plain_scanner():
    rng, own, plain = random.Random(8), pii.Pseudonyms(b"k"), PlainScanner()
    parts = ["4111 1111 1111 1111", "4111111111111111", "3782 822463 10005", "123", "12/25/1990", "25.12.1990", "2001-02-03", "+44 20 7946 0958", "+1", "555-234-4567", "(555) 234-4567", "078-05-1120", "10.0.0.1", "a.b@c.de", "GB82 WEST 1234 5698 7654 32", " ", "-", ".", "x", "\n", "12", "0000", "+", "("]
    for _ in range(3000):
        text = "".join(rng.choices(parts, k=rng.randint(1, 8)))
        assert own.rewrite(text)[1] == plain.spans(text), text


def test_folding():
    assert toxicity.fold("Ｉdіоt! 1d10t, st​upid  m0r0n*** 2024") == " idiot idiot stupid moron "
    assert toxicity.fold("5hit $hit @ss a55 b00b wow! 10 $5 3") == " shit shit ass ass boob wow "
    assert "idiot" in toxicity.fold("іdіоt") and "moron" in toxicity.fold("m0r0n") and "stupid" in toxicity.fold("st​upid")
    assert toxicity.fold(None) == "  " and toxicity.fold("  ") == "  "


def plain_score(text, lexicon):
    """Every word against every entry, every pair of words against every exception."""
    words = toxicity.fold(text).split()
    harmless = {i + d for i in range(len(words) - 1) if f"{words[i]} {words[i + 1]}" in lexicon.exceptions for d in (0, 1)}
    total = 0.0
    for i, w in enumerate(words):
        if i not in harmless:
            total += max((v for e, v in lexicon.entries.items() if (w == e.strip() if e.endswith(" ") else w.startswith(e[1:]))), default=0.0)
    a, b, c = lexicon.curve
    z = a + b * math.log1p(total) + c * total / (1 + math.log1p(max(len(words), 1)))
    return 1 / (1 + math.exp(-z))


def test_toxicity_query_against_a_plain_scorer(spark, sf, corpus):
    lexicon = toxicity.learn(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    assert lexicon.entries
    got = {r["doc_id"]: (r["score"], r["predicted"]) for r in queries.op6_toxicity(spark, sf).collect()}
    for doc, text in corpus:
        want = plain_score(text, lexicon)
        assert got[doc][0] == pytest.approx(want, abs=1e-9) and got[doc][1] == int(got[doc][0] >= 0.5)


def test_exceptions_are_learned(spark):
    rng = random.Random(4)
    filler = lambda: " ".join(rng.choice("the a house tree walk green slow river".split()) for _ in range(12))
    rows = [(i, f"{filler()} you scum {filler()}", 1) for i in range(150)] + [(1000 + i, f"{filler()} pond scum {filler()}" if i % 12 == 0 else filler(), 0) for i in range(300)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, toxic int")
    lexicon = toxicity.learn(df.select("doc_id", "text"), df.select("doc_id", "toxic"))
    assert "pond scum" in lexicon.exceptions and "you scum" not in lexicon.exceptions
    scores = {r["doc_id"]: r["score"] for r in toxicity.score(df, lexicon).collect()}
    assert min(scores[i] for i in range(150)) > 0.5 > max(scores[1000 + i] for i in range(300))


def test_exceptions_and_beginnings():
    matcher = toxicity.Lexicon({" trash ": 3.0, " scum ": 2.0, " achl": 4.0}, ("trash can",)).matcher()
    hits = lambda t: toxicity.hits(toxicity.fold(t), matcher)
    assert hits("trash can") == (0.0, 0)
    assert hits("such trash, can you") == (0.0, 0)
    assert hits("trash and scum") == (5.0, 2)
    assert hits("Achlich achlos lachl") == (8.0, 2)
    assert hits("") == (0.0, 0)


@pytest.mark.parametrize("size", ["sf0.1"])
def test_toxicity_held_out(spark, size):
    folder = f"/root/testdata/{size}"
    truth = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{folder}/labels.parquet").collect()}
    rows = [r for r in queries.op6_toxicity(spark, folder).collect() if r["held_out"] and r["doc_id"] in truth]
    hit = sum(r["predicted"] and truth[r["doc_id"]] for r in rows)
    assert hit / sum(truth[r["doc_id"]] for r in rows) > 0.85
    assert hit / max(1, sum(r["predicted"] for r in rows)) > 0.95


def test_toxicity_edges(spark, awkward, empty):
    labels = spark.createDataFrame([(1, 0), (4, 1), (4, 0), (7, None), (None, 1), (6, 5)], "doc_id bigint, toxic int")
    rows = toxicity.report(awkward, labels).collect()
    assert len(rows) == awkward.count() and all(0 <= r["score"] <= 1 for r in rows)
    assert toxicity.report(empty, labels).count() == 0
    assert toxicity.report(awkward, labels.limit(0)).count() == awkward.count()
    assert toxicity.reject(awkward, toxicity.Lexicon({}, curve=(-5.0, 0.0, 0.0))).columns == awkward.columns
