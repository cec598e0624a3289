"""Ogg media, SentencePiece encoding and web archives: round trips and plain versions."""

from __future__ import annotations

import hashlib
import random
import struct
import zlib

import numpy as np
import pytest
import sentencepiece

from collanom.llm import ogg, pieces, queries, warc

from .conftest import AWKWARD


def plain_crc(data):
    crc = 0
    for b in data:
        crc ^= b << 24
        for _ in range(8):
            crc = (crc << 1 ^ 0x04C11DB7 if crc >> 31 else crc << 1) & 0xFFFFFFFF
    return crc


def test_page_checksum():
    for data in (b"", b"a", bytes(range(256)), b"OggS" * 40):
        assert ogg.page_crc(data) == plain_crc(data)


@pytest.mark.parametrize("n", [192, 255 * 192, 254 * 255 + 192 - 254 * 255 % 192, 96_000, 96_000 * 3 + 192, 65_280, 130_560])
def test_ogg_round_trip(n):
    n += -n % 192
    payload = random.Random(n).randbytes(n)
    media = ogg.encode(payload, {"a": "b"})
    back = ogg.decode(media)
    assert back.payload == payload and back.notes == {"a": "b"} and back.rate == ogg.RATE
    assert back.times[-1] == n / ogg.RATE and back.times == sorted(back.times)
    assert set(ogg.demultiplex(media)) == {1, 2}


def test_ogg_damage_is_found():
    media = ogg.encode(b"x" * 192_000)
    for at in (0, 5, 30, 1000, len(media) - 1):
        broken = media[:at] + bytes([media[at] ^ 1]) + media[at + 1 :]
        with pytest.raises(ogg.OggError):
            ogg.decode(broken)
    with pytest.raises(ogg.OggError):
        ogg.decode(media[:-10])
    with pytest.raises(ogg.OggError):
        ogg.encode(b"")
    second = media.index(b"OggS", 4)
    assert struct.unpack_from("<I", media, second + 14)[0] == 2


def test_ogg_packets_of_one_page_have_their_own_times():
    """Two packets on a page, of which the page states the last one's granule position only."""
    head = ogg._HEAD.pack(b"PCM8HEAD", 1, ogg.RATE, 8, 300)
    text = ogg._Writer(2)

    def page(serial, number, flags, granule, packets):
        laces = b"".join(bytes([255]) * (len(p) // 255) + bytes([len(p) % 255]) for p in packets)
        raw = ogg._HEADER.pack(b"OggS", 0, flags, granule, serial, number, 0, len(laces)) + laces + b"".join(packets)
        return raw[:22] + struct.pack("<I", plain_crc(raw)) + raw[26:]

    notes = b"".join([*text.pages(b"NOTEHEAD", 0, first=True), *text.pages(b"{}", 0, last=True)])
    good = page(1, 0, ogg.FIRST, 0, [head]) + notes + page(1, 1, ogg.LAST, 300, [b"a" * 100, b"b" * 200])
    back = ogg.decode(good)
    assert back.times == [100 / ogg.RATE, 300 / ogg.RATE] and len(back.payload) == 300
    wrong = page(1, 0, ogg.FIRST, 0, [head]) + notes + page(1, 1, 0, 150, [b"a" * 100]) + page(1, 2, ogg.LAST, 300, [b"b" * 200])
    with pytest.raises(ogg.OggError):
        ogg.decode(wrong)


def test_ogg_query(spark, sf, corpus, awkward, empty):
    want = {}
    for doc, text in corpus:
        raw = (text or "").encode()
        padded = raw + b" " * (-len(raw) % 192 if raw else 192)
        want[doc] = len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-16:])
    assert {r["doc_id"]: tuple(r)[1:5] for r in queries.op5_ogg_media(spark, sf).collect()} == want
    rows = ogg.report(awkward).collect()
    assert {r["payload_bytes"] for r in rows if r["doc_id"] in (1, 2)} == {192}
    assert len({tuple(r)[1:] for r in rows if r["doc_id"] == 4}) == 1
    assert ogg.report(empty).count() == 0
    media = {r["doc_id"]: r["media"] for r in ogg.store_column(awkward).collect()}
    assert ogg.decode(bytes(media[7])).payload.rstrip(b" ").decode() == AWKWARD[-1][1]


@pytest.fixture(scope="module")
def table():
    return pieces.load()


@pytest.fixture(scope="module")
def library():
    return sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)


def test_encoding_equals_the_library(spark, sf, corpus, library):
    got = {r["doc_id"]: r for r in queries.op2_sentencepiece(spark, sf).collect()}
    for doc, text in corpus:
        ids = library.encode(text or "")
        assert (got[doc]["n_tokens"], got[doc]["ids_sha256"], got[doc]["exact"]) == (len(ids), hashlib.sha256(np.array(ids, "<i4").tobytes()).hexdigest(), True)


def test_encoding_of_odd_texts(table, library):
    own = pieces.Encoder(table)
    rng = random.Random(4)
    signs = ["a", "the", " ", "  ", "\n", "\t", "é", "中", "\U0001f389", "ing", "ation", "0", ".", "\r", "▁"]
    texts = ["".join(rng.choices(signs, k=rng.randint(0, 30))) for _ in range(1500)] + ["x" * 3000, "ab" * 2000, " " * 50]
    for t in texts:
        ids = own.encode(t)
        if pieces.SPACE not in t:
            assert np.frombuffer(ids, "<i4").tolist() == library.encode(t)
        assert own.decode(ids) == t.replace(pieces.SPACE, " ")


def small_table():
    names = ["<unk>", *(f"<0x{b:02X}>" for b in range(256)), "▁", "a", "b", "c", "ab", "bc", "abc", "▁a", "▁ab", "ca"]
    scores = [0.0] * 257 + [-3.0, -4.0, -4.5, -5.0, -6.1, -6.3, -9.7, -5.5, -8.0, -7.2]
    return pieces.PieceTable(names, scores, 1, merges=False)


def best_by_enumeration(word, table):
    best = (-1e18, None)

    def go(i, score, path):
        nonlocal best
        if i == len(word):
            best = max(best, (score, path), key=lambda x: x[0])
            return
        for j in range(i + 1, len(word) + 1):
            x = table.ids.get(word[i:j])
            if x is not None:
                go(j, score + table.scores[x], [*path, x])
            elif j == i + 1:
                go(j, score - 1e6, path + pieces._fallback(word[i:j], table))

    go(0, 0.0, [])
    return best[1]


def test_viterbi_by_enumeration_and_in_spark(spark):
    table = small_table()
    rng = random.Random(9)
    words = {"▁" * rng.randint(0, 1) + "".join(rng.choice("abcé") for _ in range(rng.randint(1, 7))) for _ in range(120)}
    viterbi = pieces.Lattice(table).sums
    for word in words:
        assert viterbi(word) == best_by_enumeration(word, table)
    frame = spark.createDataFrame([(w,) for w in words], "word string")
    got = {r["word"]: r["ids"] for r in pieces.encode_vocabulary(frame, table).collect()}
    total = lambda ids: sum(table.scores[i] if i > 256 else 0 for i in ids)
    assert got.keys() == words
    for word in words:
        assert got[word] == viterbi(word) or total(got[word]) == pytest.approx(total(viterbi(word)))


def test_lattice_of_byte_pairs_in_spark(spark, table, library, corpus):
    """The relational lattice, pair join and fold give the library's tokens, and so does the pass in a worker."""
    words = sorted({w.replace(" ", pieces.SPACE) for _, t in corpus[:150] for w in pieces._WORDS.findall(" " + (t or ""))})[::7]
    words += ["▁", "▁▁", "é\U0001f389x", "\U0001f389\U0001f389", "▁中a"]
    own = pieces.Lattice(table)
    want = {w: [i for p in pieces.merged(w, table) for i in ([table.ids[p]] if p in table.ids else pieces._fallback(p, table))] for w in words}
    assert {w: own.fold(w) for w in words} == want
    got = {r["word"]: r["ids"] for r in pieces.encode_vocabulary(spark.createDataFrame([(w,) for w in words], "word string"), table).collect()}
    assert got == want and len(words) > 500


def test_pairs_are_forgotten_and_found_again(table, monkeypatch):
    monkeypatch.setattr(pieces, "KEPT_PAIRS", 40)
    own, rng = pieces.Lattice(table), random.Random(3)
    for _ in range(300):
        word = "▁" + "".join(rng.choice("etaoinshrdlu") for _ in range(rng.randint(1, 20)))
        assert [table.pieces[i] for i in own.fold(word)] == pieces.merged(word, table)
    assert len(own.young) <= 20 and len(own.old) <= 20


def test_pieces_edges(spark, awkward, empty):
    rows = pieces.encode(awkward).collect()
    assert len(rows) == awkward.count() and all(r["exact"] for r in rows)
    assert all(r["n_tokens"] == 0 for r in rows if r["doc_id"] in (1, 2))
    back = {r["doc_id"]: r["text"] for r in pieces.decode(pieces.encode(awkward)).collect()}
    assert back[7] == AWKWARD[-1][1] and back[1] == ""
    assert pieces.encode(empty).count() == 0


def plain_archive(rows):
    first = {}
    for page, html in sorted((p, h) for p, h in rows if p is not None and len(h) >= 100):
        first.setdefault(html, page)
    return sorted(((p, len(h), hashlib.sha256(h).hexdigest(), "revisit" if first.get(h, p) != p else "response", first[h] if first.get(h, p) != p else None) for p, h in rows), key=repr)


def test_warc_query(spark, sf):
    pages = [(r["page_id"], (r["html"] or "").encode()) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    rows = queries.op8_warc(spark, sf).collect()
    assert sorted((tuple(r)[:5] for r in rows), key=repr) == plain_archive(pages)


def test_warc_revisits_order_and_edges(spark, monkeypatch):
    monkeypatch.setattr(warc, "ARCHIVE_BYTES", 2000)
    monkeypatch.setattr(warc, "RANGE_ROWS", 10)
    rng = random.Random(1)
    bodies = ["x" * 99, "y" * 100, "é" * 60, "", "<p>" + "z" * 500]
    data = [(i, f"http://www.{rng.choice('abc')}.org/{rng.randint(0, 5)}?b=2&a=1#f", rng.choice(bodies)) for i in range(120)] + [(7, "http://x.y/", "y" * 100), (500, None, None), (501, "not a url [", "q\u0000\n" * 60)]
    pages = spark.createDataFrame(data, "page_id bigint, url string, html string").repartition(5)
    rows = warc.report(pages).collect()
    assert sorted((tuple(r)[:5] for r in rows), key=repr) == plain_archive([(p, (h or "").encode()) for p, _, h in data])
    order = [(r["url_key"], r["captured"], r["page_id"]) for r in sorted(rows, key=lambda r: (r["range"], r["place"]))]
    assert order == sorted(order)
    assert len({r["range"] for r in rows}) > 3
    assert warc.report(pages.limit(0)).count() == 0


def test_warc_joins_of_many_payloads_are_salted(spark, monkeypatch):
    monkeypatch.setattr(warc, "BROADCAST_PAYLOADS", 0)
    data = [(i, f"http://a/{i}", ("x" * 200, "", "y" * 150)[i % 3]) for i in range(60)] + [(None, "http://a/", "x" * 200)]
    rows = warc.report(spark.createDataFrame(data, "page_id bigint, url string, html string")).collect()
    got = sorted((tuple(r)[:5] for r in rows), key=repr)
    want = plain_archive([(p, h.encode()) for p, _, h in data])
    assert [r for r in got if r[0] is not None] == [r for r in want if r[0] is not None] and len(got) == len(want)


def test_reading_is_linear(monkeypatch):
    monkeypatch.setattr(warc, "READ", 50)
    one = [warc.record(i, f"http://a/{i}", b"p" * i, hashlib.sha256(b"p" * i).hexdigest(), None) for i in range(300)]
    back = list(warc.records(b"".join(one)))
    assert [size for _, size, _, _ in back] == list(map(len, one)) and [len(b.partition(b"\r\n\r\n")[2]) for *_, b in back] == list(range(300))


def test_loser_tree_merges():
    rng = random.Random(3)
    for k in (0, 1, 2, 3, 7, 8):
        runs = [sorted(rng.randint(0, 50) for _ in range(rng.randint(0, 9))) for _ in range(k)]
        assert list(warc.LoserTree(runs, key=lambda x: x)) == sorted(x for r in runs for x in r)


def test_damaged_archive_is_found():
    record = warc.record(1, "http://a/", b"payload", hashlib.sha256(b"payload").hexdigest(), None)
    assert warc.index_entry("a", *next(iter(warc.records(record))))["payload_bytes"] == 7
    wrong = warc.record(1, "http://a/", b"payload", "0" * 64, None)
    with pytest.raises(ValueError, match="digest"):
        warc.index_entry("a", *next(iter(warc.records(wrong))))
    with pytest.raises((ValueError, zlib.error)):
        list(warc.records(record[:-9]))


def test_url_keys():
    assert warc.url_key("https://www.Example.com:8080/A?b=2&a=1#x") == "com,example:8080)/a?a=1&b=2"
    assert warc.url_key(None) == "" and warc.url_key("http://a.b") == "b,a)/"


def test_exact_compares_with_the_text_itself(spark):
    """A text with the sign that stands for a space decodes to a space there, and says so."""
    rows = spark.createDataFrame([(1, "one two"), (2, "one▁two")], "doc_id bigint, text string")
    assert {r["doc_id"]: r["exact"] for r in pieces.encode(rows).collect()} == {1: True, 2: False}
