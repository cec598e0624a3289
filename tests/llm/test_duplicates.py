"""SimHash, substring and line deduplication against plain versions."""

from __future__ import annotations

import collections
import hashlib
import random
import re

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from collanom.llm import common, linededup, queries, simhash, substrings
from collanom.llm.components import connected_components


def plain_fingerprint(text, shingle=4):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    runs = [" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    hashes = [xxhash.xxh64_intdigest(r.encode(), 42) for r in runs]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(prints, bits=4):
    ids = sorted(prints)
    root = list(range(len(ids)))

    def top(v):
        while root[v] != v:
            root[v] = root[root[v]]
            v = root[v]
        return v

    values = np.array([prints[i] for i in ids], dtype=np.uint64)
    for i in range(len(ids)):
        for j in np.flatnonzero(np.bitwise_count(values[i + 1 :] ^ values[i]) <= bits) + i + 1:
            a, b = top(i), top(int(j))
            if a != b:
                root[max(a, b)] = min(a, b)
    return {i: ids[top(k)] for k, i in enumerate(ids)}


def test_fingerprint():
    for text in (None, "", " ", "A", "a b c", "A b C d", "a b c d e f g", "ÄB é  x y z a a a a a"):
        assert simhash.fingerprint(text) == plain_fingerprint(text)


def test_simhash_query(spark, sf, corpus):
    prints = {d: plain_fingerprint(t) for d, t in corpus[:250]}
    got = {r["doc_id"]: r for r in queries.op4_simhash(spark, sf).collect()}
    assert all(got[d]["fingerprint"] == f"{x:016x}" for d, x in prints.items())
    every = {d: int(r["fingerprint"], 16) for d, r in got.items()}
    assert {d: r["component_id"] for d, r in got.items()} == plain_components(every)


@pytest.mark.parametrize(("bits", "hot"), [(4, 10_000), (4, 3), (1, 10_000), (6, 5)])
def test_no_link_is_missed(spark, bits, hot):
    rng = random.Random(bits)
    prints = set()
    for _ in range(25):
        base = rng.getrandbits(64)
        prints.add(base)
        for _ in range(12):
            x = base
            for b in rng.sample(range(64), rng.randint(0, bits + 1)):
                x ^= 1 << b
            prints.add(x)
    signed = [(0, x - (1 << 64) if x >> 63 else x) for x in prints]
    edges = simhash.links(spark.createDataFrame(signed, "seed int, fp bigint"), bits, hot_key=hot)
    roots = {r["node"]: r["root"] for r in connected_components(edges.select("a", "b")).collect()}
    order = sorted(prints)
    want = plain_components({x: x for x in order}, bits)
    sign = lambda x: x - (1 << 64) if x >> 63 else x
    groups, got = collections.defaultdict(set), collections.defaultdict(set)
    for x in order:
        groups[want[x]].add(x)
        got[roots.get(sign(x), sign(x))].add(x)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, got.values()))


def test_variants_are_never_broadcast(spark):
    """A table well below the broadcast threshold whose variants, 64 rows each, are not."""
    limit = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(limit)
    spark.conf.set(limit, "10m")
    try:
        distinct = common.stored(spark.range(20_000).select(F.lit(0).alias("seed"), F.xxhash64("id").alias("fp")))
        found = simhash.links(distinct)
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "Broadcast" not in plan
        found.collect()
        assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()  # nor once sizes are known
    finally:
        spark.conf.set(limit, before)


def test_components_of_a_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(100)] + [(200, 201), (7, 7)], "a bigint, b bigint")
    roots = {r["node"]: r["root"] for r in connected_components(edges).collect()}
    assert all(roots[i] == 0 for i in range(101)) and roots[201] == 200
    assert connected_components(edges.limit(0)).count() == 0


def test_simhash_edges(spark, awkward, empty):
    rows = simhash.report(awkward).collect()
    assert len(rows) == awkward.count()
    of = collections.defaultdict(set)
    for r in rows:
        of[r["fingerprint"]].add(r["component_id"])
    assert of["0" * 16] == {1}
    assert simhash.report(empty).count() == 0
    kept = simhash.keep_one(awkward)
    assert kept.columns == awkward.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert ids.count(4) == 1 and ids.count(1) == 1 and 2 not in ids and None in ids


def test_near_copies_collapse(spark):
    rng = random.Random(2)
    base = [" ".join(rng.choice("abcdefghijklmnop") * 3 + str(rng.randint(0, 400)) for _ in range(300)) for _ in range(30)]
    rows = []
    for i, text in enumerate(base):
        words = text.split()
        rows.append((100 * i, text))
        for k in range(1, 4):
            copy = list(words)
            for at in rng.sample(range(300), 4):
                copy[at] = f"new{rng.randint(0, 10_000)}"
            rows.append((100 * i + k, " ".join(copy)))
    kept = {r["doc_id"] for r in simhash.keep_one(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert {100 * i for i in range(30)} <= kept
    assert len(kept) <= 33


def _flipped(x, *bits):
    for b in bits:
        x ^= 1 << b
    return x


def _linked(spark, prints, total=61, hot=simhash.HOT_PLACE):
    """Root of each node of {node: five unsigned fingerprints} in the near-duplicate search."""
    sign = lambda x: x - (1 << 64) if x >> 63 else x
    nodes = spark.createDataFrame([(n, [sign(x) for x in fps]) for n, fps in prints.items()], "node bigint, fps array<bigint>")
    found = {r["node"]: r["root"] for r in connected_components(simhash._node_links(nodes, 5, 10, total, hot)).collect()}
    return {n: found.get(n, n) for n in prints}


@pytest.mark.parametrize("strangers", [20, 200])
def test_middle_groups_of_a_bucket_are_compared(spark, strangers):
    """Two near copies share buckets of one segment only, with strangers of lesser and greater labels in each."""
    rng = random.Random(5)
    low = 1 << 21
    one = [rng.getrandbits(64) for _ in range(5)]
    two = [_flipped(one[0], 22, 24, 26, 44, 46, 48)] + [_flipped(x, 1, 3, 22, 24, 44, 46, 48) for x in one[1:]]
    prints = {10_000: one, 10_001: two}
    for i in range(strangers):
        prints[i if i % 2 else 20_000 + i] = [one[0] % low | rng.getrandbits(43) << 21] + [rng.getrandbits(64) for _ in range(4)]
    for hot in (simhash.HOT_PLACE, 5):
        roots = _linked(spark, prints, hot=hot)
        assert roots[10_000] == roots[10_001]
        assert all(roots[n] == n for n in prints if n != 10_001)


def test_a_close_pair_hides_no_other_pair(spark):
    """The pair that is closest in one seed fails over all bits; another pair of the same nodes passes."""
    rng = random.Random(6)
    a1 = [rng.getrandbits(64) for _ in range(5)]
    b1 = [_flipped(a1[0], 22, 24, 26, 28, 30)] + [rng.getrandbits(64) for _ in range(4)]
    a2 = [_flipped(a1[0], 44, 46, 48, 50)] + [_flipped(x, 1, 3, 22, 24, 26, 44, 46, 48) for x in b1[1:]]
    roots = _linked(spark, {1: a1, 2: a2, 3: b1})
    assert roots == {1: 1, 2: 2, 3: 2}
    assert _linked(spark, {1: a1, 3: b1}) == {1: 1, 3: 3}


def test_every_shared_variant_is_compared(spark):
    """Random near fingerprints against brute force over all pairs that share a variant of any seed."""
    rng = random.Random(12)
    prints = {}
    for base in range(40):
        fps = [rng.getrandbits(64) for _ in range(5)]
        for i in range(6):
            prints[base * 10 + i] = [_flipped(x, *rng.sample(range(64), rng.randint(2, 9))) for x in fps]
    cut = simhash.segments(3)

    def linked(x, y):
        d = [a ^ b for a, b in zip(x, y, strict=True)]
        shares = any(v.bit_count() <= 10 and any((v >> f & (1 << w) - 1).bit_count() <= 1 for f, w in cut) for v in d)
        return shares and sum(v.bit_count() for v in d) <= 61

    names = sorted(prints)
    root = {n: n for n in names}
    for i in names:
        for j in names:
            if i < j and root[i] != root[j] and linked(prints[i], prints[j]):
                low, high = sorted((root[i], root[j]))
                root = {n: low if r == high else r for n, r in root.items()}
    assert len(set(root.values())) > 40
    for hot in (simhash.HOT_PLACE, 3):
        assert _linked(spark, prints, hot=hot) == root


@pytest.mark.parametrize("size", ["sf0.1"])
def test_near_duplicates_against_brute_force(spark, size):
    """Of all pairs of sf0.1 at a Jaccard index of 0.8 or more, nine in ten end in one group, at every level; clean texts stay apart."""
    docs = spark.read.parquet(f"/root/testdata/{size}/documents.parquet").select("doc_id", "text")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    shingles = {}
    for i, t in texts.items():
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        shingles[i] = frozenset(xxhash.xxh64_intdigest(" ".join(words[k : k + 5])) for k in range(max(1, len(words) - 4)))
    holders = collections.defaultdict(list)
    for i, s in shingles.items():
        for x in s:
            holders[x].append(i)
    # a pair at 0.8 shares one of the rarest fifth (and one more) of either's shingles
    near = {}
    for i, s in shingles.items():
        for x in sorted(s, key=lambda x: (len(holders[x]), x))[: len(s) - -(-4 * len(s) // 5) + 1]:
            for j in holders[x]:
                if j < i and (j, i) not in near:
                    near[j, i] = len(s & shingles[j]) / len(s | shingles[j])
    group = {r["doc_id"]: r["component_id"] for r in simhash.components(docs, 5, 16, 6, 0.8).collect()}
    for low, high in ((0.8, 0.85), (0.85, 0.9), (0.9, 1.0), (1.0, 1.1)):
        level = [p for p, v in near.items() if low <= v < high]
        found = sum(group[a] == group[b] for a, b in level)
        print(low, len(level), found / max(1, len(level)))
        assert found >= 0.9 * len(level)
    members = collections.defaultdict(list)
    for i, g in group.items():
        members[g].append(i)
    for rows in members.values():
        if 1 < len(rows) <= 60:
            for i in rows:
                assert max(len(shingles[i] & shingles[j]) / len(shingles[i] | shingles[j]) for j in rows if j != i) >= 0.5


def test_rows_are_kept_by_component_and_not_by_id(spark):
    rng = random.Random(9)
    texts = [" ".join(f"word{rng.randint(0, 5000)}" for _ in range(120)) for _ in range(5)]
    rows = [(None, texts[0]), (None, texts[1]), (7, texts[2]), (7, texts[3]), (7, texts[3]), (8, texts[4]), (None, texts[4])]
    kept = simhash.keep_one(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert collections.Counter(map(tuple, kept)) == collections.Counter([(None, texts[0]), (None, texts[1]), (7, texts[2]), (7, texts[3]), (8, texts[4])])


def plain_substrings(docs, window=35):
    words = [(d, re.findall(r"[^\x20\x09-\x0D]+", t or "")) for d, t in docs]
    count = collections.Counter(tuple(w[i : i + window]) for _, w in words for i in range(len(w) - window + 1))
    out = []
    for d, w in words:
        gone = np.zeros(len(w), bool)
        for i in range(len(w) - window + 1):
            if count[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = True
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out.append((d, len(w), int(gone.sum()), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=repr)


def test_substring_query(spark, sf, corpus):
    got = sorted((tuple(r[c] for c in ("doc_id", "n_words", "n_removed", "kept_sha256")) for r in queries.op10_substring_dedup(spark, sf).collect()), key=repr)
    assert got == plain_substrings(corpus)
    assert sum(r[2] for r in got) > 1000


def test_substring_windows_random(spark, monkeypatch):
    monkeypatch.setattr(substrings, "BLOCK_BYTES", 2000)
    monkeypatch.setattr(substrings, "BUCKET_BYTES", 1500)
    rng = random.Random(7)
    docs = [(i, " ".join(rng.choice("ab") for _ in range(rng.randint(0, 60)))) for i in range(80)] + [(5, None), (6, ""), (7, "a  b\tc\n" * 9)]
    df = spark.createDataFrame(docs, "doc_id bigint, text string")
    got = sorted(((r["doc_id"], r["n_words"], r["n_removed"], hashlib.sha256(r["kept"].encode()).hexdigest()) for r in substrings.deduplicate(df, 6).collect()), key=repr)
    assert got == plain_substrings(docs, 6)


def test_substring_edges(awkward, empty):
    rows = substrings.report(awkward).collect()
    assert len(rows) == awkward.count()
    assert next(r for r in rows if r["doc_id"] == 6)["n_removed"] == 60_000
    assert substrings.report(empty).count() == 0


def test_line_query_equals_sql(spark, sf):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    want = sorted(con.sql(queries.oracle_sql()["op1_line_dedup"]).fetchall())
    got = sorted(tuple(r[c] for c in ("doc_id", "n_lines", "n_dropped", "kept_sha256")) for r in queries.op1_line_dedup(spark, sf).collect())
    assert got == want and sum(r[2] for r in got) > 20


@pytest.mark.parametrize("bound", [linededup.BROADCAST_BYTES, 0])
def test_line_dedup_drops_boilerplate(spark, monkeypatch, bound):
    monkeypatch.setattr(linededup, "BROADCAST_BYTES", bound)
    rows = [(i, f"Home | About\nown line {i}\n\nend {i}", "h1") for i in range(40)] + [(100 + i, f"own {i}\nHome | About" if i < 1 else f"own {i}", "h2") for i in range(40)] + [(200, "Home | About", None), (201, None, None)]
    out = {r["doc_id"]: r["text"] for r in linededup.deduplicate(spark.createDataFrame(rows, "doc_id bigint, text string, source string")).collect()}
    assert all(out[i] == f"own line {i}\n\nend {i}" for i in range(40))
    assert out[100] == "own 0\nHome | About" and out[200] == "Home | About" and out[201] is None


def test_line_edges(awkward, empty):
    assert linededup.report(awkward).count() == awkward.count()
    out = linededup.deduplicate(awkward)
    assert out.columns == awkward.columns
    assert sorted(map(repr, (tuple(r) for r in out.collect()))) == sorted(map(repr, (tuple(r) for r in awkward.collect())))
    assert linededup.report(empty).count() == 0


def test_line_plan_is_native(spark, sf):
    plan = queries.op1_line_dedup(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_similarity_bits():
    assert simhash.allowed_bits(1.0, 384) == 0
    assert simhash.allowed_bits(0.8, 384, 0) == 58


def test_a_group_keeps_links_by_its_members(spark, monkeypatch):
    """All pairs of near fingerprints link, but the contraction gets a forest a task; and few keys are hot."""
    words = [f"w{i}" for i in range(400)]
    docs = spark.createDataFrame([(i, " ".join([*words, f"tail{i}"])) for i in range(120)], "doc_id bigint, text string")
    prints = {i: plain_fingerprint(" ".join([*words, f"tail{i}"])) for i in range(120)}
    distinct = len(set(prints.values()))
    counted = []
    monkeypatch.setattr(simhash, "connected_components", lambda edges: counted.append((edges.count(), edges.rdd.getNumPartitions())) or connected_components(edges))
    got = {r["doc_id"]: r["component_id"] for r in simhash.components(docs).collect()}
    assert got == plain_components(prints)
    nodes = spark.createDataFrame([(0, x - (1 << 64) if x >> 63 else x) for x in set(prints.values())], "seed int, fp bigint")
    pairs = simhash.links(nodes)
    assert pairs.count() > counted[0][0] and counted[0][0] <= 8 * (distinct - 1)
    assert simhash._forests(pairs.coalesce(1)).count() == distinct - len({c for c in plain_components(prints).values()})
    assert common.hot_limit(1000) == 200 and common.hot_limit(5_000_000) == 10_000 and common.hot_limit(10**10) == 100_000
