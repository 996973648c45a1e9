import hashlib
import itertools
import random

import pytest
import xxhash

from claimloom.llm import exact_dedup, simhash
from claimloom.llm.components import connected

from . import edge_cases


def test_chunks_cover_text_and_resynchronise():
    r = random.Random(1)
    text = bytes(r.randrange(97, 123) for _ in range(60_000))
    ends = exact_dedup.cut_points(text)
    assert ends[-1] == len(text) and ends == sorted(set(ends)) and max(b - a for a, b in zip([0, *ends], ends)) <= exact_dedup.MOST
    moved = exact_dedup.cut_points(b"some prefix " + text)
    assert len({e + 12 for e in ends} & set(moved)) > len(ends) / 2


def test_exact_duplicates(spark):
    got = {r.doc_id: r for r in exact_dedup.exact_duplicates(edge_cases.frame(spark)).collect()}
    texts = {i: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "") for i, t, *_ in edge_cases.rows()}
    assert set(got) == set(texts)
    for i, t in texts.items():
        same = [k for k, v in texts.items() if v == t]
        assert (got[i].keep_id, got[i].group_size, got[i].kept, got[i].text_sha256) == (max(same), len(same), i == max(same), hashlib.sha256(t.encode()).hexdigest())
    assert exact_dedup.exact_duplicates(edge_cases.empty(spark)).count() == 0
    twice = spark.createDataFrame([(1, "a"), (1, "a"), (None, "a")], "doc_id bigint, text string")
    rows = exact_dedup.exact_duplicates(twice).collect()
    assert [r.kept for r in rows].count(True) == 1 and {r.group_size for r in rows} == {3} and {r.keep_id for r in rows} == {1}


def test_connected_components(spark):
    r = random.Random(3)
    edges = [(i, i + 1) for i in range(40)] + [(r.randrange(100, 140), r.randrange(100, 140)) for _ in range(30)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a != b:
            a, b = sorted((find(a), find(b)))
            parent[b] = a
    got = {r.node: r.root for r in connected(spark.createDataFrame(edges, "a bigint, b bigint"), "a", "b").collect()}
    assert got == {x: find(x) for x in list(parent)}
    assert connected(spark.createDataFrame([], "a bigint, b bigint"), "a", "b").count() == 0


def plain_fingerprint(text, width=3):
    words = text.encode().lower().split()
    if not words:
        return 0
    pieces = [b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1))]
    hs = [xxhash.xxh64_intdigest(p, 42) for p in pieces]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute(fps):
    """Component of each id by comparing all pairs."""
    ids = list(fps)
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(ids, 2):
        if bin(fps[a] ^ fps[b]).count("1") <= 2:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    return {i: find(i) for i in ids}


def test_simhash_documents(spark):
    rows = edge_cases.rows()
    got = {r.doc_id: r for r in simhash.near_duplicates(edge_cases.frame(spark)).collect()}
    fps = {i: plain_fingerprint(t or "") for i, t, *_ in rows}
    want = brute(fps)
    assert {i: (r.fingerprint, r.component_id) for i, r in got.items()} == {i: (f"{fps[i]:016x}", want[i]) for i in fps}
    assert simhash.near_duplicates(edge_cases.empty(spark)).count() == 0


def test_simhash_links_hot_and_cool(spark):
    r = random.Random(5)
    centre = r.getrandbits(64)
    fps = {centre}
    for _ in range(120):
        x = centre
        for _ in range(r.randrange(1, 5)):
            x ^= 1 << r.randrange(64)
        fps.add(x)
    fps |= {r.getrandbits(64) for _ in range(60)}
    named = dict(enumerate(sorted(x - (1 << 64) if x >> 63 else x for x in fps)))
    unsigned = {i: x % (1 << 64) for i, x in named.items()}
    frame = spark.createDataFrame([(x,) for x in named.values()], "fp bigint")
    by_fp = {x: i for i, x in named.items()}
    want = brute(unsigned)
    for hot in (4, 1000):
        pairs = [(by_fp[p.a], by_fp[p.b]) for p in simhash.links(frame, hot=hot).collect()]
        assert len(set(pairs)) == len(pairs)
        assert all(bin(unsigned[a] ^ unsigned[b]).count("1") <= 2 for a, b in pairs)
        got = {i: i for i in named}
        got |= {r.node: r.root for r in connected(spark.createDataFrame(pairs, "a bigint, b bigint"), "a", "b").collect()}
        assert got == want


def test_unsettled_components_are_an_error(spark):
    links = spark.createDataFrame([(0, 1), (1, 2), (2, 3)], "src bigint, dst bigint")
    with pytest.raises(RuntimeError):
        connected(links, "src", "dst", rounds=1)


def test_simhash_broadcasts_no_uncounted_table(spark, monkeypatch):
    plans, keep = [], simhash.written
    monkeypatch.setattr(simhash, "written", lambda df, name: plans.append((name, df._jdf.queryExecution().executedPlan().toString())) or keep(df, name))
    fps = spark.createDataFrame([(0,), (1,), (3,), (1 << 40,)], "fp bigint")
    assert {(min(r.a, r.b), max(r.a, r.b)) for r in simhash.links(fps).collect()} >= {(0, 1), (0, 3), (0, 1 << 40)}
    assert {name for name, _ in plans} == {"variants", "links"} and not [name for name, plan in plans if "Broadcast" in plan]
