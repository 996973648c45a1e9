import hashlib
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from claimloom.llm import repeats, substring_dedup, suffix_dedup

from . import edge_cases


def sample():
    r = random.Random(7)
    vocabulary = [f"w{i}" for i in range(60)] + ["é", "ß漢"]
    base = [" ".join(r.choice(vocabulary) for _ in range(r.randrange(0, 160))) for _ in range(40)]
    out = list(edge_cases.rows())
    for i in range(160):
        a, b = r.choice(base), r.choice(base)
        t = a[: r.randrange(0, len(a) + 1)] + r.choice([" ", "  ", "\n", ""]) + b[r.randrange(0, len(b) + 1) :]
        out.append((100 + i, t, *[None] * 6))
    return out


def removed_words(rows, length):
    docs = [(i, (t or "").encode().split()) for i, t, *_ in rows]
    seen = Counter(tuple(w[p : p + length]) for _, w in docs for p in range(len(w) - length + 1))
    for i, w in docs:
        gone = {j for p in range(len(w) - length + 1) if seen[tuple(w[p : p + length])] > 1 for j in range(p, p + length)}
        yield i, len(w), len(gone), hashlib.sha256(b" ".join(x for j, x in enumerate(w) if j not in gone)).hexdigest()


def removed_bytes(rows, length):
    docs = [(i, (t or "").encode()) for i, t, *_ in rows]
    first = defaultdict(lambda: 1 << 70)
    for i, b in docs:
        for p in range(len(b) - length + 1):
            first[b[p : p + length]] = min(first[b[p : p + length]], i)
    for i, b in docs:
        gone = bytearray(len(b) + 1)
        for p in range(len(b) - length + 1):
            if first[b[p : p + length]] < i:
                gone[p : p + length] = b"\1" * length
        spans = sum(1 for j in range(len(b)) if gone[j] and not (j and gone[j - 1]))
        yield i, len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()


SMALL = [{}, {"chunk_bytes": 4000, "shard_bytes": 3000, "bucket_entries": 64, "hot_chunks": 3}]


@pytest.mark.parametrize("sizes", SMALL)
def test_substring_dedup(spark, sizes):
    rows = sample()
    frame = spark.createDataFrame(rows, edge_cases.SCHEMA)
    got = substring_dedup.repeated_words(frame, length=12, k=4, **sizes).collect()
    mine = sorted((r.doc_id, r.n, sum(s.end - s.start for s in r.spans), hashlib.sha256(r.kept.encode()).hexdigest()) for r in got)
    assert mine == sorted(removed_words(rows, 12))


@pytest.mark.parametrize("sizes", SMALL)
def test_suffix_dedup(spark, sizes):
    rows = sample()
    frame = spark.createDataFrame(rows, edge_cases.SCHEMA)
    got = suffix_dedup.repeated_bytes(frame, length=50, **sizes).collect()
    mine = sorted((r.doc_id, r.n, sum(s.end - s.start for s in r.spans), len(r.spans), hashlib.sha256(r.kept).hexdigest()) for r in got)
    assert mine == sorted(removed_bytes(rows, 50))


def test_empty_and_repeated_rows(spark):
    assert substring_dedup.repeated_words(edge_cases.empty(spark)).count() == 0
    assert suffix_dedup.repeated_bytes(edge_cases.empty(spark)).count() == 0
    t = " ".join(f"w{i}" for i in range(40))
    twice = spark.createDataFrame([(1, t), (1, t), (None, t)], "doc_id bigint, text string")
    assert {r.kept for r in substring_dedup.repeated_words(twice).collect()} == {""}
    assert sorted((r.doc_id is None, len(r.kept)) for r in suffix_dedup.repeated_bytes(twice).collect()) == [(False, len(t)), (False, len(t)), (True, 0)]


def test_automaton_counts():
    r = random.Random(2)
    seqs = [[r.randrange(3) for _ in range(r.randrange(0, 30))] for _ in range(20)]
    a = substring_dedup.SuffixAutomaton()
    weights = [r.randrange(1, 4) for _ in seqs]
    for s, w in zip(seqs, weights):
        a.add(s, w)
    a.close()
    count = Counter()
    for s, w in zip(seqs, weights):
        for p in range(len(s) - 3):
            count[tuple(s[p : p + 4])] += w
    probe = [r.randrange(4) for _ in range(400)]
    assert a.matches(probe, 4) == [0] * 3 + [count[tuple(probe[p : p + 4])] for p in range(len(probe) - 3)]


def test_reference_automata_are_broadcast(spark):
    ref = [" ".join(f"r{i}" for i in range(50)).encode()]
    docs = spark.createDataFrame([(1, "x " + " ".join(f"r{i}" for i in range(5, 45)) + " y"), (2, None), (3, "r1 r2")], "doc_id bigint, text string")
    got = {r.doc_id: [(s.start, s.end) for s in r.spans] for r in substring_dedup.remove_reference(docs, ref).collect()}
    assert got == {1: [(1, 41)], 2: [], 3: []}


def test_owners_tile_and_agree():
    r = np.random.default_rng(1)
    a = r.integers(0, 4, 600_000).astype(np.uint8)
    h, first, n = repeats.owners(a, 50, 16)
    assert first[0] == 0 and (first[1:] == first[:-1] + n[:-1]).all() and first[-1] + n[-1] == len(a) - 49
    h2, first2, n2 = repeats.owners(a[300_000:301_000], 50, 16)
    whole = np.repeat(h, n)
    assert (whole[300_000 : 300_000 + n2.sum()] == np.repeat(h2, n2)).all()


def test_messages_keep_their_size():
    """Chunks times shards grow with the volume, not with its square, up to the largest chunk and shard."""
    how = repeats.Repeats(50, 16, False, True, None, shard_bytes=suffix_dedup.SHARD_BYTES)

    def message(volume):
        chunk, shard = repeats._sizes(volume, how)
        return chunk * shard / volume

    assert repeats._sizes(1 << 30, how) == (how.chunk_bytes, how.shard_bytes)
    assert message(8 << 30) >= 0.99 * message(2 << 30)
    assert max(repeats._sizes(1 << 50, how)) <= repeats.LARGEST_CHUNK


def test_dealt_documents_are_packed():
    r = random.Random(3)
    texts = [" ".join(r.choice(["alpha", "beta", "gamma"]) for _ in range(200)) for _ in range(40)] + [None, ""]
    keys = [*range(40), None, 7]
    batch = pa.record_batch([pa.array([i % 3 for i in range(42)], pa.int64()), pa.array(keys, pa.int64()), pa.array(texts, pa.string())], names=["chunk", "_key", "_text"])
    rows = pa.Table.from_batches(list(repeats._dealt([batch])))
    assert rows.num_rows == 3 and rows.nbytes < 0.5 * batch.nbytes
    got = [pair for row in rows.to_pylist() for pair in zip(*repeats._undealt(pa.Table.from_pylist([row], rows.schema)))]
    assert sorted(got, key=str) == sorted(((k, (t or "").encode()) for k, t in zip(keys, texts)), key=str)


def test_hot_owners_travel_in_segments(spark, tmp_path):
    """A passage in every chunk, in many surroundings, costs far less than its windows one by one."""
    r = random.Random(9)
    word = lambda: "".join(r.choice("abcdefghijklmnop") for _ in range(r.randrange(3, 9)))
    common = " ".join(word() for _ in range(60))
    rows = [(i, " ".join([word() for _ in range(30)] + [common] + [word() for _ in range(30)])) for i in range(60)]
    frame = spark.createDataFrame(rows, "doc_id bigint, text string")

    def run(hot):
        log = tmp_path / f"sent-{hot}"

        def decide(segments, n_windows, orders, owners):
            with open(log, "a") as f:
                f.write(f"{sum(map(len, segments))} {n_windows.sum()}\n")
            return suffix_dedup.by_owner(segments, n_windows, orders, owners)

        how = repeats.Repeats(50, 16, False, True, decide, hot_chunks=hot, chunk_bytes=4000, shard_bytes=3000, bucket_entries=256)
        got = sorted(repeats.spans(frame, how).collect(), key=lambda x: x.doc_id)
        return got, np.loadtxt(log, ndmin=2).sum(axis=0)

    (cool, _), (hot, (sent, windows)) = run(1000), run(3)
    assert cool == hot and sum(len(x.spans) for x in hot) >= 59
    assert sent < 0.4 * 50 * windows
