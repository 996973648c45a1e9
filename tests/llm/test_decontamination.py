import random

from claimloom.llm import decontamination as D

from . import edge_cases


def plain_edits(item, text):
    """Least edits of item against any passage of text, by the full table."""
    row = [0] * (len(text) + 1)
    for i, a in enumerate(item):
        new = [i + 1]
        for j, b in enumerate(text):
            new.append(min(row[j] + (a != b), row[j + 1] + 1, new[j] + 1))
        row = new
    return min(row)


def edited(r, item, n):
    y = bytearray(item)
    for _ in range(n):
        p, op = r.randrange(len(y)), r.random()
        if op < 0.4:
            y[p] = r.choice(b"abcdefgh")
        elif op < 0.7:
            y.insert(p, r.choice(b"abcdefgh"))
        else:
            del y[p]
    return bytes(y)


def setting():
    r = random.Random(8)
    word = lambda: "".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(r.randrange(2, 9)))
    prose = lambda n: " ".join(word() for _ in range(n))
    items = [(i, prose(r.randrange(14, 50))) for i in range(12)] + [(90, "tiny passage here"), (91, None), (92, " ")]
    docs, want = [], {}
    for d in range(120):
        parts = [prose(r.randrange(5, 120))]
        if d % 3 == 0:
            i, t = items[r.randrange(12)]
            parts.append(edited(r, t.encode(), r.randrange(0, 1 + int(0.05 * len(t)))).decode())
        if d % 40 == 1:
            parts.append("Tiny  PASSAGE\nhere")
        docs.append((d, " ".join([*parts, prose(r.randrange(0, 60))])))
    return items, docs


def test_bit_vectors_equal_table():
    r = random.Random(1)
    for _ in range(60):
        item = bytes(r.choice(b"abc") for _ in range(r.randrange(1, 40)))
        text = bytes(r.choice(b"abc") for _ in range(r.randrange(0, 90)))
        assert D.edits_within(item, text, len(item))[0] == plain_edits(item, text)


def test_leaks_against_brute_force(spark):
    items, docs = setting()
    frame = spark.createDataFrame(docs, "doc_id bigint, text string")
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = {(r.doc_id, r.item_id): r.edits for r in D.contamination(frame, bench).collect()}
    want = {}
    for d, t in docs:
        for i, x in items:
            n = D.normal(x)
            e = plain_edits(n, D.normal(t)) if n else 1 << 30
            if n and e <= (int(D.RATE * len(n)) if len(n) >= D.SHORT else 0):
                want[d, i] = e
    assert set(got) <= set(want) and len(got) >= 0.9 * len(want) and len(want) > 40
    assert all(got[k] == want[k] for k in got)
    assert {k for k, e in want.items() if e == 0} <= set(got)
    left = {r.doc_id for r in D.clean_documents(frame, bench).collect()}
    assert left == {d for d, _ in docs} - {d for d, _ in got}


def test_edges(spark):
    items, _ = setting()
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    frame = edge_cases.frame(spark)
    assert D.contamination(frame, bench).count() == 0
    assert D.clean_documents(frame, bench).columns == frame.columns and D.clean_documents(frame, bench).count() == len(edge_cases.rows())
    assert D.contamination(edge_cases.empty(spark), bench).count() == 0
    none = spark.createDataFrame([], "item_id bigint, text string")
    assert D.contamination(frame, none).count() == 0
    null = spark.createDataFrame([(None, items[0][1]), (None, items[0][1]), (5, items[0][1])], "doc_id bigint, text string")
    assert sorted((r.doc_id or -1, r.item_id) for r in D.contamination(null, bench).collect()) == [(-1, 0), (5, 0)]


def test_tables_follow_target():
    assert D.tables_for(0.99) > D.tables_for(0.9) > D.tables_for(0.5) >= 1
