import random

import numpy as np

from claimloom.llm import quality

from . import edge_cases


def corpus(n=600):
    r = random.Random(4)
    vocabulary = ["".join(r.choice("abdeilmnorstu") for _ in range(r.randrange(2, 9))) for _ in range(900)]
    docs, labels = [], []
    for i in range(n):
        words = [r.choice(vocabulary) for _ in range(r.randrange(20, 200))]
        low, toxic = r.random() < 0.2, r.random() < 0.2
        if toxic:
            for _ in range(4):
                words.insert(r.randrange(len(words)), r.choice(["idiot", "zorbag", "zorbish", "zorbuk"]))
        text = " ".join(words)
        if low:
            text = r.choice([lambda t: t.upper().replace(" ", "!! "), lambda t: " ".join(w + "$$$" for w in t.split()), lambda t: " ".join(w for w in t.split()[:9] for _ in range(12))])(text)
        docs.append((i, text))
        labels.append((i, int(not low), int(toxic)))
    return docs, labels


def test_em_finds_accuracies():
    r = np.random.default_rng(0)
    y = r.random(4000) < 0.3
    votes = np.stack([np.where(r.random(4000) < 0.2, -1, np.where(r.random(4000) < a, y, ~y).astype(int)) for a in (0.95, 0.85, 0.7)], 1)
    p, tables, prior = quality.expectation_maximisation(votes)
    assert abs(prior - 0.3) < 0.05 and ((p > 0.5) == y).mean() > 0.9
    accuracy = [t[1, 2] / (t[1, 1] + t[1, 2]) for t in tables]
    assert abs(accuracy[0] - 0.95) < 0.06 and accuracy[0] > accuracy[1] > accuracy[2]


def test_held_out_accuracy(spark):
    docs, labels = corpus()
    frame = spark.createDataFrame(docs, "doc_id bigint, text string")
    scorer = quality.fit(frame, spark.createDataFrame([x for x in labels if x[0] < 400], "doc_id bigint, quality int, toxic int"))
    got = {r.doc_id: r for r in quality.classify(frame, scorer).collect()}
    held = [x for x in labels if x[0] >= 400]
    assert np.mean([(got[i].p_low >= 0.5) == (q == 0) for i, q, _ in held]) > 0.95
    clear = [(i, t) for i, q, t in held if q == 1]
    assert np.mean([(got[i].p_toxic >= 0.5) == bool(t) for i, t in clear]) > 0.95


def test_edges(spark):
    frame = edge_cases.frame(spark).withColumnRenamed("n_tokens", "kept")
    none = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    null = spark.createDataFrame([(1, None, None), (None, 1, 1)], "doc_id bigint, quality int, toxic int")
    for labels in (none, null):
        got = quality.classify(frame, quality.fit(frame, labels))
        assert set(frame.columns) | {"p_low", "p_toxic"} == set(got.columns)
        rows = got.collect()
        assert len(rows) == len(edge_cases.rows()) and all(0 <= r.p_low <= 1 and r.kept is not None for r in rows)
    assert quality.classify(edge_cases.empty(spark), quality.fit(edge_cases.empty(spark), none)).count() == 0
