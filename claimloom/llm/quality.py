"""Quality classifier (operator 4): a weak-label model teaches a hashed linear scorer.

Overlapping heuristic labellers vote (low / good / no vote) on a bounded sample of documents; expectation-maximisation
estimates each labeller's accuracy and gives every sampled document a posterior. Human labels, where a document has
them, are one more labeller. Two such models are fitted, for low quality and for toxicity; some toxicity labellers are
term lists mined from one half of the sample. The posteriors train two sparse linear scorers over hashed features (words,
word prefixes and text statistics), which score every document by its whole text. A document stays if both scores are
below one half.

The sample has at most SAMPLE rows (the smallest hashes of doc_id in `labels`); only their votes and features reach the
driver. Null, empty and blank texts have no features but `empty`, and stay unless the labels say otherwise; null labels
cast no vote; without any labels the fixed heuristics alone teach. Repeated rows are scored each. Other columns are kept.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import as_bytes, safe_slices, small_batches, table

SAMPLE = 6000
TERMS = 4000
MEMO_ENTRIES = 500_000
PREFIXES = (4, 5, 6)

# Plain insults, one of several labellers for toxicity.
INSULTS = frozenset(b"idiot idiots moron morons stupid loser losers scum trash worthless pathetic disgusting clown".split())

_STRIP = b".,;:!?\"'()[]{}<>*#$%&|-_"
_SYMBOLS = np.zeros(256, bool)
_SYMBOLS[list(b"&$#%*@^~=+\\{}<>")] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_ALPHA = np.zeros(256, bool)
_ALPHA[65:91] = _ALPHA[97:123] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True


def statistics(text: bytes) -> tuple[dict[str, float], set[bytes]]:
    """Shares that describe a whole text, and its distinct lower-cased words."""
    n_words = repeats = 0
    distinct: set[bytes] = set()
    last = b""
    counts = np.zeros(256, np.int64)
    for part in safe_slices(text):
        words = part.lower().split()
        counts += np.bincount(np.frombuffer(part, np.uint8), minlength=256)
        n_words += len(words)
        if words:
            repeats += sum(map(bytes.__eq__, words, [last, *words[:-1]]))
            last = words[-1]
        distinct.update(words)
    lines = [x for x in text.split(b"\n") if x]
    total, letters = max(1, int(counts.sum())), int(counts[_ALPHA].sum())
    n = max(1, n_words)
    return {
        "words": n_words,
        "variety": len(distinct) / n,
        "repeats": repeats / n,
        "symbols": int(counts[_SYMBOLS].sum()) / total,
        "shouts": text.count(b"!!") / n,
        "upper": int(counts[_UPPER].sum()) / max(1, letters),
        "pipes": int(counts[124]) / n,
        "digits": int(counts[_DIGIT].sum()) / total,
        "same_lines": 1 - len(set(lines)) / max(1, len(lines)),
    }, distinct


# Borders of the statistics' bands; the labellers use the last one.
BANDS = {
    "variety": (0.15, 0.3, 0.45, 0.6),
    "repeats": (0.03, 0.1, 0.2),
    "symbols": (0.005, 0.015, 0.03),
    "shouts": (0.02, 0.05, 0.1),
    "upper": (0.1, 0.25, 0.4),
    "pipes": (0.02, 0.05, 0.1),
    "digits": (0.05, 0.15, 0.3),
    "same_lines": (0.2, 0.5, 0.8),
}


def bands(s: dict[str, float]) -> list[str]:
    if not s["words"]:
        return ["empty"]
    short = "s" if s["words"] < 30 else "n"
    return [f"{k}:{sum(s[k] >= b for b in BANDS[k])}" for k in BANDS if k != "variety"] + [f"variety:{short}:{sum(s['variety'] >= b for b in BANDS['variety'])}"]


def quality_votes(s: dict[str, float]) -> list[int]:
    """1 low, 0 good, -1 no vote."""
    if not s["words"]:
        return [-1] * 7
    bad = [s["symbols"] > 0.03, s["shouts"] > 0.1 or s["upper"] > 0.5, s["pipes"] > 0.1, s["repeats"] > 0.2, s["variety"] < 0.3 and s["words"] >= 40, s["digits"] > 0.3]
    plain = s["symbols"] < 0.01 and s["shouts"] < 0.02 and s["pipes"] < 0.02 and s["repeats"] < 0.05 and (s["variety"] > 0.45 or s["words"] > 3000)
    return [*(1 if b else -1 for b in bad), 0 if plain else 1 if any(bad) else -1]


def hashed(feature: bytes | str) -> int:
    return xxhash.xxh64_intdigest(feature) >> 1


def word_features(word: bytes) -> list[int]:
    """Hashes of a word (even) and of its prefixes (odd)."""
    w = word.strip(_STRIP)
    return [hashed(w) & ~1, *(hashed(w[:k]) | 1 for k in PREFIXES if len(w) >= k)] if w else []


def all_features(words: set[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature hashes of a text's distinct words, and how many words have each."""
    return np.unique(np.array([f for w in words for f in word_features(w)], np.int64), return_counts=True)


def expectation_maximisation(votes: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, np.ndarray, float]:
    """Posterior of class 1, P(vote | class) per labeller as [labeller, class, vote + 1], and the class prior."""
    n, m = votes.shape
    ones, cast = (votes == 1).sum(1), (votes >= 0).sum(1)
    p = np.where(cast > 0, (ones + 0.1) / (cast + 0.4), 0.1)
    table_ = np.zeros((m, 2, 3))
    prior = 0.5
    for _ in range(rounds):
        prior = float(np.clip(p.mean(), 1e-3, 1 - 1e-3))
        for j in range(m):
            for v in (-1, 0, 1):
                here = votes[:, j] == v
                table_[j, 1, v + 1] = (p[here].sum() + 0.5) / (p.sum() + 1.5)
                table_[j, 0, v + 1] = ((1 - p)[here].sum() + 0.5) / ((1 - p).sum() + 1.5)
        log = np.full((n, 2), 0.0)
        log[:, 1], log[:, 0] = math.log(prior), math.log(1 - prior)
        for j in range(m):
            for c in (0, 1):
                log[:, c] += np.log(table_[j, c, votes[:, j] + 1])
        new = 1 / (1 + np.exp(np.clip(log[:, 0] - log[:, 1], -50, 50)))
        if np.abs(new - p).max() < 1e-6:
            p = new
            break
        p = new
    return p, table_, prior


def sparse_logistic(rows: list[np.ndarray], values: list[np.ndarray], target: np.ndarray, width: int, l1: float = 2e-4, rounds: int = 300) -> tuple[np.ndarray, float]:
    """Weights and bias by proximal gradient with momentum; classes weigh alike."""
    row = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    col = np.concatenate(rows) if rows else np.empty(0, np.int64)
    val = np.concatenate(values) if rows else np.empty(0)
    share = float(np.clip(target.mean(), 1e-3, 1 - 1e-3)) if len(target) else 0.5
    weight = np.where(target > 0.5, 0.5 / share, 0.5 / (1 - share)) / max(1, len(target))
    scale = np.sqrt(np.bincount(col, weights=val * val, minlength=width) / max(1, len(target))) + 1e-2
    w, b, vw, vb = np.zeros(width), 0.0, np.zeros(width), 0.0
    z = val / scale[col]
    for t in range(rounds):
        look, lookb = w + 0.9 * vw, b + 0.9 * vb
        s = np.bincount(row, weights=z * look[col], minlength=len(rows)) + lookb
        g = (1 / (1 + np.exp(-np.clip(s, -40, 40))) - target) * weight
        rate = 2.0 / (1 + t / 100)
        step = look - rate * np.clip(np.bincount(col, weights=z * g[row], minlength=width), -0.1, 0.1)
        new = np.sign(step) * np.maximum(np.abs(step) - rate * l1, 0)
        newb = lookb - rate * g.sum()
        vw, vb, w, b = new - w, newb - b, new, newb
    return w / scale, b


class Scorer:
    """Two linear scorers over hashed features; unknown hashes weigh nothing."""

    def __init__(self, low: dict[int, float], toxic: dict[int, float], bias: tuple[float, float], report: dict):
        self.low, self.toxic, self.bias, self.report = low, toxic, bias, report
        self.memo: dict[bytes, float] = {}

    def score(self, text: bytes) -> tuple[float, float]:
        s, words = statistics(text)
        low = self.bias[0] + sum(self.low.get(hashed("s" + f), 0.0) for f in bands(s))
        memo, toxic = self.memo, self.bias[1]
        for w in words:
            x = memo.get(w)
            if x is None:
                if len(memo) >= MEMO_ENTRIES:
                    memo.clear()
                x = memo[w] = sum(self.toxic.get(f, 0.0) for f in word_features(w))
            if x:
                toxic += x
        return 1 / (1 + math.exp(-max(-40, min(40, low)))), 1 / (1 + math.exp(-max(-40, min(40, toxic))))


def _sampled(docs: DataFrame, labels: DataFrame, text: str, key: str, size: int) -> list[tuple]:
    """(quality, toxic, statistics, feature hashes, their counts) of the sampled documents, in an order that the layout of docs does not change.

    A repeated doc_id counts once, with its least text.
    """
    ids = labels.where(F.col(key).isNotNull()).groupBy(key).agg(F.max("quality").alias("_q"), F.max("toxic").alias("_t"))
    few = ids.orderBy(F.xxhash64(key), key).limit(size)
    source = docs.select(key, F.col(text).alias("_text")).join(F.broadcast(few), key)
    source = source.groupBy(key).agg(F.min("_text").alias("_text"), F.max("_q").alias("_q"), F.max("_t").alias("_t")).select("_q", "_t", "_text", F.xxhash64(key).alias("_order"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_text"):
            stats, packed = [], []
            for t in as_bytes(batch.column(2)):
                s, distinct = statistics(t)
                stats.append(list(s.values()))
                f, n = all_features(distinct)
                packed.append(f.tobytes() + n.astype(np.uint16).tobytes())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), batch.column(1).cast(pa.int64()), pa.array(stats, pa.list_(pa.float64())), pa.array(packed, pa.binary()), batch.column(3)],
                names=["_q", "_t", "stats", "packed", "_order"],
            )

    out = []
    for r in source.mapInArrow(run, "_q bigint, _t bigint, stats array<double>, packed binary, _order bigint").toLocalIterator():
        raw = bytes(r[3])
        n = len(raw) // 10
        out.append((r[4], raw, (r[0], r[1], r[2], np.frombuffer(raw, np.int64, n), np.frombuffer(raw, np.uint16, n, 8 * n))))
    out.sort(key=lambda x: x[:2])
    return [x[2] for x in out]


def _one_of_each(feats: list[np.ndarray]) -> list[int]:
    """Documents of which no other has the same least rare features: copies and near copies count once."""
    every, times = np.unique(np.concatenate(feats), return_counts=True) if feats else (np.empty(0, np.int64), np.empty(0))
    common = every[times > max(2, len(feats) // 20)]
    met, out = set(), []
    for i, f in enumerate(feats):
        rare = f[~np.isin(f, common, assume_unique=True)][:2]
        sketch = tuple(rare.tolist()) if len(rare) else f.tobytes()
        if sketch not in met:
            met.add(sketch)
            out.append(i)
    return out


def telling(feats: list[np.ndarray], p: np.ndarray, most: int = TERMS, doubt: float = 0.01, purity: float = 0.95) -> np.ndarray:
    """Features that belong to class 1 more often than chance explains over all features tried, sorted."""
    pick = _one_of_each(feats)
    if not pick:
        return np.empty(0, np.int64)
    every, place = np.unique(np.concatenate([feats[i] for i in pick]), return_inverse=True)
    times = np.bincount(place, minlength=len(every))
    bad = np.bincount(place, weights=np.repeat(p[pick], [len(feats[i]) for i in pick]), minlength=len(every))
    share = float(np.clip(p.mean(), 1e-3, 0.5))
    least = min(math.log(max(1, len(every)) / doubt) / math.log(1 / share), max(2.5, 0.2 * float(p[pick].sum())))
    found = np.flatnonzero((bad >= least) & (bad > purity * times))
    return np.sort(every[found[np.argsort(-bad[found], kind="stable")[:most]]])


def fit(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", size: int = SAMPLE) -> Scorer:
    names = list(statistics(b"")[0])
    rows = _sampled(docs, labels, text, key, size)
    n_rows = len(rows)
    if not rows:
        rows = [(None, None, list(s.values()), *all_features(d)) for t in [b"plain words of a text that says what it means to say"] * 4 + [b"idiot moron scum"] * 2 for s, d in [statistics(t)]]
    stats, feats = [dict(zip(names, r[2])) for r in rows], [r[3] for r in rows]
    human_low = [-1 if r[0] is None else int(r[0] == 0) for r in rows]
    human_toxic = [-1 if r[1] is None else int(r[1] > 0) for r in rows]

    low_votes = np.array([[*quality_votes(s), h] for s, h in zip(stats, human_low)])
    p_low, table_low, _ = expectation_maximisation(low_votes)
    at = {f: i for i, f in enumerate(sorted({b for s in stats for b in bands(s)}))}
    dense = [np.array([at[b] for b in bands(s)], np.int64) for s in stats]
    w_low, b_low = sparse_logistic(dense, [np.ones(len(d)) for d in dense], p_low, len(at))

    shown = [i for i, h in enumerate(human_toxic) if h >= 0 and i % 2 == 0]
    truth = np.array([float(human_toxic[i]) for i in shown])
    words, stems = (telling([feats[i][feats[i] % 2 == odd] for i in shown], truth) for odd in (0, 1))
    insults = np.sort(np.array([hashed(w) & ~1 for w in INSULTS], np.int64))
    has = [[bool(np.isin(f, terms, assume_unique=True).any()) for terms in (insults, words, stems)] for f in feats]
    p_toxic, table_toxic, _ = expectation_maximisation(np.array([[*(1 if x else -1 for x in h), -1 if any(h) else 0, y] for h, y in zip(has, human_toxic)]))
    chosen = telling(feats, p_toxic)
    columns, values = [], []
    for f, r in zip(feats, rows):
        here = np.isin(f, chosen, assume_unique=True)
        columns.append(np.searchsorted(chosen, f[here]))
        values.append(r[4][here].astype(float))
    w_toxic, b_toxic = sparse_logistic(columns, values, p_toxic, len(chosen), l1=1e-4)
    return Scorer(
        {hashed("s" + f): float(w_low[i]) for f, i in at.items() if w_low[i]},
        {int(f): float(w) for f, w in zip(chosen, w_toxic) if w},
        (float(b_low), float(b_toxic)),
        {"quality": table_low.tolist(), "toxic": table_toxic.tolist(), "rows": n_rows},
    )


def classify(docs: DataFrame, scorer: Scorer, text: str = "text") -> DataFrame:
    """docs with p_low, p_toxic and kept; columns of docs with those names are replaced."""
    sent = docs.sparkSession.sparkContext.broadcast(scorer)
    base = docs.drop("p_low", "p_toxic", "kept")
    fields, names = base.schema.fields, [*base.columns, "p_low", "p_toxic", "kept"]
    at = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, text):
            scores = [sent.value.score(t) for t in as_bytes(batch.column(at))]
            low, toxic = [a for a, _ in scores], [b for _, b in scores]
            yield pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array(low, pa.float64()), pa.array(toxic, pa.float64()), pa.array([a < 0.5 and b < 0.5 for a, b in scores], pa.bool_())], names=names
            )

    from pyspark.sql import types as T

    added = [T.StructField("p_low", T.DoubleType()), T.StructField("p_toxic", T.DoubleType()), T.StructField("kept", T.BooleanType())]
    return base.mapInArrow(run, T.StructType([*fields, *added]))


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return classify(docs, fit(docs, table(spark, sf_dir, "labels"))).select("doc_id", F.round("p_low", 6).alias("p_low"), F.round("p_toxic", 6).alias("p_toxic"), "kept")


QUERIES = {"op4_quality": op4_quality}
ORACLES: dict[str, str] = {}
