"""Benchmark decontamination (operator 2): CGK embedding, bit-sampling LSH and exact edit verification.

Texts and items are lower-cased, white space collapsed, and compared as UTF-8 bytes. A document leaks an item if some
passage of it is within RATE * length edits of the item.

* The random walk of Chakraborty, Goldenberg and Koucky reads a string and advances by a random bit that depends on step
  and symbol; strings at small edit distance get embeddings at small Hamming distance, because the walks meet again.
* Windows of item size (items fall in length classes, a class embeds its shortest length) that start at words are
  embedded by several walks; each table samples BITS places. The number of tables follows from the target recall.
* Windows that share a table entry with an item are verified by bit-parallel approximate matching of the whole item.
* Only places that can hold an item are embedded: a passage within e edits of an item of L bytes keeps at least
  L - q + 1 - q * e of its q-byte strings, so places with too few strings of any item are passed over without loss.

Items below SHORT bytes are matched exactly. The items are broadcast behind a size check. Null and empty texts leak
nothing; null and blank items are passed over; items with equal text are all reported; rows of one doc_id are joined.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import small_batches, table
from .rolling import windows

RATE = 0.06
SHORT = 32
BITS = 5
WALKS = 2
TARGET = 0.95
AGREEMENT = 0.6  # expected share of equal places in the embeddings of an item and a passage at RATE edits
STEP_LENGTH = 1.6  # steps for each byte: a walk advances every other step and stays inside its window
ITEM_BYTES = 64 << 20
_BITMAP = 24


def normal(text: str | None) -> bytes:
    return " ".join((text or "").lower().split()).encode("utf-8", "replace")


def tables_for(target: float = TARGET, agreement: float = AGREEMENT, bits: int = BITS) -> int:
    """Tables after which a pair that agrees in this share of places has met with probability target."""
    return math.ceil(math.log(1 - target) / math.log(1 - agreement**bits))


def edits_within(item: bytes, text: bytes, most: int) -> tuple[int, int]:
    """(least edits of item against any passage of text, where that passage ends), by Myers' bit vectors; (most + 1, -1) if more."""
    m = len(item)
    peq: dict[int, int] = {}
    for i, c in enumerate(item):
        peq[c] = peq.get(c, 0) | (1 << i)
    full, top = (1 << m) - 1, 1 << (m - 1)
    pv, mv, score = full, 0, m
    best, at = (m, 0) if m <= most else (most + 1, -1)
    get = peq.get
    for j, c in enumerate(text):
        eq = get(c, 0)
        xv = eq | mv
        xh = (((eq & pv) + pv) ^ pv) | eq
        ph = mv | ~(xh | pv)
        mh = pv & xh
        if ph & top:
            score += 1
        elif mh & top:
            score -= 1
        ph <<= 1
        mh <<= 1
        pv = (mh | ~(xv | ph)) & full
        mv = ph & xv & full
        if score < best:
            best, at = score, j + 1
    return best, at


class Items:
    """The benchmark's items, their tables and their q-byte strings."""

    def __init__(self, items: list[tuple[int, str | None]], rate: float = RATE, bits: int = BITS, walks: int = WALKS, target: float = TARGET, seed: int = 42):
        self.rate = rate
        every = [(i, n) for i, t in items if (n := normal(t))]
        self.short = [(i, n) for i, n in every if len(n) < SHORT]
        self.items = sorted(((i, n) for i, n in every if len(n) >= SHORT), key=lambda x: len(x[1]))
        self.classes: list[int] = []
        if not self.items:
            return
        lengths = [len(n) for _, n in self.items]
        self.edits = [int(rate * n) for n in lengths]
        self.q = max(3, min(8, min(n // (e + 1) for n, e in zip(lengths, self.edits))))
        self.reach = int((1 + rate) * lengths[0]) + 1
        self.least = max(1, min(math.floor((n - self.q + 1 - self.q * e) * min(1.0, (self.reach - self.q) / ((1 + rate) * n))) for n, e in zip(lengths, self.edits)))
        self.grams = np.zeros(1 << _BITMAP, bool)
        self.own_grams = [np.unique(windows(np.frombuffer(n, np.uint8), self.q)) for _, n in self.items]
        for own in self.own_grams:
            self.grams[own >> np.uint64(64 - _BITMAP)] = True
        self.classes = sorted({lengths[0], lengths[len(lengths) // 3], lengths[2 * len(lengths) // 3]})
        r = np.random.default_rng(seed)
        self.steps = r.integers(0, 2, (walks, int(STEP_LENGTH * max(self.classes)), 256), dtype=np.int64)
        tables = tables_for(target, bits=bits)
        self.samples = {c: [(w, sorted(r.choice(int(STEP_LENGTH * c), bits, replace=False).tolist())) for w in np.arange(tables) % walks] for c in self.classes}
        self.known: dict[int, dict[int, list[int]]] = {}
        text = b"".join(n + bytes(2 * max(self.classes)) for _, n in self.items)
        starts = np.cumsum([0, *(len(n) + 2 * max(self.classes) for _, n in self.items)])[:-1]
        own = np.array([max(c for c in self.classes if c <= n) for n in lengths])
        for c in self.classes:
            here = np.flatnonzero(own == c)
            entry: dict[int, list[int]] = {}
            for keys in self.keys(np.frombuffer(text, np.uint8), starts[here], c):
                for i, k in zip(here.tolist(), keys.tolist()):
                    entry.setdefault(k, []).append(i)
            self.known[c] = entry
        self.sorted = {c: np.sort(np.array(list(e), np.uint64)) for c, e in self.known.items()}

    def keys(self, text: np.ndarray, starts: np.ndarray, length: int) -> Iterator[np.ndarray]:
        """One key for each start and table: the table's places of the embedded window."""
        samples = self.samples[length]
        for w in range(len(self.steps)):
            mine = [(t, places) for t, (v, places) in enumerate(samples) if v == w]
            wanted = {p for _, places in mine for p in places}
            kept, at = {}, starts.astype(np.int64).copy()
            for j in range(max(wanted, default=-1) + 1):
                c = text.take(at)
                if j in wanted:
                    kept[j] = c
                at += self.steps[w, j].take(c)
            for t, places in mine:
                key = np.full(len(starts), t + 1, np.uint64)
                for p in places:
                    key = key * np.uint64(257) + kept[p].astype(np.uint64)
                yield key

    def places(self, text: np.ndarray) -> np.ndarray:
        """Word starts of a normalised text where an item may begin."""
        hits = self.grams[windows(text, self.q) >> np.uint64(64 - _BITMAP)]
        if int(hits.sum()) < self.least:
            return np.empty(0, np.int64)
        total = np.concatenate([[0], np.cumsum(hits)])
        span = min(len(hits), max(1, self.reach - self.q + 1))
        dense = np.flatnonzero(total[span:] - total[:-span] >= self.least)
        if not len(dense):
            return dense
        longest = int((1 + self.rate) * len(self.items[-1][1])) + self.reach
        near = np.zeros(len(text) + 1, np.int64)
        np.add.at(near, np.maximum(dense - longest, 0), 1)
        np.add.at(near, np.minimum(dense + span, len(text)), -1)
        blank = text == 32
        start = np.concatenate([[True], blank[:-1]]) & ~blank
        gaps = np.arange(len(text)) - np.maximum.accumulate(np.where(start, np.arange(len(text)), 0))
        start |= (gaps >= 24) & ((text & 0xC0) != 0x80)  # inside very long words any character may begin an item
        return np.flatnonzero(start & (np.cumsum(near[:-1]) > 0))

    def leaks(self, texts: list[bytes]) -> list[list[tuple[int, int, int, int]]]:
        """For each normalised text: (item index or -1 - short index, edits, start, end) of every leaked item, best passage."""
        out: list[list[tuple[int, int, int, int]]] = [[] for _ in texts]
        for d, t in enumerate(texts):
            for i, (_, n) in enumerate(self.short):
                at = t.find(n)
                if at >= 0:
                    out[d].append((-1 - i, 0, at, at + len(n)))
        if not self.classes:
            return out
        docs, starts, bodies, base = [], [], [], 0
        bases = {}
        for d, t in enumerate(texts):
            if len(t) < self.q:
                continue
            a = np.frombuffer(t, np.uint8)
            p = self.places(a)
            if len(p):
                bases[d] = base
                docs.append(np.full(len(p), d))
                starts.append(p + base)
                bodies.append(t + bytes(2 * max(self.classes) + 1))
                base += len(bodies[-1])
        if not docs:
            return out
        text, doc, start = np.frombuffer(b"".join(bodies), np.uint8), np.concatenate(docs), np.concatenate(starts)
        tried: dict[tuple[int, int], list[int]] = {}
        for c in self.classes:
            entry, order = self.known[c], self.sorted[c]
            if not len(order):
                continue
            for keys in self.keys(text, start, c):
                at = np.minimum(np.searchsorted(order, keys), len(order) - 1)
                for j in np.flatnonzero(order[at] == keys).tolist():
                    for i in entry[int(keys[j])]:
                        tried.setdefault((int(doc[j]), i), []).append(int(start[j]))
        hashes: dict[int, np.ndarray] = {}
        for (d, i), spots in tried.items():
            n, e = self.items[i][1], self.edits[i]
            whole = texts[d].find(n)
            if whole >= 0:
                out[d].append((i, 0, whole, whole + len(n)))
                continue
            if d not in hashes:
                hashes[d] = windows(np.frombuffer(texts[d], np.uint8), self.q)
            own, need = self.own_grams[i], len(n) - self.q + 1 - self.q * e
            best, done = (e + 1, -1), -1
            for s in sorted(set(spots)):
                a = s - bases[d]
                if a <= done:
                    continue
                done = a + e  # the passage that was just tried covers starts up to here
                low = max(0, a - e)
                near = hashes[d][low : a + len(n) + 2 * e + 1]
                if (own[np.minimum(np.searchsorted(own, near), len(own) - 1)] == near).sum() < need:
                    continue  # too few common strings for so few edits
                got, end = edits_within(n, texts[d][low : a + len(n) + 2 * e + 1], e)
                if got < best[0]:
                    best = (got, low + end)
                if not got:
                    break
            if best[0] <= e:
                out[d].append((i, best[0], max(0, best[1] - len(n)), best[1]))
        return out


def contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id", rate: float = RATE) -> DataFrame:
    """key, item_id, edits, start and end (bytes of the normalised text) of every leak: one row for each document and item."""
    size = benchmark.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if size > ITEM_BYTES:
        raise ValueError(f"the items have {size} bytes; the broadcast holds {ITEM_BYTES}: run them in parts")
    items = Items([(r[0], r[1]) for r in benchmark.select("item_id", "text").collect()], rate)
    sent = docs.sparkSession.sparkContext.broadcast(items)
    source = docs.select(key, F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Items = sent.value
        for batch in small_batches(batches, "_text", 2 << 20):
            found = own.leaks([normal(t) for t in batch.column(1).to_pylist()])
            rows = [(d, own.items[i][0] if i >= 0 else own.short[-1 - i][0], e, a, z) for d, f in enumerate(found) for i, e, a, z in f]
            take = pa.array([r[0] for r in rows], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(take), *(pa.array([r[k] for r in rows], pa.int64()) for k in (1, 2, 3, 4))], names=[key, "item_id", "edits", "start", "end"])

    kind = docs.schema[key].dataType.simpleString()
    found = source.mapInArrow(run, f"{key} {kind}, item_id bigint, edits bigint, start bigint, end bigint")
    best = F.min(F.struct("edits", "start", "end")).alias("b")
    return found.groupBy(key, "item_id").agg(best).select(key, "item_id", "b.edits", "b.start", "b.end")


def clean_documents(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs without the rows that leak an item; a row is judged by its own doc_id and text."""
    marked = docs.withColumn("_mark", F.xxhash64(key, text))
    bad = contamination(marked, benchmark, text, "_mark").select("_mark").distinct()
    return marked.join(bad, "_mark", "left_anti").select(*docs.columns)


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {"op2_decontamination": op2_decontamination}
ORACLES: dict[str, str] = {}
