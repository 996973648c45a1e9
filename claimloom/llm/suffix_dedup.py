"""Suffix-array deduplication (operator 5) with a logarithmic family of indexes.

A batch of text gets a suffix array (suffixes compared over their first `length` bytes). It is merge-scanned against the
levels of the family for matches of `length` bytes, and what is new becomes a level; levels of about equal size merge, so
a family of n suffixes has O(log n) levels and each suffix is moved O(log n) times. Batches come in document order, so
the family knows for each string the first document it starts in, and a later document loses the bytes it covers.

`repeats` routes strings that may occur twice to shards, each with a family of its own; matches never cross documents.
Null texts are empty. Bytes are judged on the input; rows of one doc_id do not remove each other's bytes; rows without a
doc_id come after all others. Other columns are not read.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import table
from .repeats import Repeats, spans

MIN_BYTES = 50
OWNER_BYTES = 16
BATCH = 1 << 16
SHARD_BYTES = 1 << 20
FAMILY_WINDOWS = 1 << 19


class SuffixFamily:
    """Levels of sorted strings of `length` bytes, each with the smallest order it came with."""

    def __init__(self, length: int = MIN_BYTES):
        self.length = length
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, text: np.ndarray, starts: np.ndarray, orders: np.ndarray) -> np.ndarray:
        """The smallest order with which each string text[start:start+length] has come, this batch included."""
        if not len(starts):
            return np.empty(0, np.int64)
        view = np.lib.stride_tricks.sliding_window_view(text, self.length)
        keys = np.ascontiguousarray(view[starts]).view(f"S{self.length}").ravel()
        array = np.argsort(keys)  # the batch's suffix array, over its chosen suffixes
        ordered = keys[array]
        head = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
        distinct, first = ordered[head], np.minimum.reduceat(orders[array], head)
        new = np.ones(len(distinct), bool)
        for known, since in self.levels:  # merge-scan: sorted strings against a sorted level
            at = np.minimum(np.searchsorted(known, distinct), len(known) - 1)
            met = known[at] == distinct
            first[met] = np.minimum(first[met], since[at[met]])
            since[at[met]] = first[met]
            new &= ~met
        out = np.empty(len(keys), np.int64)
        out[array] = np.repeat(first, np.diff(np.append(head, len(ordered))))
        if new.any():
            self.levels.append((distinct[new], first[new]))
        while len(self.levels) > 1 and len(self.levels[-2][0]) < 2 * len(self.levels[-1][0]):
            (a, x), (b, y) = self.levels.pop(), self.levels.pop()
            place = np.searchsorted(b, a) + np.arange(len(a))
            keys, since = np.empty(len(a) + len(b), a.dtype), np.empty(len(a) + len(b), np.int64)
            rest = np.ones(len(keys), bool)
            rest[place] = False
            keys[place], since[place], keys[rest], since[rest] = a, x, b, y
            self.levels.append((keys, since))
        return out


def first_orders(segments: list[bytes], n_windows: np.ndarray, orders: np.ndarray, length: int = MIN_BYTES, batch: int = BATCH) -> np.ndarray:
    """For each window of the segments, the smallest order of a segment that has it."""
    begin = np.cumsum(n_windows) - n_windows
    out = np.zeros(int(n_windows.sum()), np.int64)
    family = SuffixFamily(length)
    line = np.argsort(orders, kind="stable")
    cuts = np.searchsorted(np.cumsum(n_windows[line]), np.arange(batch, out.size + batch, batch))
    for a, z in zip([0, *(cuts[:-1] + 1).tolist()], [*(cuts[:-1] + 1).tolist(), len(line)]):
        pick = line[a:z]
        if not len(pick):
            continue
        bodies = [segments[i] for i in pick.tolist()]
        size = np.fromiter(map(len, bodies), np.int64, len(bodies))
        n = n_windows[pick]
        rank = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        found = family.add(np.frombuffer(b"".join(bodies), np.uint8), np.repeat(np.cumsum(size) - size, n) + rank, np.repeat(orders[pick], n))
        out[np.repeat(begin[pick], n) + rank] = found
    return out


def by_owner(segments: list[bytes], n_windows: np.ndarray, orders: np.ndarray, owners: np.ndarray, length: int = MIN_BYTES, most: int = FAMILY_WINDOWS) -> np.ndarray:
    """first_orders with a new family for every `most` windows or so; strings of different owners never match."""
    begin = np.cumsum(n_windows) - n_windows
    out = np.empty(int(n_windows.sum()), np.int64)
    line = np.argsort(owners, kind="stable")
    held = np.cumsum(n_windows[line])
    a = 0
    while a < len(line):
        z = int(np.searchsorted(held, (held[a - 1] if a else 0) + most)) + 1
        while z < len(line) and owners[line[z]] == owners[line[z - 1]]:
            z += 1
        pick = line[a:z]
        n = n_windows[pick]
        rank = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat(begin[pick], n) + rank] = first_orders([segments[i] for i in pick.tolist()], n, orders[pick], length)
        a = z
    return out


def repeated_bytes(docs: DataFrame, text: str = "text", key: str = "doc_id", length: int = MIN_BYTES, k: int = OWNER_BYTES, **sizes) -> DataFrame:
    """key, n (bytes), spans (removed byte runs) and kept (the other bytes) of every row."""

    def decide(segments, n_windows, orders, owners):
        return by_owner(segments, n_windows, orders, owners, length)

    how = Repeats(**{"length": length, "k": min(k, length), "words": False, "by_order": True, "decide": decide, "shard_bytes": SHARD_BYTES} | sizes)
    return spans(docs, how, text, key)


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_bytes(table(spark, sf_dir, "documents"))
    removed = F.aggregate("spans", F.lit(0).cast("bigint"), lambda n, s: n + s["end"] - s["start"])
    return found.select("doc_id", F.col("n").alias("n_bytes"), removed.alias("n_removed"), F.size("spans").cast("bigint").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


QUERIES = {"op5_suffix_dedup": op5_suffix_dedup}
ORACLES = {
    "op5_suffix_dedup": """
WITH d AS (
  SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents
), piece AS (
  SELECT doc_id, k * 200 AS base, h[400 * k + 1:400 * k + 498] AS s FROM (SELECT doc_id, h, unnest(range(0, (len(h) // 2 + 199) // 200)) AS k FROM d)
), win AS (
  SELECT doc_id, base + j AS p, md5(s[2 * j + 1:2 * j + 100]) AS body FROM (SELECT doc_id, base, s, unnest(range(0, least(200, len(s) // 2 - 49))) AS j FROM piece WHERE len(s) >= 100)
), firsts AS (
  SELECT body, min(doc_id) AS m FROM win GROUP BY body HAVING min(doc_id) < max(doc_id)
), hit AS (
  SELECT doc_id, p FROM win JOIN firsts USING (body) WHERE m < doc_id
), byte AS (
  SELECT doc_id, base + j AS i, s[2 * j + 1:2 * j + 2] AS b
  FROM (SELECT doc_id, base, s, unnest(range(0, least(200, len(s) // 2))) AS j FROM piece SEMI JOIN hit USING (doc_id))
), marked AS (
  SELECT byte.doc_id, i, b, max(hit.p) OVER (PARTITION BY byte.doc_id ORDER BY i ROWS BETWEEN 49 PRECEDING AND CURRENT ROW) IS NOT NULL AS gone
  FROM byte LEFT JOIN hit ON hit.doc_id = byte.doc_id AND hit.p = byte.i
), runs AS (
  SELECT doc_id, count(*) FILTER (WHERE gone) AS n, count(*) FILTER (WHERE gone AND NOT coalesce(before, false)) AS s,
    coalesce(string_agg(b, '' ORDER BY i) FILTER (WHERE NOT gone), '') AS t
  FROM (SELECT *, lag(gone) OVER (PARTITION BY doc_id ORDER BY i) AS before FROM marked) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(runs.n, 0) AS BIGINT) AS n_removed, CAST(coalesce(runs.s, 0) AS BIGINT) AS n_spans,
  sha256(unhex(coalesce(runs.t, d.h))) AS kept_sha256
FROM d LEFT JOIN runs USING (doc_id)
"""
}
