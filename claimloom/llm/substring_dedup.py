"""Substring deduplication (operator 1) with suffix automata of reference shards.

Every window of `length` words that also starts elsewhere is removed, same document included; windows are judged on the
input. The reference is cut into shards of bounded size; a shard's suffix automaton counts how often each of its
substrings occurs, and text streams through it for matching statistics (the longest suffix that occurs, word by word).
Windows whose match reaches `length` words and occurs twice are taken; touching ones form maximal spans.

Sending every document past every shard would grow with the square of the corpus. `repeats` therefore first drops the
windows that cannot repeat and routes the others to the one shard that can hold their copies. With a reference of its
own and of checked size, `remove_reference` broadcasts the automata instead.

Null texts have no words. Empty and short texts keep all; repeated rows remove one another; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import as_bytes, small_batches, table
from .repeats import Repeats, normal_words, spans, word_bounds

MIN_WORDS = 35
OWNER_WORDS = 8
SHARD_WORDS = 40_000
REFERENCE_BYTES = 64 << 20


class SuffixAutomaton:
    """Generalised suffix automaton over integer sequences, with weighted occurrence counts."""

    def __init__(self):
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length, self.count = [-1], [0], [0]

    def _clone(self, p: int, q: int, c: int) -> int:
        nxt, link = self.next, self.link
        new = len(nxt)
        nxt.append(nxt[q].copy())
        link.append(link[q])
        self.length.append(self.length[p] + 1)
        self.count.append(0)
        link[q] = new
        while p >= 0 and nxt[p].get(c) == q:
            nxt[p][c] = new
            p = link[p]
        return new

    def add(self, sequence: Sequence[int], weight: int = 1) -> None:
        nxt, link, length, count = self.next, self.link, self.length, self.count
        last = 0
        for c in sequence:
            q = nxt[last].get(c)
            if q is not None:
                last = q if length[q] == length[last] + 1 else self._clone(last, q, c)
            else:
                new, p = len(nxt), last
                nxt.append({})
                length.append(length[last] + 1)
                count.append(0)
                link.append(0)
                while p >= 0 and c not in nxt[p]:
                    nxt[p][c] = new
                    p = link[p]
                if p >= 0:
                    q = nxt[p][c]
                    link[new] = q if length[q] == length[p] + 1 else self._clone(p, q, c)
                last = new
            count[last] += weight

    def close(self) -> None:
        """Sum the counts up the suffix links; no more sequences after this."""
        link, count = self.link, self.count
        for v in np.argsort(np.array(self.length), kind="stable")[:0:-1].tolist():
            count[link[v]] += count[v]

    def matches(self, sequence: Sequence[int], least: int) -> list[int]:
        """For each position, how often the `least` symbols that end there occur (0: they do not)."""
        nxt, link, length, count = self.next, self.link, self.length, self.count
        v = n = 0
        out = []
        for c in sequence:
            step = nxt[v].get(c)
            while step is None and v:
                v = link[v]
                n = length[v]
                step = nxt[v].get(c)
            if step is None:
                out.append(0)
                continue
            v, n = step, n + 1
            up = link[v]
            while length[up] >= least:  # a suffix of `least` symbols lives further up
                v = up
                n = length[v]
                up = link[v]
            out.append(count[v] if n >= least else 0)
        return out


def repeat_counts(segments: list[bytes], n_windows: np.ndarray, weights: np.ndarray, owners: np.ndarray, length: int = MIN_WORDS, shard_words: int = SHARD_WORDS) -> np.ndarray:
    """Occurrences of each window of the distinct segments, by automata over whole owner groups of about shard_words."""
    begin = np.cumsum(n_windows) - n_windows
    out = np.zeros(int(n_windows.sum()), np.int64)
    order = np.argsort(owners, kind="stable").tolist()
    group: list[int] = []
    held = 0

    def flush() -> None:
        names: dict[bytes, int] = {}
        automaton = SuffixAutomaton()
        words = {i: [names.setdefault(w, len(names)) for w in segments[i].split(b" ")] for i in group}
        for i, seq in words.items():
            automaton.add(seq, int(weights[i]))
        automaton.close()
        for i, seq in words.items():
            out[begin[i] : begin[i] + n_windows[i]] = automaton.matches(seq, length)[length - 1 :]

    for at, i in enumerate(order):
        group.append(i)
        held += int(n_windows[i]) + length - 1
        if held >= shard_words and (at + 1 == len(order) or owners[order[at + 1]] != owners[i]):
            flush()
            group, held = [], 0
    if group:
        flush()
    return out


def repeated_words(docs: DataFrame, text: str = "text", key: str = "doc_id", length: int = MIN_WORDS, k: int = OWNER_WORDS, **sizes) -> DataFrame:
    """key, n (words), spans (removed word runs) and kept (text of the words that stay) of every row."""

    def decide(segments, n_windows, weights, owners):
        return repeat_counts(segments, n_windows, weights, owners, length)

    how = Repeats(length=length, k=min(k, length), words=True, by_order=False, decide=decide, **sizes)
    return spans(docs, how, text, key).withColumn("kept", F.col("kept").cast("string"))


def remove_reference(docs: DataFrame, reference: list[bytes], text: str = "text", key: str = "doc_id", length: int = MIN_WORDS) -> DataFrame:
    """key, n (words) and spans (word runs that occur in the reference): its automata, of checked size, are broadcast."""
    if (size := sum(map(len, reference))) > REFERENCE_BYTES:
        raise ValueError(f"the reference has {size} bytes; over {REFERENCE_BYTES} use repeated_words on the union")
    shards: list[tuple[dict[bytes, int], SuffixAutomaton]] = []
    for at, t in enumerate(reference):
        if not shards or len(shards[-1][1].next) > 2 * SHARD_WORDS:
            shards.append(({}, SuffixAutomaton()))
        names, automaton = shards[-1]
        automaton.add([names.setdefault(w, len(names)) for w in normal_words(t).split(b" ") if w])
    for _, automaton in shards:
        automaton.close()
    sent = docs.sparkSession.sparkContext.broadcast(shards)
    source = docs.select(key, F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_text"):
            n, starts, ends = [], [], []
            for t in as_bytes(batch.column(1)):
                normal = normal_words(t)
                words = normal.split(b" ") if normal else []
                hit = np.zeros(len(words) + 1, np.int64)
                for names, automaton in sent.value:
                    for i, c in enumerate(automaton.matches([names.get(w, -1) for w in words], length)):
                        if c:
                            hit[i + 1 - length] += 1
                            hit[i + 1] -= 1
                edge = np.flatnonzero(np.diff(np.concatenate([[0], np.cumsum(hit[:-1]) > 0, [0]]).astype(np.int8)))
                n.append(len(words))
                starts.append(edge[::2].tolist())
                ends.append(edge[1::2].tolist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(starts, pa.list_(pa.int64())), pa.array(ends, pa.list_(pa.int64()))], names=[key, "n", "_a", "_z"])

    kind = docs.schema[key].dataType.simpleString()
    out = source.mapInArrow(run, f"{key} {kind}, n bigint, _a array<bigint>, _z array<bigint>")
    return out.select(key, "n", F.arrays_zip(F.col("_a").alias("start"), F.col("_z").alias("end")).alias("spans"))


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_words(table(spark, sf_dir, "documents"))
    removed = F.aggregate("spans", F.lit(0).cast("bigint"), lambda n, s: n + s["end"] - s["start"])
    return found.select("doc_id", F.col("n").alias("n_words"), removed.alias("n_removed"), F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


QUERIES = {"op1_substring_dedup": op1_substring_dedup}
ORACLES = {
    "op1_substring_dedup": """
WITH d AS (
  SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS ws FROM documents
), win AS (
  SELECT doc_id, p, array_to_string(ws[p:p + 34], ' ') AS body
  FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 33)) AS p FROM d WHERE len(ws) >= 35)
), twice AS (
  SELECT body FROM win GROUP BY body HAVING count(*) > 1
), starts AS (
  SELECT doc_id, list(p) AS ps FROM win SEMI JOIN twice USING (body) GROUP BY doc_id
), cover AS (
  SELECT DISTINCT doc_id, i FROM (SELECT doc_id, unnest(range(p, p + 35)) AS i FROM (SELECT doc_id, unnest(ps) AS p FROM starts))
), word AS (
  SELECT doc_id, i, ws[i] AS w FROM (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS i FROM d)
), kept AS (
  SELECT doc_id, string_agg(w, ' ' ORDER BY i) AS t, count(*) AS n FROM word ANTI JOIN cover USING (doc_id, i) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.ws) AS BIGINT) AS n_words, CAST(len(d.ws) - coalesce(kept.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept.t, '')) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)
"""
}
