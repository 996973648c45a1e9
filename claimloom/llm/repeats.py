"""Routing that brings together every passage of `length` symbols that may occur twice, for operators 1 and 5.

A passage (window) is owned by the smallest of the k-symbol hashes inside it, the rightmost on ties. Equal windows have
equal owners, so a window can only repeat if its owner's hash does. The windows of one owner are consecutive; together
they are a segment. Five steps, each a group of bounded size:

1. documents are dealt into chunks; each chunk sends its distinct owner hashes to buckets;
2. a bucket finds the hashes that several chunks sent and answers each chunk with bits;
3. a chunk sends the segments of repeated owners, equal ones once, to the shard of the owner's hash;
4. a shard decides each window (suffix automaton, suffix arrays: the operator's method) and answers the chunks;
5. a chunk turns the answers into spans.

Owners that very many chunks hold would fill one shard: their windows get owners anew, by longer hashes, and go in
shorter segments to the shards of those. All steps recompute the same from a chunk's rows, so lost executors
cost only their tasks. What is sent is packed and compressed, documents too; they are dealt once and that exchange is reused.
A message is what one chunk sends to one shard. Beyond VOLUME chunks and shards grow, so that messages keep their size.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import as_bytes, safe_slices, small_batches, text_volume
from .rolling import mix, windows

CHUNK_BYTES = 4 << 20
LARGEST_CHUNK = 64 << 20
LARGEST_SHARD = 3 << 20
VOLUME = 2 << 30
BUCKET_ENTRIES = 1 << 20
SHARD_BYTES = 3 << 20
HOT_CHUNKS = 1000
LAST = np.iinfo(np.int64).max
_BLOCK_BITS = 18
_U = np.uint64

Decider = Callable[[list[bytes], np.ndarray, np.ndarray, np.ndarray], np.ndarray]


@dataclass(frozen=True)
class Repeats:
    """length: symbols of a window; k: symbols of an owner; words: symbols are words, else bytes.

    decide(segments, window counts, weights, owners) gives a number for each window of the distinct segments; weights
    are occurrences (by_order False: a window is taken if its number is 2 or more) or the smallest document order
    (by_order True: taken if its number is below the order of the document).
    """

    length: int
    k: int
    words: bool
    by_order: bool
    decide: Decider
    hot_chunks: int = HOT_CHUNKS
    chunk_bytes: int = CHUNK_BYTES
    shard_bytes: int = SHARD_BYTES
    bucket_entries: int = BUCKET_ENTRIES


def normal_words(text: bytes) -> bytes:
    """The words of a text (between ASCII white space) joined by one blank."""
    return b" ".join(y for x in safe_slices(text) if (y := b" ".join(x.split())))


def word_bounds(normal: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words of a text whose words one blank separates."""
    if not normal:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    blanks = np.flatnonzero(np.frombuffer(normal, np.uint8) == 32)
    return np.concatenate([[0], blanks + 1]), np.concatenate([blanks, [len(normal)]])


def word_symbols(normal: bytes, starts: np.ndarray, ends: np.ndarray, block: int = 1 << 16) -> np.ndarray:
    """A 64-bit hash of each word."""
    out = np.empty(len(starts), np.uint64)
    b = np.frombuffer(normal, np.uint8)
    with np.errstate(over="ignore"):
        for at in range(0, len(starts), block):
            s, e = starts[at : at + block], ends[at : at + block]
            base, lens = int(s[0]), e - s
            part = b[base : int(e[-1]) + 1].astype(np.uint64)
            part += _U(0x9E3779B97F4A7C15)
            spread = np.arange(len(part), dtype=np.uint64)
            spread -= np.repeat((s - base).astype(np.uint64), np.append(np.diff(s), len(part) - (int(s[-1]) - base)))
            spread += _U(1)
            spread *= _U(0xD6E8FEB86659FD93)
            part *= spread
            part ^= part >> _U(29)
            part *= _U(0xBF58476D1CE4E5B9)
            inside = e - base < len(part)
            part[(e - base)[inside]] = 0
            out[at : at + block] = mix(np.add.reduceat(part, s - base) + lens.astype(np.uint64))
    return out


def owners(symbols: np.ndarray, length: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(owner hash, first window, window count) of every segment, in order; the segments tile all windows."""
    total = len(symbols) - length + 1
    if total <= 0:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    g, w = windows(symbols, k), length - k + 1
    hashes, firsts, counts = [], [], []
    low = _U((1 << _BLOCK_BITS) - 1)
    step = (1 << _BLOCK_BITS) - w
    for at in range(0, total, step):
        n = min(step, total - at)
        part = g[at : at + n + w - 1]
        v = part & ~low
        v |= low - np.arange(len(part), dtype=np.uint64)
        span = 1
        while span < w:
            jump = min(span, w - span)
            v = np.minimum(v[: len(v) - jump], v[jump:])
            span += jump
        own = (low - (v & low)).astype(np.int64)
        turn = np.concatenate([[0], np.flatnonzero(np.diff(own)) + 1])
        hashes.append(part[own[turn]])
        firsts.append(turn + at)
        counts.append(np.diff(np.append(turn, n)))
    return np.concatenate(hashes), np.concatenate(firsts), np.concatenate(counts)


def _scaled(h: np.ndarray, parts: int) -> np.ndarray:
    """Hashes to 0..parts-1, in their order."""
    return (((h >> _U(32)) * _U(parts)) >> _U(32)).astype(np.int64)


def _pack(*arrays: np.ndarray | bytes) -> tuple[int, bytes]:
    raw = b"".join(x if isinstance(x, bytes) else np.ascontiguousarray(x).tobytes() for x in arrays)
    return len(raw), pa.compress(raw, codec="zstd", asbytes=True)


def _unpack(row: dict) -> bytes:
    return pa.decompress(row["payload"], row["size"], codec="zstd", asbytes=True)


def _give_back() -> None:
    """Hand freed memory back after a group: a worker lives through many of them."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library


def _grouped(step: Callable[[pa.Table], pa.Table]) -> Callable[[pa.Table], pa.Table]:
    def run(table: pa.Table) -> pa.Table:
        out = step(table)
        _give_back()
        return out

    return run


def _paired(step: Callable[[pa.Table, pa.Table], pa.Table]) -> Callable[[pa.Table, pa.Table], pa.Table]:
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out = step(left, right)
        _give_back()
        return out

    return run


_DEALT = pa.schema([("chunk", pa.int64()), ("n", pa.int64()), ("size", pa.int64()), ("payload", pa.binary())])
_DEALT_SQL = "chunk bigint, n bigint, size bigint, payload binary"


def _dealt(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (chunk, key, text) of a batch as one packed row for each chunk: its keys, which of them are null, lengths and texts."""
    for batch in small_batches(batches, "_text", 16 << 20):
        chunk = batch.column(0).to_numpy(zero_copy_only=False)
        keys = batch.column(1)
        null = keys.is_null().to_numpy(zero_copy_only=False).astype(np.uint8)
        keys = pa.compute.fill_null(keys, 0).to_numpy(zero_copy_only=False)
        texts = as_bytes(batch.column(2))
        order = np.argsort(chunk, kind="stable")
        rows = []
        for at in np.split(order, np.flatnonzero(np.diff(chunk[order])) + 1):
            if len(at):
                own = [texts[i] for i in at.tolist()]
                lens = np.fromiter(map(len, own), np.int64, len(own))
                rows.append(dict(zip(_DEALT.names, (int(chunk[at[0]]), len(at), *_pack(keys[at], null[at], lens, b"".join(own))))))
        yield from pa.Table.from_pylist(rows, _DEALT).to_batches()
        del keys, texts, rows
        _give_back()


def _undealt(table: pa.Table) -> tuple[list[int | None], list[bytes]]:
    keys, texts = [], []
    for row in table.to_pylist():
        raw, n = _unpack(row), row["n"]
        null = np.frombuffer(raw, np.uint8, n, 8 * n).tolist()
        keys += [None if x else k for k, x in zip(np.frombuffer(raw, np.int64, n).tolist(), null)]
        start = 17 * n
        for size in np.frombuffer(raw, np.int64, n, 9 * n).tolist():
            texts.append(raw[start : start + size])
            start += size
    return keys, texts


_SENT = pa.schema([("dest", pa.int64()), ("chunk", pa.int64()), ("first", pa.int64()), ("n", pa.int64()), ("size", pa.int64()), ("payload", pa.binary())])
_SENT_SQL = "dest bigint, chunk bigint, first bigint, n bigint, size bigint, payload binary"


class _Chunk:
    """A chunk's documents in a fixed order, with their symbols and segments."""

    def __init__(self, table: pa.Table, how: Repeats):
        keys, texts = _undealt(table)
        orders = [LAST if x is None else x for x in keys]
        self.at = sorted(range(len(texts)), key=lambda i: (orders[i], texts[i]))
        self.keys = [keys[i] for i in self.at]
        self.orders = np.array([orders[i] for i in self.at], np.int64)
        self.how = how
        self.texts = [normal_words(texts[i]) if how.words else texts[i] for i in self.at]

    def bounds(self, i: int) -> tuple[np.ndarray, np.ndarray] | None:
        return word_bounds(self.texts[i]) if self.how.words else None

    def symbols(self, i: int, bounds) -> np.ndarray:
        return word_symbols(self.texts[i], *bounds) if self.how.words else np.frombuffer(self.texts[i], np.uint8)

    def segments(self) -> None:
        how = self.how
        parts = [owners(self.symbols(i, self.bounds(i)), how.length, how.k) if len(t) >= how.length else None for i, t in enumerate(self.texts)]
        none = np.empty(0, np.int64)
        held = [(i, p) for i, p in enumerate(parts) if p is not None]
        self.hash = np.concatenate([p[0] for _, p in held] or [np.empty(0, np.uint64)])
        self.first = np.concatenate([p[1] for _, p in held] or [none])
        self.count = np.concatenate([p[2] for _, p in held] or [none])
        self.doc = np.repeat(np.array([i for i, _ in held], np.int64), [len(p[0]) for _, p in held]) if held else none


def _buckets(n_symbols: int, how: Repeats) -> int:
    return max(1, -(-2 * n_symbols // ((how.length - how.k + 2) * how.bucket_entries)))


def _sizes(volume: int, how: Repeats) -> tuple[int, int]:
    """Bytes of a chunk and of a shard: as given up to VOLUME, then their product grows with the volume."""
    more = max(1.0, volume / VOLUME)
    return (
        min(int(how.chunk_bytes * more ** (1 / 3)), max(LARGEST_CHUNK, how.chunk_bytes)),
        min(int(how.shard_bytes * more ** (2 / 3)), max(LARGEST_SHARD, how.shard_bytes)),
    )


def spans(docs: DataFrame, how: Repeats, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, n (symbols), spans (maximal removed runs, half-open, in symbols) and kept (the rest as bytes) of every row.

    Null texts are empty; empty and short texts keep all. Rows without a key count as later than all others. Repeated
    rows are rows of their own. The key is a bigint; other columns are not read.
    """
    _, volume = text_volume(docs, text)
    chunk_bytes, shard_bytes = _sizes(volume, how)
    chunks, shards = max(1, -(-volume // chunk_bytes)), max(1, -(-volume // shard_bytes))
    buckets = _buckets(volume // (6 if how.words else 1), how)
    dealt = docs.select(F.pmod(F.xxhash64(key, text), F.lit(chunks)).alias("chunk"), F.col(key).cast("bigint").alias("_key"), F.col(text).alias("_text")).mapInArrow(_dealt, _DEALT_SQL)

    def ask(table: pa.Table) -> pa.Table:
        c = _Chunk(table, how)
        c.segments()
        u = np.unique(c.hash)
        edges = np.searchsorted(_scaled(u, buckets), np.arange(buckets + 1))
        me = table.column(0)[0].as_py()
        rows = [(int(b), me, 0, int(z - a), *_pack((u[a:z] & _U(0xFFFFFFFF)).astype(np.uint32))) for b, (a, z) in enumerate(zip(edges[:-1], edges[1:])) if z > a]
        return pa.Table.from_pylist([dict(zip(_SENT.names, r)) for r in rows], _SENT)

    def answer(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        blobs = [np.frombuffer(_unpack(r), np.uint32) for r in rows]
        every = np.concatenate(blobs)
        order = np.argsort(every, kind="stable")
        ordered = every[order]
        new = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
        times = np.repeat(np.diff(np.append(new, len(ordered))), np.diff(np.append(new, len(ordered))))
        level = np.empty(len(every), np.uint8)
        level[order] = (times > 1).astype(np.uint8) + (times > how.hot_chunks)
        out, at = [], 0
        for r, b in zip(rows, blobs):
            part = level[at : at + len(b)]
            at += len(b)
            out.append(dict(zip(_SENT.names, (r["dest"], r["chunk"], 0, len(b), *_pack(np.packbits(part > 0), np.packbits(part > 1))))))
        return pa.Table.from_pylist(out, _SENT)

    def send(table: pa.Table, answers: pa.Table) -> pa.Table:
        c = _Chunk(table, how)
        c.segments()
        me = table.column(0)[0].as_py()
        u, inverse, times = np.unique(c.hash, return_inverse=True, return_counts=True)
        edges = np.searchsorted(_scaled(u, buckets), np.arange(buckets + 1))
        taken, hot = times > 1, np.zeros(len(u), bool)
        for r in answers.to_pylist():
            a, n, raw = edges[r["dest"]], r["n"], np.frombuffer(_unpack(r), np.uint8)
            half = len(raw) // 2
            taken[a : a + n] |= np.unpackbits(raw[:half], count=n).astype(bool)
            hot[a : a + n] = np.unpackbits(raw[half:], count=n)
        chosen = np.flatnonzero(taken[inverse])
        route, is_hot = c.hash[chosen], hot[inverse[chosen]]
        doc, first, count = c.doc[chosen], c.first[chosen], c.count[chosen]
        if is_hot.any():  # their windows travel in segments of longer owners
            parts = [(route[~is_hot], doc[~is_hot], first[~is_hot], count[~is_hot])]
            for d in np.unique(doc[is_hot]).tolist():
                at = np.flatnonzero(is_hot & (doc == d))
                h, starts, _ = owners(c.symbols(d, c.bounds(d)), how.length, how.length - (how.length - how.k) // 3)
                w = np.repeat(first[at] - (np.cumsum(count[at]) - count[at]), count[at]) + np.arange(count[at].sum())
                own = np.searchsorted(starts, w, side="right") - 1
                cut = np.flatnonzero(np.concatenate([[True], (np.diff(own) != 0) | (np.diff(w) != 1)]))
                parts.append((h[own[cut]], np.full(len(cut), d), w[cut], np.diff(np.append(cut, len(w)))))
            route, doc, first, count = (np.concatenate(x) for x in zip(*parts))
            line = np.lexsort((first, doc))
            route, doc, first, count = route[line], doc[line], first[line], count[line]
        known: dict[bytes, int] = {}
        ids = np.empty(len(doc), np.int64)
        bodies: list[bytes] = []
        last = first + count + how.length - 1
        ends = np.flatnonzero(np.diff(doc)) + 1
        for a, z in zip([0, *ends.tolist()], [*ends.tolist(), len(doc)]):
            if a == z:
                continue
            d = int(doc[a])
            t = c.texts[d]
            lo, hi = first[a:z], last[a:z]
            if how.words:
                ws, we = c.bounds(d)
                lo, hi = ws[lo], we[hi - 1]
            for j, x, y in zip(range(a, z), lo.tolist(), hi.tolist()):
                body = t[x:y]
                i = known.setdefault(body, len(bodies))
                if i == len(bodies):
                    bodies.append(body)
                ids[j] = i
        n = len(bodies)
        weight = np.full(n, LAST, np.int64) if how.by_order else np.bincount(ids, minlength=n).astype(np.int64)
        if how.by_order:
            np.minimum.at(weight, ids, c.orders[doc])
        some = np.zeros(n, np.int64)
        some[ids] = np.arange(len(ids))
        route, own_count = route[some] if n else np.empty(0, np.uint64), count[some] if n else np.empty(0, np.int64)
        shard = _scaled(route, shards)
        order = np.argsort(route, kind="stable")  # shards come in the order of their hashes
        # Inside a shard the next 16 bits tell owners apart well enough: owners that share them only share a group.
        inside = (((route >> _U(32)) * _U(shards) & _U(0xFFFFFFFF)) >> _U(16)).astype(np.uint16)
        place = np.empty(n, np.int64)
        place[order] = np.arange(n)
        cuts = np.searchsorted(shard[order], np.arange(shards + 1))
        out = []
        for s in np.flatnonzero(np.diff(cuts)).tolist():
            pick = order[cuts[s] : cuts[s + 1]]
            texts = [bodies[i] for i in pick.tolist()]
            lens = np.fromiter(map(len, texts), np.uint32, len(texts))
            out.append((s, me, int(cuts[s]), len(texts), *_pack(weight[pick], own_count[pick].astype(np.uint32), lens, inside[pick], b"".join(texts))))
        if len(ids):
            gap = first - np.append(0, (first + count)[:-1])  # mostly none: neighbours
            out.append((-1 - me, me, n, len(ids), *_pack(gap.astype(np.int64), place[ids].astype(np.uint32), doc.astype(np.uint32), count.astype(np.uint32))))
        return pa.Table.from_pylist([dict(zip(_SENT.names, r)) for r in out], _SENT)

    def settle(table: pa.Table) -> pa.Table:
        if table.column(0)[0].as_py() < 0:
            return table
        rows = table.to_pylist()
        known: dict[bytes, int] = {}
        routes, weights, counts, ids, bodies = [], [], [], [], []
        for r in rows:
            raw, n = _unpack(r), r["n"]
            weights.append(np.frombuffer(raw, np.int64, n))
            counts.append(np.frombuffer(raw, np.uint32, n, 8 * n).astype(np.int64))
            routes.append(np.frombuffer(raw, np.uint16, n, 16 * n))
            ends = np.cumsum(np.frombuffer(raw, np.uint32, n, 12 * n).astype(np.int64)) + 18 * n
            own, start = [], 18 * n
            for end in ends.tolist():
                body = raw[start:end]
                start = end
                i = known.setdefault(body, len(bodies))
                if i == len(bodies):
                    bodies.append(body)
                own.append(i)
            ids.append(np.array(own, np.int64))
        every = np.concatenate(ids)
        weight = np.full(len(bodies), LAST, np.int64) if how.by_order else np.zeros(len(bodies), np.int64)
        (np.minimum if how.by_order else np.add).at(weight, every, np.concatenate(weights))
        count, route = np.zeros(len(bodies), np.int64), np.zeros(len(bodies), np.uint64)
        count[every], route[every] = np.concatenate(counts), np.concatenate(routes)
        del known
        number = how.decide(bodies, count, weight, route)
        begin = np.cumsum(count) - count
        out = []
        for r, own, w in zip(rows, ids, weights):
            n = count[own]
            at = np.repeat(begin[own] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            bits = number[at] < np.repeat(w, n) if how.by_order else number[at] >= 2
            out.append(dict(zip(_SENT.names, (r["dest"], r["chunk"], r["first"], r["n"], *_pack(np.packbits(bits))))))
        return pa.Table.from_pylist(out, _SENT)

    def finish(table: pa.Table, sent: pa.Table) -> pa.Table:
        c = _Chunk(table, how)
        rows = sent.to_pylist()
        taken_doc = taken_at = np.empty(0, np.int64)
        home = [r for r in rows if r["dest"] < 0]
        if home:
            raw, n, m = _unpack(home[0]), home[0]["n"], home[0]["first"]
            ids = np.frombuffer(raw, np.uint32, n, 8 * n).astype(np.int64)
            doc = np.frombuffer(raw, np.uint32, n, 12 * n).astype(np.int64)
            count = np.frombuffer(raw, np.uint32, n, 16 * n).astype(np.int64)
            first = np.cumsum(np.frombuffer(raw, np.int64, n) + count) - count
            own_count, weight = np.empty(m, np.int64), np.full(m, LAST, np.int64)
            own_count[ids] = count
            np.minimum.at(weight, ids, c.orders[doc])
            begin = np.concatenate([[0], np.cumsum(own_count)])
            bits = np.zeros(begin[-1], bool)
            for r in rows:
                if r["dest"] >= 0:
                    a, z = begin[r["first"]], begin[r["first"] + r["n"]]
                    bits[a:z] = np.unpackbits(np.frombuffer(_unpack(r), np.uint8), count=z - a)
            rank = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
            flag = bits[np.repeat(begin[ids], count) + rank]
            if how.by_order:
                flag |= np.repeat(c.orders[doc] > weight[ids], count)
            taken_doc, taken_at = np.repeat(doc, count)[flag], (np.repeat(first, count) + rank)[flag]
            order = np.argsort(taken_doc, kind="stable")
            taken_doc, taken_at = taken_doc[order], taken_at[order]
        edges = np.searchsorted(taken_doc, np.arange(len(c.texts) + 1))
        sizes, starts, stops, kept = [], [], [], []
        for i, t in enumerate(c.texts):
            bounds = c.bounds(i)
            n = len(bounds[0]) if how.words else len(t)
            sizes.append(n)
            if edges[i] == edges[i + 1]:
                starts.append([])
                stops.append([])
                kept.append(t)
                continue
            change = np.zeros(n + 1, np.int64)
            at = taken_at[edges[i] : edges[i + 1]]
            np.add.at(change, at, 1)
            np.add.at(change, at + how.length, -1)
            edge = np.flatnonzero(np.diff(np.concatenate([[0], np.cumsum(change[:-1]) > 0, [0]]).astype(np.int8)))
            a, z = edge[::2], edge[1::2]
            starts.append(a.tolist())
            stops.append(z.tolist())
            keep = [(x, y) for x, y in zip([0, *z.tolist()], [*a.tolist(), n]) if y > x]
            kept.append(b" ".join(t[bounds[0][x] : bounds[1][y - 1]] for x, y in keep) if how.words else b"".join(t[x:y] for x, y in keep))
        return pa.table(
            [pa.array(c.keys, pa.int64()), pa.array(sizes, pa.int64()), pa.array(starts, pa.list_(pa.int64())), pa.array(stops, pa.list_(pa.int64())), pa.array(kept, pa.binary())],
            names=["_key", "n", "_a", "_z", "kept"],
        )

    by_chunk = dealt.groupBy("chunk")
    answers = by_chunk.applyInArrow(_grouped(ask), _SENT_SQL).groupBy("dest").applyInArrow(_grouped(answer), _SENT_SQL)
    sent = by_chunk.cogroup(answers.groupBy("chunk")).applyInArrow(_paired(send), _SENT_SQL)
    settled = sent.groupBy("dest").applyInArrow(_grouped(settle), _SENT_SQL)
    done = by_chunk.cogroup(settled.groupBy("chunk")).applyInArrow(_paired(finish), "_key bigint, n bigint, _a array<bigint>, _z array<bigint>, kept binary")
    return done.select(F.col("_key").alias(key), "n", F.arrays_zip(F.col("_a").alias("start"), F.col("_z").alias("end")).alias("spans"), "kept")
