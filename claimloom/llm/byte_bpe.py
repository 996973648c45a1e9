"""Byte-level BPE encoding and decoding (operator 8), in two tiers.

Tier one: a minimal perfect hash over the vocabulary gives the id of a pre-token that is a vocabulary entry.
Tier two: other pre-tokens start as single bytes in a doubly linked list; a heap yields the adjacent pair of lowest rank
(leftmost first) until no pair is in the vocabulary. A bounded memo keeps what a worker has met.

Null and empty texts give no ids (the digests are those of zero bytes). Repeated rows are encoded each; long texts are
cut only between two non-space characters around a single blank, where no pre-token can reach across.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import small_batches, table

MEMO_ENTRIES = 600_000
SLICE_CHARS = 1 << 19


class PerfectHash:
    """Minimal perfect hash by displacement: n keys to slots 0..n-1; a slot's stored key settles membership."""

    def __init__(self, keys: list[bytes], load: int = 2):
        self.n = len(keys)
        self.buckets = max(1, -(-self.n // load))
        members: list[list[bytes]] = [[] for _ in range(self.buckets)]
        for k in keys:
            members[xxhash.xxh64_intdigest(k, 0) % self.buckets].append(k)
        self.seeds = [0] * self.buckets
        self.slots: list[bytes | None] = [None] * self.n
        order = sorted(range(self.buckets), key=lambda i: -len(members[i]))
        for b in order:
            group = members[b]
            if len(group) < 2:
                break
            seed = 1
            while True:
                at = [xxhash.xxh64_intdigest(k, seed) % self.n for k in group]
                if len(set(at)) == len(at) and all(self.slots[i] is None for i in at):
                    break
                seed += 1
            self.seeds[b] = seed
            for k, i in zip(group, at):
                self.slots[i] = k
        free = iter([i for i, k in enumerate(self.slots) if k is None])
        for b in order:
            if len(members[b]) == 1:  # a lone key takes any free slot: its seed is the slot itself, negated
                i = next(free)
                self.seeds[b], self.slots[i] = -1 - i, members[b][0]

    def slot(self, key: bytes) -> int:
        """The key's slot, or -1."""
        if not self.n:
            return -1
        seed = self.seeds[xxhash.xxh64_intdigest(key, 0) % self.buckets]
        i = -1 - seed if seed < 0 else xxhash.xxh64_intdigest(key, seed) % self.n
        return i if self.slots[i] == key else -1


class ByteBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.pattern = pattern
        self.ranks = ranks  # of the pairs that merging asks for
        self.index = PerfectHash(list(ranks))
        self.ids = [ranks[k] for k in self.index.slots]
        self.tokens: dict[int, bytes] = {i: k for k, i in ranks.items()}

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if not k.startswith("_")}

    def rank(self, piece: bytes) -> int:
        i = self.index.slot(piece)
        return self.ids[i] if i >= 0 else -1

    def merge(self, piece: bytes) -> list[int]:
        """Ids of a pre-token that is not in the vocabulary."""
        n, rank, pop, push = len(piece), self.ranks.get, heapq.heappop, heapq.heappush
        right = list(range(1, n + 1))
        left = list(range(-1, n - 1))
        end = list(range(1, n + 1))  # of the symbol that starts here; 0: merged away
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := rank(piece[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, stop = pop(heap)
            j = right[i]
            if not end[i] or j >= n or end[j] != stop or not end[j]:
                continue  # one of the two has changed since
            end[i], end[j] = stop, 0
            k = right[i] = right[j]
            if k < n:
                left[k] = i
                if (r := rank(piece[i : end[k]])) is not None:
                    push(heap, (r, i, end[k]))
            if (h := left[i]) >= 0 and (r := rank(piece[h:stop])) is not None:
                push(heap, (r, h, stop))
        out, i = [], 0
        while i < n:
            out.append(self.ranks[piece[i : end[i]]])
            i = right[i]
        return out

    def piece_ids(self, piece: bytes) -> list[int]:
        whole = self.rank(piece)
        return [whole] if whole >= 0 else self.merge(piece)

    def _ready(self) -> None:
        if not hasattr(self, "_find"):
            outer = self

            class Memo(dict):
                def __missing__(self, token: str) -> bytes:
                    if len(self) >= MEMO_ENTRIES:
                        self.clear()
                    got = self[token] = np.array(outer.piece_ids(token.encode("utf-8", "replace")), "<u4").tobytes()
                    return got

            self._find, self._memo = regex.compile(self.pattern).findall, Memo()

    def encode_packed(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        self._ready()
        return b"".join(b"".join(map(self._memo.__getitem__, self._find(part))) for part in slices(text))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_packed(text), "<u4").tolist()

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


def slices(text: str, limit: int = SLICE_CHARS) -> Iterator[str]:
    """Pieces cut in front of a single blank between two characters that are not white space."""
    start = 0
    while len(text) - start > limit:
        cut = start + limit
        while (cut := text.find(" ", cut)) > 0 and (cut + 1 >= len(text) or text[cut - 1].isspace() or text[cut + 1].isspace()):
            cut += 1
        if cut < 0:
            break
        yield text[start:cut]
        start = cut
    yield text[start:]


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def encode_decode(docs: DataFrame, codec: ByteBpe, text: str = "text", keep: tuple[str, ...] = ("doc_id",), ids: bool = False) -> DataFrame:
    """keep columns, n_tokens and the digests of ids and decoded bytes; with ids=True also the ids. The codec's size is that of its vocabulary."""
    shared = docs.sparkSession.sparkContext.broadcast(codec)
    source = docs.select(*keep, F.col(text).alias("_text"))
    width = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: ByteBpe = shared.value
        for batch in small_batches(batches, "_text", 4 << 20):
            n, id_sha, text_sha, lists = [], [], [], []
            for t in batch.column(width).to_pylist():
                packed = own.encode_packed(t or "")
                got = np.frombuffer(packed, "<u4")
                n.append(len(got))
                id_sha.append(hashlib.sha256(packed).hexdigest())
                text_sha.append(hashlib.sha256(own.decode(got.tolist())).hexdigest())
                if ids:
                    lists.append(got.astype(np.int32))
            columns = [*(batch.column(i) for i in range(width)), pa.array(n, pa.int64()), pa.array(id_sha, pa.string()), pa.array(text_sha, pa.string())]
            names = [*keep, "n_tokens", "ids_sha256", "decoded_sha256"]
            if ids:
                columns.append(pa.array(lists, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    kinds = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in keep)
    return source.mapInArrow(run, f"{kinds}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * ids)


def default_codec() -> ByteBpe:
    import public_tokenizers

    return ByteBpe(load_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken")), public_tokenizers.PATTERN)


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_decode(table(spark, sf_dir, "documents"), default_codec())


QUERIES = {"op8_byte_bpe": op8_byte_bpe}
ORACLES: dict[str, str] = {}
