"""Token counts (operator 6): lengths only, from Arrow batches.

The tokenizers library drops white space and never merges across it, so the count of a text is the sum over its
pieces between ASCII white space. Pieces that the worker has not met are encoded together, in lists balanced by bytes;
their lengths are kept in a memo of bounded size. Long texts are cut at white space only.

Null and empty texts count 0 tokens and 0 bytes; repeated rows are counted each; other columns are not read.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import as_bytes, safe_slices, small_batches, table

MEMO_ENTRIES = 600_000
BATCH_BYTES = 64 << 10

_memos: dict[str, tuple[object, dict[bytes, int]]] = {}


def _loaded(definition: str) -> tuple[object, dict[bytes, int]]:
    """One tokenizer and memo for each Python worker and tokenizer definition."""
    key = str(hash(definition))
    if key not in _memos:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        tok = Tokenizer.from_str(definition)
        tok.no_truncation()
        tok.no_padding()
        _memos[key] = (tok, {})
    return _memos[key]


def _balanced(pieces: list[bytes], limit: int = BATCH_BYTES) -> Iterator[list[bytes]]:
    group: list[bytes] = []
    held = 0
    for p in pieces:
        if group and held + len(p) > limit:
            yield group
            group, held = [], 0
        group.append(p)
        held += len(p)
    if group:
        yield group


def _learn(tok, memo: dict[bytes, int], pieces: set[bytes]) -> None:
    encode = getattr(tok, "encode_batch_fast", tok.encode_batch)
    for group in _balanced(sorted(pieces, key=len)):
        for piece, enc in zip(group, encode([p.decode("utf-8", "replace") for p in group], add_special_tokens=False)):
            memo[piece] = len(enc)


def counts(texts: list[bytes], definition: str) -> list[int]:
    tok, memo = _loaded(definition)
    out = []
    for text in texts:
        n = 0
        for part in safe_slices(text):
            words = part.split()
            new = set(words).difference(memo)
            if new:
                if len(memo) + len(new) > MEMO_ENTRIES:
                    memo.clear()
                    new = set(words)
                _learn(tok, memo, new)
            n += sum(map(memo.__getitem__, words))
        out.append(n)
    return out


def count_tokens(docs: DataFrame, definition: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), limit: int = 2048) -> DataFrame:
    """keep columns, n_bytes, n_tokens and over_limit of every row; definition: the tokenizer's JSON (a few MB at most)."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(definition)
    source = docs.select(*keep, F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_text"):
            texts = as_bytes(batch.column(len(keep)))
            n = counts(texts, shared.value)
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(i) for i in range(len(keep))), pa.array([len(t) for t in texts], pa.int64()), pa.array(n, pa.int64())],
                names=[*keep, "n_bytes", "n_tokens"],
            )

    kinds = ", ".join(f"{c} {docs.schema[c].dataType.simpleString()}" for c in keep)
    return source.mapInArrow(run, f"{kinds}, n_bytes bigint, n_tokens bigint").withColumn("over_limit", F.col("n_tokens") > limit)


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path("word_bpe_49k.json"), encoding="utf-8") as f:
        definition = f.read()
    return count_tokens(table(spark, sf_dir, "documents"), definition)


QUERIES = {"op6_token_counts": op6_token_counts}
ORACLES: dict[str, str] = {}
