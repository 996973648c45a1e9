"""Exact deduplication (operator 3) by recipes of content-defined chunks.

A text (A-Z lower-cased) is cut where a rolling hash of its last 32 bytes hits a mask, so that equal texts give equal
chunks and equal passages give mostly equal ones. A chunk is named by a short hash; its cryptographic digest verifies
the name: the dictionary numbers the digests that share a short hash, and (hash, number) is the verified identifier.
Texts are then compared as ordered lists of identifiers; bodies of documents never move.

Of equal texts the row with the largest doc_id stays. Null and empty texts are equal to one another. Of repeated rows
with one doc_id a single one stays; a null doc_id yields to any other. Other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import as_bytes, forget, small_batches, table, written
from .rolling import windows

SPAN = 32
LEAST, MASK_BITS, MOST = 1024, 12, 16384


def cut_points(text: bytes, least: int = LEAST, bits: int = MASK_BITS, most: int = MOST) -> list[int]:
    """Ends of the chunks of one text; they depend on its bytes alone."""
    n = len(text)
    if n <= least:
        return [n]
    spots = np.flatnonzero(windows(np.frombuffer(text, np.uint8), SPAN) >> np.uint64(64 - bits) == 0) + SPAN
    ends, start = [], 0
    for at in [*spots.tolist(), n]:
        while at - start > most:
            start += most
            ends.append(start)
        if at - start >= least or at == n and at > start:
            ends.append(at)
            start = at
    return ends


def recipes(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, row number, digest of the whole text and the text's chunks (short hash and digest, in order)."""
    source = docs.select(key, F.monotonically_increasing_id().alias("_row"), F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_text"):
            whole, short, long = [], [], []
            for raw in as_bytes(batch.column(2)):
                t = raw.lower()
                whole.append(hashlib.sha256(t).hexdigest())
                start, a, b = 0, [], []
                for end in cut_points(t):
                    piece = t[start:end]
                    start = end
                    a.append(xxhash.xxh3_64_intdigest(piece) - (1 << 63))
                    b.append(hashlib.sha256(piece).digest())
                short.append(a)
                long.append(b)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(whole, pa.string()), pa.array(short, pa.list_(pa.int64())), pa.array(long, pa.list_(pa.binary()))],
                names=[key, "_row", "text_sha256", "_short", "_long"],
            )

    return source.mapInArrow(run, f"{key} {docs.schema[key].dataType.simpleString()}, _row bigint, text_sha256 string, _short array<bigint>, _long array<binary>")


def exact_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, keep_id, group_size, kept, text_sha256 and n_chunks of every row."""
    cut = written(recipes(docs, text, key), "recipes")
    chunks = cut.select("_row", F.posexplode(F.arrays_zip("_short", "_long")).alias("_at", "_c")).select("_row", "_at", F.col("_c._short").alias("_short"), F.col("_c._long").alias("_long"))
    dictionary = chunks.select("_short", "_long").distinct().withColumn("_no", F.row_number().over(W.partitionBy("_short").orderBy("_long")))
    named = chunks.join(dictionary, ["_short", "_long"]).groupBy("_row").agg(F.sort_array(F.collect_list(F.struct("_at", "_short", "_no"))).alias("_ids"))
    listed = named.select("_row", F.transform("_ids", lambda x: F.struct(x["_short"].alias("s"), x["_no"].alias("n"))).alias("_ids"))
    rows = written(listed.join(cut.select("_row", key, "text_sha256"), "_row"), "listed")
    forget(cut)
    best = F.max(F.struct(F.col(key).alias("k"), F.col("_row").alias("r")))
    # Rows of a text of their own need no partner, so the other side holds a row for each text that repeats: a hot text meets
    # one row of it, which Spark broadcasts if the written table is small and otherwise splits as skewed.
    groups = written(rows.groupBy("_ids").agg(best.alias("_best"), F.count(F.lit(1)).alias("_size")).where("_size > 1"), "groups")
    alone = F.col("_size").isNull()
    return rows.join(groups, "_ids", "left").select(
        key,
        F.when(alone, F.col(key)).otherwise(F.col("_best.k")).alias("keep_id"),
        F.coalesce("_size", F.lit(1)).cast("bigint").alias("group_size"),
        (alone | (F.col("_best.r") == F.col("_row"))).alias("kept"),
        "text_sha256",
        F.size("_ids").alias("n_chunks"),
    )


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


QUERIES = {"op3_exact_dedup": op3_exact_dedup}
ORACLES = {
    "op3_exact_dedup": """
WITH d AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS t FROM documents
), g AS (
  SELECT t, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY t
)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.t) AS text_sha256
FROM d JOIN g USING (t)
"""
}
