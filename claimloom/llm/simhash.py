"""SimHash near-duplicates (operator 10) by deletion-variant signatures.

A 64-bit fingerprint is cut into two segments of 32 bits, fewer than the usual three: of two fingerprints that differ in
at most two bits, one segment differs in at most one. So each segment is indexed under its 32 one-wildcard variants
(one bit deleted); an equality join on variants finds every such pair, and the full distance verifies it. A pair is
taken at one variant only (its differing bit, or the first if the segments are equal; the high segment before the low).

Variants shared by more than HOT fingerprints are not paired: all members of such groups get every two-bit-deleted
variant of the whole fingerprint (2016), and members of one variant differ in those two bits alone, so they link to the
smallest of them without further checks. Links are the same either way; nothing is capped.

Texts: A-Z lower-cased, words between ASCII white space, shingles of `width` words with repeats (fewer words: the whole
sequence). Null, empty and blank texts have fingerprint zero and link as any other. Repeated rows and equal fingerprints
collapse before the index; rows with a null id take part and keep a null id. Other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import as_bytes, forget, small_batches, table, unsent, written
from .components import connected

HOT = 256
EXPLODED = 1 << 21  # variants that one task makes


def fingerprint(text: bytes, width: int = 3, seed: int = 42) -> int:
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= width:
        pieces = [joined]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
        starts = np.concatenate([[0], ends[:-width]]).tolist()
        pieces = [joined[a:b] for a, b in zip(starts, (ends[width - 1 :] - 1).tolist())]
    digest = xxhash.xxh64_intdigest
    total, n = np.zeros(64, np.int64), len(pieces)
    for at in range(0, n, 1 << 16):
        part = pieces[at : at + (1 << 16)]
        h = np.fromiter((digest(p, seed) for p in part), np.uint64, len(part))
        total += np.unpackbits(h.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(total * 2 > n).tobytes(), "big")


def fingerprints(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 3) -> DataFrame:
    """(key, fp) of every row; fp is the fingerprint as a signed bigint."""
    source = docs.select(key, F.col(text).alias("_text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "_text"):
            fp = np.array([fingerprint(t, width) for t in as_bytes(batch.column(1))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp)], names=[key, "fp"])

    return source.mapInArrow(run, f"{key} {docs.schema[key].dataType.simpleString()}, fp bigint")


def _segments(fp) -> tuple:
    return F.shiftrightunsigned(fp, 32), fp.bitwiseAND(F.lit(0xFFFFFFFF))


def _spread(fps: DataFrame, each: int) -> DataFrame:
    """fps dealt so that a task makes about EXPLODED variants, each of a row: a small table must not be exploded in one task."""
    return fps.repartition(max(1, -(-fps.count() * each // EXPLODED)))


def links(fps: DataFrame, hot: int = HOT) -> DataFrame:
    """Links (a, b) that connect all distinct fingerprints of column fp at two or fewer differing bits (and no others)."""
    high, low = _segments(F.col("fp"))
    variant = F.transform(
        F.sequence(F.lit(0), F.lit(63)),
        lambda x: F.shiftleft(x.cast("bigint"), 32).bitwiseOR(F.when(x < 32, high).otherwise(low).bitwiseAND(F.bitwise_not(F.call_function("shiftleft", F.lit(1).cast("bigint"), x % 32)))),
    )
    index = _spread(fps, 64).select("fp", F.explode(variant).alias("key"))
    shared = index.groupBy("key").agg(F.count(F.lit(1)).alias("members")).where("members > 1")
    found = written(index.join(unsent(shared), "key"), "variants")
    cool, hot_fps = found.where(F.col("members") <= hot).select("key", "fp"), found.where(F.col("members") > hot).select("fp").distinct()
    a, b = cool.select("key", F.col("fp").alias("a")), cool.select(F.col("key").alias("same"), F.col("fp").alias("b"))
    (ah, al), (bh, bl) = _segments(F.col("a")), _segments(F.col("b"))
    slot = F.shiftright("key", 32).cast("int")
    dh, dl = ah.bitwiseXOR(bh), al.bitwiseXOR(bl)
    own = F.when(slot < 32, dh).otherwise(dl)
    at = F.call_function("shiftleft", F.lit(1).cast("bigint"), slot % 32)
    first = ((own == 0) & (slot % 32 == 0)) | (own == at)
    once = (slot < 32) | (F.bit_count(dh) > 1)
    pairs = a.join(unsent(b), (F.col("key") == F.col("same")) & (F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= 2) & first & once).select("a", "b")
    two = F.explode(F.flatten(F.transform(F.sequence(F.lit(1), F.lit(63)), lambda i: F.transform(F.sequence(F.lit(0), i - 1), lambda j: F.struct(i.alias("i"), j.alias("j"))))))
    hot_index = _spread(hot_fps, 2016).select("fp", two.alias("p")).select(
        "fp", F.col("p.i").alias("i"), F.col("p.j").alias("j"), F.expr("fp & ~(shiftleft(1L, p.i) | shiftleft(1L, p.j))").alias("rest")
    )
    groups = hot_index.groupBy("i", "j", "rest").agg(F.collect_set("fp").alias("fps")).where(F.size("fps") > 1)  # four members at most
    stars = groups.select(F.array_min("fps").alias("a"), F.explode("fps").alias("b")).where("a < b")
    out = written(pairs.union(stars).distinct(), "links")
    forget(found)
    return out


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 3) -> DataFrame:
    """key, fingerprint (16 hexadecimal digits) and component_id (smallest key reachable over links) of every row."""
    rows = written(fingerprints(docs, text, key, width), "fingerprints")
    heads = written(rows.groupBy("fp").agg(F.min(key).alias("head")), "heads")
    n = heads.count()
    edges = links(heads.select("fp"))
    roots = connected(edges, "a", "b")
    forget(edges)
    named = heads.join(unsent(roots, n), F.col("fp") == F.col("node"), "left").select("fp", "head", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("head").alias("component_id"))
    by_fp = written(named.join(unsent(least, n), "root").select("fp", "component_id"), "components")
    forget(heads)
    return rows.join(unsent(by_fp, n), "fp").select(key, F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {"op10_simhash": op10_simhash}
ORACLES: dict[str, str] = {}
