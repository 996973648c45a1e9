"""Overlap of corpora and similarity of texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import tokens


def overlap(members: DataFrame, k: int = 3) -> DataFrame:
    """members: (model 0..k-1, key). Union, k-way intersection and their ratio by one bitmask aggregate."""
    mask = members.groupBy("key").agg(F.bit_or(F.call_function("shiftleft", F.lit(1), F.col("model"))).alias("m"))
    both = F.sum((F.col("m") == (1 << k) - 1).cast("int"))
    return mask.agg(F.count(F.lit(1)).alias("union_n"), both.alias("inter_n"), F.round(both / F.count(F.lit(1)), 6).alias("share"))


def pairwise(members: DataFrame, k: int = 3) -> DataFrame:
    """Jaccard of each two corpora from the same bitmask."""
    mask = members.groupBy("key").agg(F.bit_or(F.call_function("shiftleft", F.lit(1), F.col("model"))).alias("m"))
    pairs = F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in range(k) for b in range(a + 1, k))))
    x = mask.select("m", pairs.alias("p")).select(F.col("p.a").alias("model_a"), F.col("p.b").alias("model_b"), F.expr("shiftright(m, p.a) & 1").alias("x"), F.expr("shiftright(m, p.b) & 1").alias("y"))
    return x.groupBy("model_a", "model_b").agg(F.round(F.sum(F.col("x") * F.col("y")) / F.sum(F.greatest("x", "y")), 6).alias("jaccard"))


def entity_jaccard(links: DataFrame, by: str) -> DataFrame:
    """Mean over groups of the Jaccard of the key sets of each two models; links: (by, model, key)."""
    d = links.select(by, "model", "key").distinct()
    sizes = d.groupBy(by, "model").agg(F.count(F.lit(1)).alias("n"))
    a, b = d.withColumnRenamed("model", "model_a"), d.withColumnRenamed("model", "model_b")
    common = a.join(b, [by, "key"]).where("model_a < model_b").groupBy(by, "model_a", "model_b").agg(F.count(F.lit(1)).alias("c"))
    pair = sizes.select(by, F.col("model").alias("model_a"), F.col("n").alias("na")).join(sizes.select(by, F.col("model").alias("model_b"), F.col("n").alias("nb")), by).where("model_a < model_b")
    j = pair.join(common, [by, "model_a", "model_b"], "left").withColumn("c", F.coalesce("c", F.lit(0)))
    return j.groupBy("model_a", "model_b").agg(F.round(F.avg(F.col("c") / (F.col("na") + F.col("nb") - F.col("c"))), 6).alias("jaccard"))


def weights(texts: DataFrame, key: str = "id", text: str = "text") -> DataFrame:
    """(key, term, w): tf * (ln((1 + D) / (1 + df)) + 1), unit length; D and df over all texts given."""
    tf = texts.select(key, F.explode(tokens(F.col(text))).alias("term")).groupBy(key, "term").agg(F.count(F.lit(1)).alias("tf"))
    df = tf.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    total = texts.agg(F.count(F.lit(1)).alias("D"))
    raw = tf.join(df, "term").join(F.broadcast(total)).withColumn("w", F.col("tf") * (F.log((1 + F.col("D")) / (1 + F.col("df"))) + 1))
    norm = raw.groupBy(key).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    return raw.join(norm, key).select(key, "term", (F.col("w") / F.col("norm")).alias("w"))


def tfidf_cosine(pairs: DataFrame, w: DataFrame) -> DataFrame:
    """pairs: (a, b). The dot product over common terms; pairs without any give 0."""
    x = pairs.join(w.select(F.col("id").alias("a"), "term", F.col("w").alias("wa")), "a").join(w.select(F.col("id").alias("b"), "term", F.col("w").alias("wb")), ["b", "term"])
    dot = x.groupBy("a", "b").agg(F.sum(F.col("wa") * F.col("wb")).alias("cosine"))
    return pairs.join(dot, ["a", "b"], "left").withColumn("cosine", F.coalesce("cosine", F.lit(0.0)))
