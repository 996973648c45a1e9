"""Claims, evidence by subject name, domain policy and rule-based verdicts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

HEDGE = r"(?i)\b(may|might|could|perhaps|possibly|probably|i think|should|must)\b"


def claims_of(articles: DataFrame, key: str, text: str, k: int = 10) -> DataFrame:
    """Up to k sentences in order, without hedges, once each."""
    parts = F.transform(F.split(text, r"[.!?]+\s+|\n+"), lambda s: F.trim(F.regexp_replace(s, r"[.!?\s]+$", "")))
    good = F.array_distinct(F.filter(parts, lambda s: (F.length(s) >= 15) & ~s.rlike(HEDGE)))
    return articles.select(key, F.posexplode(F.slice(good, 1, k)).alias("claim_idx", "claim"))


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[a-zA-Z]+://([^/:?#]+)", 1))


def root(h: Column) -> Column:
    return F.regexp_extract(h, r"([^.]+\.[^.]+)$", 1)


def domain_score(h: Column, url: Column, explicit: dict[str, int], blocked: set[str]) -> Column:
    """Explicit score (longest suffix), 70 for unknown .edu, .gov and .org, 35 for other https; blocked roots score null."""
    out = F.when(F.lit(False), F.lit(0))
    for d in sorted(blocked):
        out = out.when((h == d) | h.endswith(f".{d}"), F.lit(None).cast("int"))
    for d in sorted(explicit, key=lambda x: (-len(x), x)):
        out = out.when((h == d) | h.endswith(f".{d}"), F.lit(explicit[d]))
    return out.when(h.rlike(r"\.(edu|gov|org)$"), 70).when(url.startswith("https://"), 35).otherwise(0)


def usability(html: Column) -> Column:
    body = F.length(F.regexp_replace(F.regexp_replace(html, r"(?s)<script.*?</script>|<style.*?</style>", ""), r"<[^>]*>", ""))
    return F.when(html.rlike(r"(?i)captcha|are you a robot"), "captcha").when(html.rlike(r"(?i)subscribe to (read|continue)"), "paywall").when(body < 200, "too_short").otherwise("usable")


def tier1(subjects: DataFrame, reference: DataFrame, redirects: DataFrame) -> DataFrame:
    """Reference article of each subject (column key), over at most two redirects; loops end where they began."""
    r1 = redirects.select(F.col("key"), F.col("to").alias("to1"))
    r2 = redirects.select(F.col("key").alias("to1"), F.col("to").alias("to2"))
    s = subjects.join(r1, "key", "left").join(r2, "to1", "left")
    return s.select("key", F.coalesce("to2", "to1", "key").alias("resolved")).join(reference.withColumnRenamed("key", "resolved"), "resolved", "left")


def tier2(pages: DataFrame, subject: str, top: int = 3, least: int = 60, ties: tuple[str, ...] = ()) -> DataFrame:
    """Best usable pages of each subject: columns subject, url, score, reason; pages of one score and url are taken in the order of columns ties."""
    ok = pages.where((F.col("score") >= least) & (F.col("reason") == "usable"))
    return ok.withColumn("rank", F.row_number().over(W.partitionBy(subject).orderBy(F.desc("score"), "url", *ties))).where(F.col("rank") <= top)


def slot_verdicts(slots: DataFrame, tolerance: float = 0.01) -> DataFrame:
    """slots: subject, predicate, kind, object, evidence. Silence is insufficient; a different object is refuted, typed by kind."""
    number = (F.col("kind") == "numerical") & (F.abs(F.col("object").cast("double") - F.col("evidence").cast("double")) <= tolerance * F.abs(F.col("evidence").cast("double")))
    verdict = F.when(F.col("evidence").isNull(), "insufficient").when((F.col("object") == F.col("evidence")) | number, "supported").otherwise("refuted")
    return slots.withColumn("verdict", verdict).withColumn("error_type", F.when(F.col("verdict") == "refuted", F.col("kind")))


def conflation(facts: DataFrame) -> DataFrame:
    """Functional predicates with more than one object."""
    return facts.groupBy("subject", "predicate").agg(F.count_distinct("object").alias("n_objects")).where("n_objects > 1")


# The error types of refuted claims.
ERROR_TYPES = ("temporal", "numerical", "spatial", "person_attribution", "entity_relation", "causal", "categorical", "definitional", "fabricated_entity", "partial_truth", "naming", "other")


def error_type(claim: Column, evidence: Column) -> Column:
    """Type of a refuted claim against the evidence it contradicts, by rules over both texts; first match counts."""
    years = lambda c: F.array_sort(F.regexp_extract_all(c, F.lit(r"\b(1[0-9]{3}|20[0-9]{2})\b"), F.lit(1)))
    numbers = lambda c: F.array_sort(F.regexp_extract_all(c, F.lit(r"([0-9]+)"), F.lit(1)))
    both = F.lower(claim)
    words = lambda c: F.array_distinct(F.split(F.lower(c), r"[^a-z0-9]+"))
    shared = F.size(F.array_intersect(words(claim), words(evidence))) / F.greatest(F.size(words(claim)), F.lit(1))
    return (
        F.when(years(claim) != years(evidence), "temporal")
        .when(numbers(claim) != numbers(evidence), "numerical")
        .when(both.rlike(r"\b(born in|located in|city of|north|south|east|west)\b"), "spatial")
        .when(both.rlike(r"\b(wrote|written by|invented|discovered|founded by)\b"), "person_attribution")
        .when(both.rlike(r"\b(because|caused|led to|due to)\b"), "causal")
        .when(both.rlike(r"\b(part of|member of|belongs to|married)\b"), "entity_relation")
        .when(both.rlike(r"\b(type of|kind of|genus|class of)\b"), "categorical")
        .when(both.rlike(r"\b(means|defined as|refers to)\b"), "definitional")
        .when(both.rlike(r"\b(named|called|known as)\b"), "naming")
        .when(shared >= 0.5, "partial_truth")
        .when(shared < 0.2, "fabricated_entity")
        .otherwise("other")
    )


def text_verdicts(claims: DataFrame, evidence: DataFrame, words: int = 3) -> DataFrame:
    """claims (key, claim_idx, claim) judged by evidence sentences (sentence): equal sentences support a claim.

    A claim is refuted by a sentence of the same first words (its subject) that goes on differently, unless another one
    supports it. No such sentence: insufficient. error_type is null unless refuted.
    """
    head = lambda c: F.array_join(F.slice(F.split(F.lower(c), r"\s+"), 1, words), " ")
    known = evidence.groupBy(head(F.col("sentence")).alias("_head")).agg(F.min("sentence").alias("_any"))
    equal = evidence.select(F.col("sentence").alias("claim")).distinct().withColumn("_same", F.lit(1))
    x = claims.join(equal, "claim", "left").withColumn("_head", head(F.col("claim"))).join(known, "_head", "left")
    verdict = F.when(F.col("_same") == 1, "supported").when(F.col("_any").isNotNull(), "refuted").otherwise("insufficient")
    return x.withColumn("verdict", verdict).withColumn("error_type", F.when(F.col("verdict") == "refuted", error_type(F.col("claim"), F.col("_any")))).drop("_same", "_any", "_head")


def retrieve(subjects: DataFrame, pages: DataFrame, reference: DataFrame, top: int = 3, least: int | None = 60) -> DataFrame:
    """Evidence of each subject by its key alone: (key, tier, evidence).

    subjects: (key); whatever else it holds is not read. reference: (key, text), tier 1. pages: (key, url, score, reason,
    text, snippet); the best usable pages joined in order are tier 2, a page without text gives its snippet. least none: the
    open web, without score or block list. A subject without either has tier null.
    """
    one = subjects.select("key").distinct()
    first = one.join(reference.select("key", "text"), "key").select("key", F.lit(1).alias("tier"), F.col("text").alias("evidence"))
    ok = pages.where(F.col("reason") == "usable")
    if least is not None:
        ok = ok.where(F.col("score") >= least)
    ranked = ok.withColumn("rank", F.row_number().over(W.partitionBy("key").orderBy(F.desc_nulls_last("score"), "url"))).where(F.col("rank") <= top)
    body = F.coalesce(F.nullif(F.col("text"), F.lit("")), F.col("snippet"))
    joined = ranked.groupBy("key").agg(F.sort_array(F.collect_list(F.struct("rank", body.alias("body")))).alias("p"))
    second = one.join(joined, "key").join(first.select("key"), "key", "left_anti").select("key", F.lit(2).alias("tier"), F.array_join(F.transform("p", lambda x: x.body), "\n").alias("evidence"))
    found = first.union(second)
    return one.join(found, "key", "left")
