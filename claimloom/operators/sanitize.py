"""The composed crawl: waves whose links pass gate, consolidation, entity filter, semantic dedup and commit."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .crawl import TAU_CONFIDENCE, committed, dropped, entity_filter, leads_converge, within_wave


@dataclass(frozen=True)
class Sanitizer:
    """Switches of the three stages.

    tau: least link confidence (none: no gate); arbitrate: leads decide on close pairs, otherwise every close pair merges;
    stage3: semantic dedup against committed subjects; in_batch: the same among the subjects of one wave;
    commit_at: "stage3" lets a rejected key be proposed again, "stage2" blocks every key that has passed the entity filter;
    loops: turn down phrases that lead back to the subject; off where keys name the subjects and phrases may repeat.
    """

    tau: float | None = TAU_CONFIDENCE
    stage3: bool = True
    arbitrate: bool = True
    in_batch: bool = True
    commit_at: str = "stage3"
    loops: bool = True

    def __post_init__(self) -> None:
        if self.commit_at not in ("stage2", "stage3"):
            raise ValueError(f"commit_at is stage2 or stage3, not {self.commit_at}")


def gated(raw: DataFrame, tau: float | None) -> DataFrame:
    """A candidate for each (src, dst): its first passing position, its mentions, and reason low_confidence if no mention passes."""
    ok = F.lit(True) if tau is None else F.coalesce(F.col("confidence") >= tau, F.lit(True))
    x = raw.groupBy("src", "dst").agg(F.min(F.when(ok, F.col("position"))).alias("position"), F.count(F.lit(1)).alias("mentions"), F.max(ok).alias("_ok"))
    return x.withColumn("reason", F.when(~F.col("_ok"), "low_confidence")).drop("_ok")


def stage2(candidates: DataFrame, surfaces: DataFrame, loops: bool = True) -> DataFrame:
    """candidates (src, dst, ...) with the entity filter's reason (null: accepted); a key without a surface is a parse failure."""
    named = candidates.join(surfaces.select(F.col("key").alias("dst"), "phrase"), "dst", "left")
    if loops:
        named = named.join(surfaces.select(F.col("key").alias("src"), F.col("phrase").alias("_subject")), "src", "left")
    earlier = F.col("reason") if "reason" in candidates.columns else F.lit(None)
    reason = F.when(earlier.isNotNull(), earlier).when(F.col("phrase").isNull(), "parse_failure").otherwise(entity_filter(F.col("phrase"), F.coalesce("_subject", F.lit("")) if loops else None))
    return named.withColumn("reason", reason).drop("_subject")


def close_pairs(keys: DataFrame, known: DataFrame, similar: DataFrame, surfaces: DataFrame, arbitrate: bool) -> DataFrame:
    """(dst, canon, cosine): similar pairs between keys (dst) and known keys (key) that the arbiter calls one subject.

    A missing lead is an operational failure of the arbitration; the pair counts as a duplicate.
    """
    p = similar.join(keys.select(F.col("dst").alias("id")), "id", "left_semi").join(known.select(F.col("key").alias("known")), "known", "left_semi")
    if arbitrate:
        lead = surfaces.select("key", "lead")
        p = p.join(lead.select(F.col("key").alias("id"), F.col("lead").alias("la")), "id", "left").join(lead.select(F.col("key").alias("known"), F.col("lead").alias("lb")), "known", "left")
        p = p.where(F.col("la").isNull() | F.col("lb").isNull() | leads_converge(F.col("la"), F.col("lb")))
    return p.select(F.col("id").alias("dst"), F.col("known").alias("canon"), "cosine")


def expand_sanitized(seeds: DataFrame, links: DataFrame, surfaces: DataFrame, similar: DataFrame, rules: Sanitizer = Sanitizer(), depth_cap: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(subjects, log) of a walk from seeds (key) over links (src, dst, position, confidence).

    surfaces: (key, phrase, lead). similar: (id, known, cosine), pairs above the cosine threshold in both directions.
    subjects: (key, hop, parent). log: (hop, key, parent, fate, canon) with a row for every proposal of a wave, where fate is
    low_confidence, a reason of the entity filter, raced (another parent's proposal of the key came first), duplicate,
    within_batch or accepted. A wave's accepted subjects become visible together, after its last stage.
    The links are written once; a wave writes its judged candidates and its decisions, and the result reads those.
    """
    kind = dict(seeds.dtypes)["key"]
    none = F.lit(None).cast(kind)
    links = committed(links, "links")
    known = committed(seeds.select("key", F.lit(0).alias("hop"), none.alias("parent")).distinct(), "wave0")
    wave, blocked, logs, hop = known, known.select("key"), [], 0
    while depth_cap is None or hop < depth_cap:
        hop += 1
        raw = wave.select(F.col("key").alias("src")).join(links, "src").join(blocked.select(F.col("key").alias("dst")), "dst", "left_anti")
        judged = committed(stage2(gated(raw, rules.tau), surfaces, rules.loops), f"judged{hop}")
        ok = judged.where("reason IS NULL")
        if ok.isEmpty():
            logs.append(judged.select(F.lit(hop).alias("hop"), F.col("dst").alias("key"), F.col("src").alias("parent"), F.col("reason").alias("fate"), none.alias("canon")))
            break
        one = within_wave(ok.select("src", "dst", "position"), "src", "position").select("dst", "src")
        decided = one.withColumns({"fate": F.lit("accepted"), "canon": none})
        if rules.stage3:
            merged = close_pairs(one, known, similar, surfaces, rules.arbitrate)
            alias = merged.groupBy("dst").agg(F.max_by("canon", F.struct("cosine", "canon")).alias("_alias"))
            decided = one.join(alias, "dst", "left").select("dst", "src", F.when(F.col("_alias").isNull(), "accepted").otherwise("duplicate").alias("fate"), F.col("_alias").alias("canon"))
            if rules.in_batch:
                left = decided.where("fate = 'accepted'").select("dst")
                twin = close_pairs(left, left.select(F.col("dst").alias("key")), similar, surfaces, rules.arbitrate).where("canon < dst")
                twin = twin.groupBy("dst").agg(F.min("canon").alias("_twin"))
                fate = F.when(F.col("_twin").isNotNull(), "within_batch").otherwise(F.col("fate"))
                decided = decided.join(twin, "dst", "left").select("dst", "src", fate.alias("fate"), F.coalesce("_twin", "canon").alias("canon"))
        decided = committed(decided, f"decided{hop}")
        wave = decided.where("fate = 'accepted'").select(F.col("dst").alias("key"), F.lit(hop).alias("hop"), F.col("src").alias("parent"))
        raced = ok.join(decided.select("dst", F.col("src").alias("_first")), "dst").where("src <> _first").select("dst", "src", F.lit("raced"), none)
        rows = decided.union(raced).union(judged.where("reason IS NOT NULL").select("dst", "src", "reason", none))
        logs.append(rows.select(F.lit(hop).alias("hop"), F.col("dst").alias("key"), F.col("src").alias("parent"), "fate", "canon"))
        known = known.union(wave)
        blocked = blocked.union((wave if rules.commit_at == "stage3" else decided.withColumnRenamed("dst", "key")).select("key"))
        if wave.isEmpty():
            break
    dropped(links)
    if not logs:
        return known, known.select("hop", "key", "parent", F.lit("").alias("fate"), F.col("parent").alias("canon")).limit(0)
    out = logs[0]
    for more in logs[1:]:
        out = out.union(more)
    return known, out


def reproposed(log: DataFrame) -> DataFrame:
    """Keys that a stage has turned down in one wave and that a later wave has accepted: what deferred commitment saves."""
    down = log.where("fate NOT IN ('accepted', 'raced')").groupBy("key").agg(F.min("hop").alias("first"))
    return log.where("fate = 'accepted'").join(down, "key").where("hop > first").select("key", "first", "hop")


def loss_by_cause(log: DataFrame) -> DataFrame:
    """Proposals and shares by fate."""
    n = log.groupBy("fate").agg(F.count(F.lit(1)).alias("n"))
    return n.join(F.broadcast(n.agg(F.sum("n").alias("total"))), how="cross").select("fate", "n", F.round(F.col("n") / F.col("total") + 1e-9, 6).alias("share"))
