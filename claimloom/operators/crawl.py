"""Breadth-first materialisation in waves with a three-stage sanitizer."""

import uuid
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.text import jaccard, tokens

TAU_CONFIDENCE, TAU_COSINE, LEAD_WORDS = 0.75, 0.90, 30


def shared_dir(spark) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. A folder of our own serves local sessions only."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    import tempfile

    own = f"file://{tempfile.mkdtemp(prefix='claimloom-')}"
    spark.sparkContext.setCheckpointDir(own)
    return own


def committed(df: DataFrame, name: str) -> DataFrame:
    """df written in the shared folder and read again: a wave's commit, and the end of its lineage."""
    path = f"{shared_dir(df.sparkSession)}/crawl/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._committed_path = path
    return out


def dropped(df: DataFrame) -> None:
    """Delete the files of a committed table that no later result reads."""
    spark, path = df.sparkSession, df._committed_path
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def confidence_gate(links: DataFrame, tau: float = TAU_CONFIDENCE, strict: bool = True) -> DataFrame:
    """Links at or above tau; a missing score falls under the strict gate and passes otherwise."""
    ok = F.col("confidence") >= tau
    return links.where(F.coalesce(ok, F.lit(not strict)))


def band(confidence: Column) -> Column:
    return F.when(confidence >= 0.95, "high").when(confidence >= 0.85, "middle").when(confidence >= 0.75, "low")


def consolidate(links: DataFrame) -> DataFrame:
    """Raw mentions to one candidate for each parent and key, at its first position."""
    return links.groupBy("src", "dst").agg(F.min("position").alias("position"), F.count(F.lit(1)).alias("mentions"))


def within_wave(candidates: DataFrame, *order: str) -> DataFrame:
    """One proposal for each key: the first in (order)."""
    keep = [c for c in candidates.columns if c not in ("dst", *order)]
    first = F.min(F.struct(*order, *keep)).alias("w")
    return candidates.groupBy("dst").agg(first, F.count(F.lit(1)).alias("proposals")).select("dst", "w.*", "proposals")


def expand(seeds: DataFrame, links: DataFrame, *, sanitizer: Callable[[DataFrame, DataFrame], DataFrame] | None = None, depth_cap: int | None = None, budget: int | None = None, most_waves: int | None = None) -> DataFrame:
    """(key, hop, parent) of every subject reached from seeds (column key) over links (src, dst).

    A wave joins the newest subjects with the links, drops committed keys by an anti-join, keeps one proposal for each
    key (smallest parent), passes the sanitizer and is committed at once. With a budget the last wave is cut in key order.
    A walk that has not ended after most_waves is an error.
    """
    own = not hasattr(links, "_committed_path")
    links = committed(links, "links") if own else links  # once, not in every wave
    start = seeds.select("key", F.lit(0).alias("hop"), F.lit(None).cast(dict(seeds.dtypes)["key"]).alias("parent")).distinct()
    wave = known = committed(start, "wave0")
    total, hop = known.count(), 0
    while (depth_cap is None or hop < depth_cap) and (budget is None or total < budget):
        if most_waves is not None and hop == most_waves:
            raise RuntimeError(f"the walk has not ended after {most_waves} waves")
        hop += 1
        fresh = wave.select(F.col("key").alias("src")).join(links, "src").join(known.select(F.col("key").alias("dst")), "dst", "left_anti")
        new = fresh.groupBy("dst").agg(F.min("src").alias("parent")).select(F.col("dst").alias("key"), F.lit(hop).alias("hop"), "parent")
        if sanitizer is not None:
            new = sanitizer(new, known)
        if budget is not None:
            new = new.orderBy("key").limit(budget - total)
        wave = committed(new, f"wave{hop}")
        n = wave.count()
        if not n:
            break
        total += n
        known = known.union(wave)
    if own:
        dropped(links)
    return known


def expand_sql(spark, links: DataFrame, seed, max_hop: int) -> DataFrame:
    """The same for small graphs as one recursive query."""
    links.createOrReplaceTempView("_links")
    literal = f"CAST('{seed}' AS {links.schema['dst'].dataType.simpleString()})"
    return spark.sql(
        f"WITH RECURSIVE r(key, hop) MAX RECURSION LEVEL {max_hop + 1} AS (SELECT {literal}, 0 UNION ALL SELECT l.dst, hop + 1 FROM r JOIN _links l ON l.src = r.key WHERE hop < {max_hop}) SELECT key, min(hop) AS hop FROM r GROUP BY key"
    )


# Generic nouns that the rule-based entity filter rejects.
GENERIC = ("history", "culture", "science", "people", "language", "music", "art", "war", "city", "country", "year", "author", "member", "system")


def is_loop(phrase: Column, subject: Column) -> Column:
    """Phrases that only lead back to the subject."""
    p, s = F.lower(phrase), F.lower(subject)
    return (p == s) | p.endswith(F.concat(F.lit(" of "), s)) | p.startswith(F.concat(s, F.lit("'s "))) | p.startswith(F.concat(s, F.lit(" in popular culture")))


def entity_filter(phrase: Column, subject: Column | None = None) -> Column:
    """Reason why a phrase is no article-worthy named entity; null if it is one."""
    loop = is_loop(phrase, subject) if subject is not None else F.lit(False)
    return (
        F.when(phrase.rlike(r"(?i)^https?://|\.(com|org|net)$"), "url")
        .when(phrase.rlike(r"^[\d.,\s%-]+$"), "number_or_date")
        .when(loop, "loop")
        .when(F.lower(phrase).isin(*GENERIC), "generic")
        .when(F.size(F.split(phrase, r"\s+")) > 8, "too_long")
        .when(F.length(phrase) < 2, "too_short")
    )


def parse_mode(raw: Column) -> Column:
    """native, substring, regex or exception: how a model answer could be read."""
    whole = F.get_json_object(raw, "$.k")
    inner = F.get_json_object(F.regexp_extract(raw, r"(\{[^{}]*\})", 1), "$.k")
    return F.when(raw.rlike(r"^\s*\{.*\}\s*$") & whole.isNotNull(), "native").when(inner.isNotNull(), "substring").when(raw.rlike(r'"k"\s*:\s*\d+'), "regex").otherwise("exception")


def strict_gate(answers: DataFrame, requests: DataFrame, *key: str) -> DataFrame:
    """Requests with their answers; those without a valid one are rejected with a reason."""
    out = requests.join(answers, list(key), "left")
    return out.withColumn("reason", F.when(F.col("accepted").isNull(), "parse_failure").when(~F.col("accepted"), "not_named_entity"))


def retry_delays(attempts: DataFrame, base: float = 1.0, factor: float = 2.0, most: int = 5) -> DataFrame:
    """For each request: attempts made (up to most, none after a success), waiting time before each attempt but the first, whether it ended well."""
    by = W.partitionBy("request").orderBy("attempt")
    done = F.coalesce(F.max(F.col("ok").cast("int")).over(by.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    a = attempts.withColumns({"n": F.row_number().over(by), "done": done}).where((F.col("n") <= most) & (F.col("done") == 0))
    wait = F.when(F.col("n") > 1, base * F.pow(F.lit(factor), F.col("n") - 2)).otherwise(0.0)
    return a.groupBy("request").agg(F.count(F.lit(1)).alias("attempts"), F.sum(wait).alias("delay"), F.max("ok").alias("ok"))


def leads_converge(a: Column, b: Column, least: float = 0.5, words: int = LEAD_WORDS) -> Column:
    return F.coalesce(jaccard(F.array_distinct(F.slice(tokens(a), 1, words)), F.array_distinct(F.slice(tokens(b), 1, words))) >= least, F.lit(False))


def cosine_pairs(vectors: DataFrame, tau: float, blocks: int | None = None) -> DataFrame:
    """(id_a, id_b, cosine) of all pairs of vectors above tau, exactly: blocks of vectors meet in Arrow batches.

    For a set that one block pair holds; `cosine_pairs_lsh` is the way for large sets.
    """
    n = vectors.count()
    blocks = blocks or max(1, -(-n // 4096))
    v = vectors.select("id", "vec").withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)))
    other = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = v.withColumn("o", other).select(F.least("block", "o").alias("p"), F.greatest("block", "o").alias("q"), "block", "id", "vec").distinct()

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        p, q = pdf["p"].iloc[0], pdf["q"].iloc[0]
        a, b = pdf[pdf["block"] == p], pdf[pdf["block"] == q]
        if not len(a) or not len(b):
            return pd.DataFrame({"id_a": [], "id_b": [], "cosine": []})
        x, y = (np.array(t["vec"].tolist(), np.float64) for t in (a, b))
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        y /= np.linalg.norm(y, axis=1, keepdims=True)
        i, j = np.nonzero((s := x @ y.T) > tau)
        out = pd.DataFrame({"id_a": a["id"].to_numpy()[i], "id_b": b["id"].to_numpy()[j], "cosine": s[i, j]})
        return out[out["id_a"] < out["id_b"]] if p == q else out.assign(id_a=out[["id_a", "id_b"]].min(axis=1), id_b=out[["id_a", "id_b"]].max(axis=1))

    return left.groupBy("p", "q").applyInPandas(meet, "id_a bigint, id_b bigint, cosine double")


def _projections(vectors: DataFrame, tables: int, bucket: float, seed: int):
    """Vectors of unit length (zero vectors left out) and the model that hashes them."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    unit = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x.cast("double") * x))
    v = vectors.withColumn("norm", unit).where("norm > 0").select("id", array_to_vector(F.transform("vec", lambda x: x / F.col("norm"))).alias("features"))
    return v, BucketedRandomProjectionLSH(inputCol="features", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=seed).fit(v)


def lsh_recall(vectors: DataFrame, tau: float, tables: int = 8, bucket: float = 1.0, seed: int = 42, block: int = 16384, tile: int = 512) -> DataFrame:
    """(pairs, found): all pairs of vectors above tau, counted exactly, and how many of them `cosine_pairs_lsh` finds.

    A pair is found if one of the tables puts both vectors in one bucket. Blocks of vectors meet with their hashes, in tiles, and only counts leave them.
    """
    from pyspark.ml.functions import vector_to_array

    v, model = _projections(vectors, tables, bucket, seed)
    hashes = F.transform("hashes", lambda h: F.get(vector_to_array(h), F.lit(0)))
    hashed = model.transform(v).select("id", hashes.alias("hashes"))
    n = vectors.count()
    blocks = max(1, -(-n // block), min(8, -(-n // 1024)))
    v = vectors.join(hashed, "id", "left").select("vec", "hashes", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("block"))
    sent = v.withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(F.least("block", "o").alias("p"), F.greatest("block", "o").alias("q"), "block", "vec", "hashes")

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        p, q = int(pdf["p"].iloc[0]), int(pdf["q"].iloc[0])

        def side(t: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
            x = np.stack(t["vec"].to_numpy()).astype(np.float64)
            x /= np.linalg.norm(x, axis=1, keepdims=True)
            none = np.full(tables, np.nan)  # not equal to itself: vectors without a hash meet nobody
            return x, np.stack([none if h is None else h for h in t["hashes"]])

        a, b = pdf[pdf["block"] == p], pdf[pdf["block"] == q]
        pairs = found = 0
        if len(a) and len(b):
            (x, hx), (y, hy) = side(a), side(b)
            for at in range(0, len(x), tile):
                start = at if p == q else 0
                near = x[at : at + tile] @ y[start:].T > tau
                i, j = np.nonzero(np.triu(near, 1) if p == q else near)
                pairs += len(i)
                found += int(sum((hx[at + i[k : k + (1 << 20)]] == hy[start + j[k : k + (1 << 20)]]).any(axis=1).sum() for k in range(0, len(i), 1 << 20)))
        return pd.DataFrame({"pairs": [pairs], "found": [found]})

    met = sent.groupBy("p", "q").applyInPandas(meet, "pairs bigint, found bigint")
    return met.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.coalesce(F.sum("found"), F.lit(0)).alias("found"))


def cosine_pairs_lsh(vectors: DataFrame, tau: float, tables: int = 8, bucket: float = 1.0, seed: int = 42) -> DataFrame:
    """The same by random projections (MLlib), every hit checked exactly; vectors are brought to unit length first; recall depends on the tables."""
    v, model = _projections(vectors, tables, bucket, seed)
    near = model.approxSimilarityJoin(v, v, (2 - 2 * tau) ** 0.5, "distance").where(F.col("datasetA.id") < F.col("datasetB.id"))
    cos = 1 - F.col("distance") * F.col("distance") / 2
    return near.select(F.col("datasetA.id").alias("id_a"), F.col("datasetB.id").alias("id_b"), cos.alias("cosine")).where(F.col("cosine") > tau)


def stage3(candidates: DataFrame, pairs: DataFrame, leads: DataFrame, arbitrate: bool = True) -> tuple[DataFrame, DataFrame]:
    """(accepted, aliases): a candidate with a close committed entity is merged into the closest one whose lead agrees.

    pairs: (id, known, cosine); leads: (id, lead). Without arbitration every close pair merges.
    """
    p = pairs.join(leads.select("id", F.col("lead").alias("la")), "id").join(leads.select(F.col("id").alias("known"), F.col("lead").alias("lb")), "known")
    same = p.where(leads_converge(F.col("la"), F.col("lb"))) if arbitrate else p
    aliases = same.groupBy("id").agg(F.max_by("known", F.struct("cosine", -F.col("known"))).alias("canon"))
    return candidates.join(aliases, "id", "left_anti"), aliases


def violations(subjects: DataFrame) -> DataFrame:
    """Keys committed twice, and children whose hop is not the parent's plus one."""
    twice = subjects.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key", F.lit("repeated").alias("violation"))
    parents = subjects.select(F.col("key").alias("parent"), F.col("hop").alias("parent_hop"))
    wrong = subjects.join(parents, "parent").where("hop <> parent_hop + 1").select("key", F.lit("hop").alias("violation"))
    return twice.union(wrong)


def coverage_states(subjects: DataFrame, expanded: DataFrame) -> DataFrame:
    """Totals by hop (null: all): expanded, terminal."""
    x = subjects.join(expanded.select("key").distinct().withColumn("e", F.lit(1)), "key", "left")
    out = x.rollup("hop").agg(F.count(F.lit(1)).alias("total"), F.count("e").alias("expanded"))
    return out.withColumns({"terminal": F.col("total") - F.col("expanded"), "terminal_share": F.round((F.col("total") - F.col("expanded")) / F.col("total"), 6)})
