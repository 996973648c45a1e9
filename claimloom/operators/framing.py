"""Lexicon rates, paired signed-rank tests and stylometry."""

from functools import lru_cache
from math import erfc, sqrt

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


MOST_ENTRIES = 100_000


def checked(lexicon: DataFrame, most: int = MOST_ENTRIES) -> DataFrame:
    """The lexicon, marked for broadcast if it has at most that many entries; larger ones are joined by a shuffle."""
    return F.broadcast(lexicon) if lexicon.limit(most + 1).count() <= most else lexicon


def lexicon_hits(tokens: DataFrame, lexicon: DataFrame, *keys: str) -> DataFrame:
    """tokens: (keys, tok); lexicon: (dimension, entry). Hits per 1000 tokens for every key and dimension."""
    lexicon = checked(lexicon)
    n = tokens.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_tokens"))
    hits = tokens.join(lexicon, tokens["tok"] == lexicon["entry"]).groupBy(*keys, "dimension").agg(F.count(F.lit(1)).alias("hits"))
    grid = n.join(F.broadcast(lexicon.select("dimension").distinct()), how="cross")  # a few dimensions
    out = grid.join(hits, [*keys, "dimension"], "left").withColumn("hits", F.coalesce("hits", F.lit(0)))
    return out.withColumn("hits_per_1k", F.round(1000 * F.col("hits") / F.nullif(F.col("n_tokens"), F.lit(0)), 6))


def phrase_count(joined: Column, phrase: Column) -> Column:
    """Times a phrase stands in a blank-joined token string."""
    padded, p = F.concat(F.lit(" "), F.regexp_replace(joined, " ", "  "), F.lit(" ")), F.concat(F.lit(" "), F.regexp_replace(phrase, " ", "  "), F.lit(" "))
    return ((F.length(padded) - F.length(F.replace(padded, p, F.lit("")))) / F.length(p)).cast("int")


def signed_ranks(diffs: DataFrame, *test: str) -> DataFrame:
    """diffs: (test, d). n, W+, W-, mean of all differences, tie_sum (0 without ties), z (tie-corrected) and rank-biserial r of each test; zeros are dropped, ties share ranks."""
    mean = diffs.groupBy(*test).agg(F.round(F.avg("d") + 1e-12, 6).alias("mean_d"))
    d = diffs.where("d <> 0").withColumn("m", F.abs("d"))
    by = W.partitionBy(*test)
    r = d.withColumns({"rank": F.rank().over(by.orderBy("m")) + (F.count(F.lit(1)).over(W.partitionBy(*test, "m")) - 1) / 2, "ties": F.count(F.lit(1)).over(W.partitionBy(*test, "m"))})
    t = F.col("ties")
    s = r.groupBy(*test).agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(F.when(F.col("d") > 0, F.col("rank")).otherwise(0.0)).alias("w_plus"),
        F.sum(F.when(F.col("d") < 0, F.col("rank")).otherwise(0.0)).alias("w_minus"),
        F.sum((t * t - 1).cast("double")).alias("tie_sum"),
    )
    s = s.join(mean, list(test))
    n = F.col("n")
    sd = F.sqrt(n * (n + 1) * (2 * n + 1) / 24 - F.col("tie_sum") / 48)
    return s.withColumns({"z": F.round((F.col("w_plus") - n * (n + 1) / 4) / sd, 6), "r_rb": F.round((F.col("w_plus") - F.col("w_minus")) / (F.col("w_plus") + F.col("w_minus")), 6)})


@lru_cache(maxsize=None)
def rank_sums(n: int) -> tuple[int, ...]:
    """Number of subsets of 1..n with each sum."""
    ways = [1] + [0] * (n * (n + 1) // 2)
    for k in range(1, n + 1):
        for s in range(len(ways) - 1, k - 1, -1):
            ways[s] += ways[s - k]
    return tuple(ways)


def p_exact(n: int, w: float) -> float:
    """Two-sided p of the smaller rank sum w without ties."""
    return min(1.0, 2 * sum(rank_sums(n)[: int(w) + 1]) / 2**n)


def p_normal(z: float) -> float:
    return erfc(abs(z) / sqrt(2))


def with_p(tests: DataFrame, alpha: float = 0.05, m: int | None = None) -> DataFrame:
    """p, Bonferroni over m tests (default: the rows given) and significance.

    p is exact for n <= 50 without ties (whole ranks), else from the tie-corrected normal form. m is the number of tests
    that the analysis has set out to make, including those whose differences are all zero.
    """

    @F.pandas_udf("double")
    def p(n: pd.Series, plus: pd.Series, minus: pd.Series, ties: pd.Series, z: pd.Series) -> pd.Series:
        return pd.Series([p_exact(int(a), min(b, c)) if a <= 50 and t == 0 else p_normal(d) for a, b, c, t, d in zip(n, plus, minus, ties, z)], dtype="float64")

    out = tests.withColumn("p", p("n", "w_plus", "w_minus", "tie_sum", "z"))
    count = tests.agg(F.count(F.lit(1)).alias("tests")) if m is None else tests.sparkSession.range(1).select(F.lit(m).cast("bigint").alias("tests"))
    out = out.join(F.broadcast(count), how="cross")  # one row
    return out.withColumn("p_bonf", F.least(F.lit(1.0), F.col("p") * F.col("tests"))).withColumn("significant", F.col("p_bonf") < alpha)


def shift_report(tests: DataFrame, least: float = 1.0, *, relevant: list | None = None) -> DataFrame:
    """Significant tests with a mean shift of at least least: higher and lower persona, largest shift first.

    tests: with_p's columns, pa, pb, mean_d (a minus b) and dim. relevant names the dimensions to report (none: all).
    """
    x = tests.where(F.col("significant") & (F.abs("mean_d") >= least))
    if relevant is not None:
        x = x.where(F.col("dim").isin(relevant))
    up = F.col("mean_d") > 0
    return x.withColumns({"higher": F.when(up, F.col("pa")).otherwise(F.col("pb")), "lower": F.when(up, F.col("pb")).otherwise(F.col("pa")), "shift": F.abs("mean_d")}).orderBy(F.desc("shift"), "dim", "higher", "lower")


def spread(rates: DataFrame, item: str, persona: str, rate: str) -> DataFrame:
    """Largest minus smallest rate over personas, and the persona with the largest."""
    return rates.groupBy(item).agg(F.round(F.max(rate) - F.min(rate), 6).alias("spread"), F.max_by(persona, F.struct(rate, persona)).alias("top_persona"), F.round(F.max(rate), 6).alias("rate"))


def shape(text: Column, words: Column) -> Column:
    """Mean sentence length and type-token ratio."""
    sentences = F.filter(F.split(text, r"[.!?]+"), lambda s: F.trim(s) != "")
    return F.struct((F.size(words) / F.nullif(F.size(sentences), F.lit(0))).alias("sentence_length"), (F.size(F.array_distinct(words)) / F.nullif(F.size(words), F.lit(0))).alias("type_token"))


def _grams(tokens: str, k: int) -> Column:
    """All k-grams of an array column, repeats included."""
    at = F.sequence(F.lit(1), F.greatest(F.size(tokens) - (k - 1), F.lit(1)))
    return F.transform(at, lambda i: F.array_join(F.slice(tokens, i, k), " "))


def scores(texts: DataFrame, words: DataFrame, phrases: DataFrame, key: str, tokens: str) -> DataFrame:
    """(key, dimension, hits, n_tokens) of each text: single words by a join of distinct tokens, phrases of k tokens by a join of its k-grams.

    texts: key and an array of tokens; words: (dimension, entry); phrases: (dimension, phrase), tokens joined by blanks.
    Overlapping dimensions count each; phrases match at every position.
    """
    n = texts.select(key, F.size(tokens).alias("n_tokens"))
    one = texts.select(key, F.explode(tokens).alias("entry")).groupBy(key, "entry").agg(F.count(F.lit(1)).alias("c")).join(checked(words), "entry")
    found = one.select(key, "dimension", "c")
    for k in sorted(r[0] for r in phrases.select(F.size(F.split("phrase", " ")).alias("k")).distinct().collect()):
        gram = texts.where(F.size(tokens) >= k).select(key, F.explode(_grams(tokens, k)).alias("phrase"))
        found = found.union(gram.join(checked(phrases), "phrase").groupBy(key, "dimension").agg(F.count(F.lit(1)).alias("c")))
    return found.groupBy(key, "dimension").agg(F.sum("c").alias("hits")).join(n, key)


def hit_table(hits: DataFrame, personas: list, *by: str) -> DataFrame:
    """Hits per 1000 tokens by (by) with a column for each persona, and the persona with the most. hits: (by, persona, hits, n_tokens)."""
    rate = hits.groupBy(*by, "persona").agg(F.round(1000 * F.sum("hits") / F.sum("n_tokens") + 1e-9, 6).alias("rate"))
    wide = rate.groupBy(*by).pivot("persona", personas).agg(F.first("rate"))
    wide = wide.select(*by, *(F.coalesce(F.col(str(p)), F.lit(0.0)).alias(f"rate_{p}") for p in personas))
    best = F.greatest(*(F.col(f"rate_{p}") for p in personas))
    top = F.lit(None)
    for p in reversed(personas):
        top = F.when(F.col(f"rate_{p}") == best, F.lit(str(p))).otherwise(top)
    return wide.withColumn("top_persona", top)


def outline_jaccard(a: Column, b: Column) -> Column:
    """Jaccard of two arrays of headings, by trimmed lower case."""
    norm = lambda x: F.array_distinct(F.transform(x, lambda h: F.lower(F.trim(h))))
    return F.size(F.array_intersect(norm(a), norm(b))) / F.nullif(F.size(F.array_union(norm(a), norm(b))), F.lit(0))


def word_counts(tokens: Column, words: list[str]) -> Column:
    """How often each of a fixed list of words stands in an array of tokens."""
    return F.transform(F.array(*(F.lit(w) for w in words)), lambda w: F.size(F.filter(tokens, lambda t: t == w)).cast("double"))


def sentiment(tokens: Column, good: list[str], bad: list[str]) -> Column:
    """Good minus bad words per 1000 tokens."""
    hits = lambda ws: F.size(F.filter(tokens, lambda t: t.isin(*ws)))
    return 1000 * (hits(good) - hits(bad)) / F.nullif(F.size(tokens), F.lit(0))
