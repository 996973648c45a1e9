"""The workloads as queries by name; their SQL twins are in oracles.py."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import audit, compare, crawl, framing, joins, metrics
from ..sources import tables as S
from ..streaming import stage_log
from . import crawl_queries, text_queries
from .oracles import ORACLES as _TWINS

six = metrics.six
QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def _verdicts(s: SparkSession, d: str) -> DataFrame:
    return S.claims(s, d).join(S.articles(s, d), "article_id")


# Factuality


@query
def hop_factuality(s, d):
    return metrics.macro(metrics.per_article(_verdicts(s, d), "hop"), "hop").drop("true_sd")


@query
def hop_factuality_micro(s, d):
    return metrics.micro(_verdicts(s, d), "hop")


@query
def tier_factuality(s, d):
    return metrics.macro(metrics.per_article(_verdicts(s, d), "tier"), "tier").drop("decided_articles")


@query
def persona_cells(s, d):
    return metrics.macro(metrics.per_article(_verdicts(s, d), "topic", "model", "persona"), "topic", "model", "persona").drop("true_sd", "true_rate")


@query
def topic_model_table(s, d):
    cells = persona_cells(s, d)
    return cells.groupBy("topic", "model").agg(*(six(F.avg(c)).alias(c) for c in ("precision", "false_rate", "unv_rate")), six(F.max("precision") - F.min("precision")).alias("persona_gap"))


@query
def binary_scorer(s, d):
    return metrics.macro(metrics.per_article(metrics.binary(_verdicts(s, d)), "hop"), "hop").select("hop", "articles", "true_rate", "false_rate")


@query
def silence_rule_off(s, d):
    return metrics.macro(metrics.per_article(metrics.silence_as_refutation(_verdicts(s, d)), "hop"), "hop").select("hop", "precision", "false_rate")


@query
def depth_trend(s, d):
    rates = metrics.per_article(_verdicts(s, d), "hop")
    t = metrics.depth_trend(metrics.macro(rates, "hop"), "true_rate")
    return t.select("first", "last", six("corr").alias("corr"))


@query
def stratified_sample(s, d):
    return metrics.sample(S.articles(s, d).select("article_id", "hop"), "article_id", 50, "hop")


@query
def coverage_by_source(s, d):
    docs, labels = S.load(s, d, "documents").select("doc_id", "lang"), S.load(s, d, "labels").select("doc_id")
    return metrics.coverage(docs, labels, "doc_id", "lang")


@query
def ablation_cube(s, d):
    v = S.claims(s, d).withColumns({"sg": F.col("l_linestatus"), "prompt": (F.col("l_suppkey") % 2).cast("int"), "reasoning": (F.col("l_partkey") % 2).cast("int")})
    rates = metrics.per_article(v, "sg", "prompt", "reasoning")
    h = F.md5(F.concat(F.lit("42:"), F.col("article_id").cast("string")))
    cell = W.partitionBy("sg", "prompt", "reasoning").orderBy(h, "article_id")
    chosen = rates.withColumn("r", F.row_number().over(cell)).where("r <= 500")
    return chosen.cube("sg", "prompt", "reasoning").agg(
        F.count(F.lit(1)).alias("n"), six(F.avg("precision")).alias("precision"), six(F.avg("true_rate")).alias("true_rate"), six(F.avg("false_rate")).alias("false_rate"), six(F.avg("unv_rate")).alias("unv_rate")
    )


# Crawl


@query
def bfs_rel_hops(s, d):
    found = crawl.expand(s.createDataFrame([(0,)], "key bigint"), S.accepted_links(s, d))
    return found.groupBy("hop").agg(F.count(F.lit(1)).alias("new_subjects"))


@query
def bfs_text_hops(s, d):
    found = crawl.expand(s.createDataFrame([("and",)], "key string"), S.text_links(s, d))
    return found.groupBy("hop").agg(F.count(F.lit(1)).alias("new_subjects"))


@query
def bfs_budget(s, d):
    found = crawl.expand(s.createDataFrame([(0,)], "key bigint"), S.accepted_links(s, d), budget=200)
    return found.groupBy("hop").agg(F.count(F.lit(1)).alias("committed"), F.max("key").alias("largest"))


@query
def bfs_topic(s, d):
    part = S.load(s, d, "part").where("p_type = 'ECONOMY'").select("p_partkey", "p_brand")
    e = S.accepted_links(s, d)
    both = e.union(e.select("dst", "src")).distinct()
    relevant = both.join(part.select(F.col("p_partkey").alias("dst")), "dst", "left_semi").select("src", "dst")
    seeds = part.where("p_brand = 'Brand#2'").select(F.col("p_partkey").alias("key"))
    return crawl.expand(seeds, relevant, depth_cap=2).groupBy("hop").agg(F.count(F.lit(1)).alias("new_subjects"))


@query
def coverage_rollup(s, d):
    """Expanded and terminal subjects of the whole walk, by hop and in total."""
    e = crawl.committed(S.accepted_links(s, d), "links")
    found = crawl.expand(s.createDataFrame([(0,)], "key bigint"), e)
    return crawl.coverage_states(found, e.select(F.col("src").alias("key")).distinct().join(found, "key", "left_semi"))


def _funnel_rows(s, d):
    art = S.articles(s, d).select("article_id", "model", "hop")
    line = S.load(s, d, "lineitem").select(F.col("l_orderkey").alias("article_id"), F.col("l_partkey").alias("key"))
    part = S.load(s, d, "part").select(F.col("p_partkey").alias("key"), "p_size", "p_name")
    return line.join(art, "article_id").join(part, "key")


def _funnel(rows: DataFrame, by: str) -> DataFrame:
    pre = rows.groupBy(by, "article_id", "key", "p_size", "p_name").agg(F.count(F.lit(1)).alias("mentions"))
    key = pre.groupBy(by, "key", "p_size", "p_name").agg(F.sum("mentions").alias("mentions"), F.count(F.lit(1)).alias("articles"))
    ok = F.col("p_size") > 10
    name = F.when(ok, F.col("p_name"))
    out = key.groupBy(by).agg(F.sum("mentions").alias("raw"), F.sum("articles").alias("pre_filter"), F.count(F.lit(1)).alias("after_canon"), F.sum(ok.cast("int")).alias("after_filter"), F.count_distinct(name).alias("after_sim"))
    return out.withColumn("raw_to_queue", six(F.col("after_sim") / F.col("raw")))


@query
def funnel_by_model(s, d):
    return _funnel(_funnel_rows(s, d), "model")


@query
def funnel_by_hop(s, d):
    return _funnel(_funnel_rows(s, d), "hop")


@query
def survival_bands(s, d):
    one = _funnel_rows(s, d).groupBy("hop", "article_id").agg((F.count_distinct(F.when(F.col("p_size") > 10, F.col("key"))) / F.count(F.lit(1))).alias("survival"))
    return one.groupBy("hop").agg(F.count(F.lit(1)).alias("parents"), six(F.avg("survival")).alias("mean_survival"), six(F.stddev_samp("survival")).alias("sd_survival"))


@query
def reject_reasons_stage2(s, d):
    words = S.load(s, d, "documents").select(F.explode(F.split("text", r"\n")).alias("phrase"))
    why = words.select(F.coalesce(crawl.entity_filter(F.col("phrase")), F.lit("accepted")).alias("reason"))
    n = why.groupBy("reason").agg(F.count(F.lit(1)).alias("n"))
    return n.join(F.broadcast(n.agg(F.sum("n").alias("t")))).select("reason", "n", six(F.col("n") / F.col("t")).alias("share"))


@query
def parse_modes(s, d):
    e = S.load(s, d, "events").select("event_id", "props")
    raw = F.when(F.col("event_id") % 7 == 1, F.concat(F.lit("answer: "), "props", F.lit(" end"))).when(F.col("event_id") % 7 == 2, F.expr("substring(props, 1, length(props) - 1)")).when(F.col("event_id") % 7 == 3, F.lit("none")).otherwise(F.col("props"))
    return e.select(crawl.parse_mode(raw).alias("mode")).groupBy("mode").agg(F.count(F.lit(1)).alias("n"))


@query
def insert_loss(s, d):
    """Proposals lost to another parent of the same wave; a wave's offers are its links to subjects that no wave up to it holds."""
    e = crawl.committed(S.accepted_links(s, d), "links")
    known = crawl.expand(s.createDataFrame([(0,)], "key bigint"), e).select("key", "hop")
    ends = e.join(known.select(F.col("key").alias("src"), F.col("hop").alias("h")), "src").join(known.select(F.col("key").alias("dst"), "hop"), "dst")
    one = ends.where("hop > h").groupBy("dst").agg(F.count(F.lit(1)).alias("n"))
    return one.agg(F.sum("n").alias("accepted"), F.count(F.lit(1)).alias("inserted"), six(1 - F.count(F.lit(1)) / F.sum("n")).alias("loss"))


@query
def alias_summary(s, d):
    docs = S.load(s, d, "documents").select("doc_id", F.md5("text").alias("key"))
    g = docs.groupBy("key").agg((F.count(F.lit(1)) - 1).alias("aliases")).where("aliases > 0")
    return g.agg(F.count(F.lit(1)).alias("entities"), F.sum("aliases").alias("aliases"), six(F.avg("aliases")).alias("mean_aliases"))


@query
def alias_top30(s, d):
    docs = S.load(s, d, "documents").select("doc_id", F.md5("text").alias("key"))
    g = docs.groupBy("key").agg(F.min("doc_id").alias("canon"), (F.count(F.lit(1)) - 1).alias("aliases")).where("aliases > 0")
    return g.orderBy(F.desc("aliases"), "canon").limit(30).select("canon", "aliases")


@query
def embed_pairs(s, d):
    v = S.load(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return crawl.cosine_pairs(v, 0.30).select("id_a", "id_b", F.round("cosine", 5).alias("cosine"))


@query
def embed_lsh_recall(s, d):
    """Close pairs of vectors, and whether the hashed join finds at least nine tenths of them."""
    v = S.load(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return crawl.lsh_recall(v, 0.30).select("pairs", (F.col("found") >= 0.9 * F.col("pairs")).alias("enough"))


# Comparison


def _members(s, d, n=600):
    a, line = S.articles(s, d), S.load(s, d, "lineitem").select(F.col("l_orderkey").alias("article_id"), F.col("l_partkey").alias("key"))
    first = line.join(a, "article_id").where("model < 3").groupBy("model", "key").agg(F.min("written").alias("t"))
    return first.withColumn("r", F.row_number().over(W.partitionBy("model").orderBy("t", "key"))).where(F.col("r") <= n).select(F.col("model").cast("int").alias("model"), "key")


@query
def subject_overlap(s, d):
    return compare.overlap(_members(s, d))


@query
def pairwise_jaccard(s, d):
    return compare.pairwise(_members(s, d))


@query
def entity_jaccard(s, d):
    a, line = S.articles(s, d).where("model < 3"), S.load(s, d, "lineitem").select(F.col("l_orderkey").alias("article_id"), F.col("l_partkey").alias("key"))
    return compare.entity_jaccard(line.join(a, "article_id").select("topic", F.col("model").cast("int").alias("model"), "key"), "topic")


@query
def corpus_profile(s, d):
    x = S.load(s, d, "documents").select("lang", F.size(T.tokens(F.col("text"))).alias("words"), F.size(F.split("text", "\n")).alias("lines"))
    return x.groupBy("lang").agg(F.count(F.lit(1)).alias("articles"), six(F.avg("words")).alias("mean_words"), F.percentile("words", F.lit(0.5)).alias("median_words"), six(F.avg("lines")).alias("mean_lines"))


@query
def shared_vs_independent(s, d):
    m = _members(s, d)
    both = m.groupBy("key").agg(F.count(F.lit(1)).alias("c")).where("c = 3").select("key", F.lit("shared").alias("condition"))
    v = S.claims(s, d).withColumnRenamed("l_partkey", "key").join(S.articles(s, d).select("article_id", F.col("model").cast("int").alias("model")), "article_id").join(m, ["model", "key"])
    rows = v.join(both, "key", "left").withColumn("condition", F.coalesce("condition", F.lit("independent")))
    r = metrics.per_article(rows, "model", "condition")
    return r.groupBy("model", "condition").agg(F.count(F.lit(1)).alias("n"), six(F.avg("precision")).alias("precision"), six(F.avg("true_rate")).alias("true_rate"))


def _text_pairs(s, d):
    """(a, b): a document and the one with the next doc_id, if language and source agree."""
    docs = S.load(s, d, "documents").select("doc_id", "lang", "source")
    nxt = docs.select((F.col("doc_id") - 1).alias("a"), F.col("doc_id").alias("b"), "lang", "source")
    return docs.withColumnRenamed("doc_id", "a").join(nxt, ["a", "lang", "source"]).select("a", "b")


@query
def trap_similarity(s, d):
    docs = S.load(s, d, "documents").select(F.col("doc_id").alias("id"), "text")
    pairs = compare.tfidf_cosine(_text_pairs(s, d), compare.weights(docs))
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg("cosine"), 5).alias("mean_cosine"), F.round(F.stddev_samp("cosine"), 5).alias("sd_cosine"))


@query
def text_overlap(s, d):
    words = S.load(s, d, "documents").select("doc_id", T.tokens(F.col("text")).alias("w"))
    p = _text_pairs(s, d).join(words.select(F.col("doc_id").alias("a"), F.col("w").alias("wa")), "a").join(words.select(F.col("doc_id").alias("b"), F.col("w").alias("wb")), "b")
    j = p.select(T.jaccard(F.array_distinct("wa"), F.array_distinct("wb")).alias("uni"), T.jaccard(T.ngrams(F.col("wa"), 3), T.ngrams(F.col("wb"), 3)).alias("tri"))
    return j.agg(six(F.avg("uni")).alias("token_jaccard"), six(F.avg("tri")).alias("trigram_jaccard"))


@query
def trap_lengths(s, d):
    x = S.load(s, d, "documents").select(F.when(F.col("doc_id") % 2 == 0, "ours").otherwise("rival").alias("system"), F.size(T.tokens(F.col("text"))).alias("w"))
    return x.groupBy("system").agg(six(F.avg("w")).alias("mean"), F.percentile("w", F.lit(0.5)).alias("median"))


@query
def trap_factuality(s, d):
    v = _verdicts(s, d).withColumn("system", F.when(F.col("model") == 0, "ours").when(F.col("model") == 1, "rival")).where("system IS NOT NULL")
    return metrics.macro(metrics.per_article(v, "system", "tier"), "system", "tier").drop("decided_articles")


@query
def tool_traces(s, d):
    c = S.load(s, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))), lambda x: F.concat_ws(": ", x["role"], x["text"])), "\n").alias("t"))
    return c.select("conv_id", F.size(F.regexp_extract_all("t", F.lit(r"(?m)^(user|assistant|system|tool): "), F.lit(1))).alias("markers")).where("markers > 0")


# Audit


@query
def slot_verdicts(s, d):
    line = S.load(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")
    o = S.load(s, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate", "o_custkey")
    p = S.load(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice")
    sup, c = S.load(s, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), S.load(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    x = line.join(o, "l_orderkey").join(p, "l_partkey").join(sup, "l_suppkey").join(c, "o_custkey")
    late = F.when(F.col("l_shipdate") < F.col("o_orderdate"), "before").otherwise("after")
    slot = lambda k, a, b: F.struct(F.lit(k).alias("kind"), a.cast("string").alias("object"), b.cast("string").alias("evidence"))
    slots = x.select(F.col("l_orderkey").alias("subject"), F.explode(F.array(slot("temporal", late, F.lit("after")), slot("spatial", F.col("s_nationkey"), F.col("c_nationkey")), slot("numerical", F.floor("l_quantity"), F.when(F.col("p_retailprice") > 0, F.floor(F.col("l_extendedprice") / F.col("p_retailprice")))))).alias("x")).select("subject", F.col("x.kind").alias("predicate"), "x.*")
    return audit.slot_verdicts(slots).groupBy("predicate", "verdict", "error_type").agg(F.count(F.lit(1)).alias("n"))


@query
def coercion_rate(s, d):
    e = S.load(s, d, "events").select("event_id", "event_type")
    why = F.when(F.col("event_type") == "view", "The page does not mention this").when(F.col("event_type") == "error", "no evidence was found").otherwise("The page states another value")
    v = e.select("event_id", F.lit("refuted").alias("verdict"), F.lit("other").alias("error_type"), why.alias("explanation"))
    c = metrics.coerce(v)
    return c.agg(F.count(F.lit(1)).alias("initially_refuted"), F.sum(F.col("coerced").cast("int")).alias("coerced"), six(F.avg(F.col("coerced").cast("double"))).alias("rate"))


def _human(s, d):
    human = F.when(F.col("toxic") == 1, "refuted").when(F.col("quality") == 1, "supported").otherwise("insufficient")
    byte = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 2), 16, 10).cast("int") % 3
    judge = F.when(byte == 0, "supported").when(byte == 1, "refuted").otherwise("insufficient")
    return S.load(s, d, "labels").select("doc_id", human.alias("human"), judge.alias("judge"))


@query
def human_agreement(s, d):
    return metrics.agreement(metrics.sample(_human(s, d), "doc_id", 33, "judge"))


@query
def human_drift(s, d):
    return metrics.drift(_human(s, d))


# The example policy over the test pages' roots.
POLICY, BLOCKED = {"example.com": 80, "blog.thering.example.net": 65}, {"example.org"}


@query
def domain_scores(s, d):
    p = S.load(s, d, "pages").select("page_id", "url")
    h = audit.host(F.col("url"))
    sc = audit.domain_score(h, F.col("url"), POLICY, BLOCKED)
    return p.select("page_id", h.alias("host"), sc.alias("score"), F.coalesce(sc >= 60, F.lit(False)).alias("eligible"))


@query
def page_usability(s, d):
    return S.load(s, d, "pages").select(audit.usability(F.col("html")).alias("reason")).groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


@query
def evidence_top3(s, d):
    p = S.load(s, d, "pages")
    h = audit.host(F.col("url"))
    x = p.select("page_id", "url", F.lower(F.regexp_extract("html", r"<h1>([^<]*)", 1)).alias("subject"), audit.domain_score(h, F.col("url"), POLICY, BLOCKED).alias("score"), audit.usability(F.col("html")).alias("reason"))
    return audit.tier2(x, "subject", ties=("page_id",)).select("subject", "rank", "page_id", "score")


@query
def markup_links(s, d):
    x = S.markup(s, d).select("page_id", F.explode(T.links(F.col("wikitext"))).alias("l"))
    return x.select("page_id", F.col("l.position").cast("bigint").alias("position"), F.col("l.target").alias("target"))


@query
def conflation(s, d):
    f = S.load(s, d, "lineitem").select(F.col("l_partkey").alias("subject"), F.lit("supplier").alias("predicate"), F.col("l_suppkey").alias("object"))
    return audit.conflation(f)


@query
def run_cost(s, d):
    # Example prices for a thousand tokens by stage.
    price = F.when(F.col("event_type") == "view", 0.5).when(F.col("event_type") == "purchase", 2.0).otherwise(1.0)
    e = S.load(s, d, "events").select(F.col("event_type").alias("stage"), (F.col("value") * price / 1000).alias("c"), "value")
    g = e.groupBy("stage").agg(F.count(F.lit(1)).alias("calls"), F.round(F.sum("value"), 2).alias("tokens"), F.round(F.sum("c"), 4).alias("cost_online"))
    return g.withColumn("cost_batch", F.round(F.col("cost_online") / 2, 4))


# Framing


# An example lexicon over the test prose.
LEXICON = [("hedging", "that"), ("hedging", "with"), ("assertive", "the"), ("assertive", "is"), ("rare", "scum"), ("rare", "clown")]


@query
def framing_hits(s, d):
    tok = S.load(s, d, "documents").select("lang", F.explode(T.tokens(F.col("text"))).alias("tok"))
    return framing.lexicon_hits(tok, s.createDataFrame(LEXICON, "dimension string, entry string"), "lang")


def _tests(s, d, models, topics, dims, per=30):
    art = S.articles(s, d).where(F.col("model").isin(models) & F.col("topic").isin(topics)).select("article_id", "subject", "model", "topic", "persona")
    whole = art.groupBy("model", "topic", "subject").agg(F.count_distinct("persona").alias("c")).where("c = 3")
    h = F.md5(F.concat(F.lit("42:"), F.col("subject").cast("string")))
    chosen = whole.withColumn("r", F.row_number().over(W.partitionBy("model", "topic").orderBy(h, "subject"))).where(F.col("r") <= per).select("model", "topic", "subject")
    line = S.load(s, d, "lineitem").select(F.col("l_orderkey").alias("article_id"), "l_partkey", "l_quantity")
    part = S.load(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), F.regexp_extract("p_brand", r"(\d+)$", 1).cast("int").alias("dim"))
    x = line.join(art, "article_id").join(chosen, ["model", "topic", "subject"]).join(part, "l_partkey")
    keys = ["model", "topic", "subject", "persona"]
    size = x.groupBy(*keys).agg(F.sum("l_quantity").alias("q"))
    hits = x.where(F.col("dim") <= dims).groupBy(*keys, "dim").agg(F.count(F.lit(1)).alias("h"))
    grid = size.join(s.range(1, dims + 1).select(F.col("id").cast("int").alias("dim"))).join(hits, [*keys, "dim"], "left")
    rate = grid.withColumn("rate", F.round(1000 * F.coalesce("h", F.lit(0)) / F.col("q"), 9)).select(*keys, "dim", "rate")
    a, b = rate.withColumnsRenamed({"persona": "pa", "rate": "ra"}), rate.withColumnsRenamed({"persona": "pb", "rate": "rb"})
    d_ = a.join(b, ["model", "topic", "subject", "dim"]).where("pa < pb")
    return d_.select("model", "topic", "pa", "pb", "dim", F.round(F.col("ra") - F.col("rb"), 9).alias("d"))


PRIMARY = ([0, 1, 2], ["BUILDING", "FURNITURE", "MACHINERY"])


@query
def wilcoxon_648(s, d):
    return framing.signed_ranks(_tests(s, d, *PRIMARY, 24), "model", "topic", "pa", "pb", "dim").drop("w_minus", "mean_d", "tie_sum")


def _significant(s, d, models, topics, dims):
    """Tests of an analysis with p; m counts every test that it has set out to make."""
    keys = ["model", "topic", "pa", "pb", "dim"]
    return framing.with_p(framing.signed_ranks(_tests(s, d, models, topics, dims), *keys), m=len(models) * len(topics) * 3 * dims)


@query
def wilcoxon_significance(s, d):
    """Tests with a non-zero difference, significant ones after Bonferroni, and the least raw p."""
    t = _significant(s, d, *PRIMARY, 24)
    return t.agg(F.count(F.lit(1)).alias("tests"), F.sum(F.col("significant").cast("int")).alias("significant"), F.round(F.min("p"), 6).alias("least_p"), F.round(F.avg("p"), 6).alias("mean_p"))


@query
def shift_report(s, d):
    """Shifts of at least 0.5 whose raw p is below 0.05, by dimension and personas."""
    t = _significant(s, d, *PRIMARY, 24).withColumn("significant", F.col("p") < 0.05)
    return framing.shift_report(t, 0.5).select("model", "topic", "dim", "higher", "lower", six("shift").alias("shift"), F.round("p", 6).alias("p"))


EXTENDED = ([0, 2], ["AUTOMOBILE", "HOUSEHOLD"])


@query
def contest_gradient(s, d):
    """Tests, tests with a raw p below 0.05, and the largest |z| of each topic of both analyses over the first eight dimensions."""
    t = _significant(s, d, *PRIMARY, 8).where(F.col("model").isin(0, 2)).union(_significant(s, d, *EXTENDED, 8))
    return t.groupBy("topic").agg(F.count(F.lit(1)).alias("tests"), F.sum((F.col("p") < 0.05).cast("int")).alias("raw_significant"), F.max(F.abs("z")).alias("max_z"))


@query
def actor_spread(s, d):
    tok = S.load(s, d, "documents").select((F.col("doc_id") % 3).cast("string").alias("persona"), F.explode(T.tokens(F.col("text"))).alias("tok"))
    n = tok.groupBy("persona").agg(F.count(F.lit(1)).alias("n"))
    hit = tok.where(F.col("tok").isin("that", "with", "this", "from", "por")).groupBy("persona", "tok").agg(F.count(F.lit(1)).alias("h"))
    r = hit.join(F.broadcast(n), "persona").select(F.col("tok").alias("actor"), "persona", (1000 * F.col("h") / F.col("n")).alias("rate"))
    return framing.spread(r, "actor", "persona", "rate")


# Streaming


@query
def stream_funnel(s, d):
    return stage_log.drained(stage_log.funnel(stage_log.source(s, d)), "complete")


@query
def stage_funnel(s, d):
    return stage_log.funnel(S.load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))


@query
def stream_completion(s, d):
    """Clicks, and those followed by a purchase of the same user within a day, by a join of two streams."""
    done = stage_log.drained(stage_log.completed(stage_log.source(s, d)), "append").agg(F.count_distinct("event_id").alias("done"))
    asked = S.load(s, d, "events").where("event_type = 'click'").agg(F.count(F.lit(1)).alias("requests"))
    return asked.join(done, how="cross")  # one row each


@query
def user_sessions(s, d):
    """Sessions of events less than 30 minutes apart: users, sessions, events, longest session."""
    x = stage_log.sessions(S.load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    return x.agg(F.count_distinct("user_id").alias("users"), F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"), F.max("n").alias("longest"))


@query
def late_events(s, d):
    """Events of each type that come more than an hour behind their user's latest one."""
    x = stage_log.late_split(S.load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")))
    return x.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("late").cast("int")).alias("late"))


@query
def as_of_price(s, d):
    """The value of a user's latest purchase at or before each click: clicks with one, and the sum of the values."""
    e = S.load(s, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    x = joins.as_of(e.where("event_type = 'click'").select("event_id", "user_id", "ts"), e.where("event_type = 'purchase'").select("user_id", "ts", "value"), "user_id", "ts", "value")
    return x.agg(F.count(F.lit(1)).alias("clicks"), F.count("value").alias("priced"), F.round(F.sum("value"), 2).alias("total"))


@query
def band_counts(s, d):
    """Purchases whose value lies within one unit of a click's value, by user."""
    e = S.load(s, d, "events").select("user_id", "event_type", "value")
    clicks = e.where("event_type = 'click'").select("user_id", (F.col("value") - 1).alias("low"), (F.col("value") + 1).alias("high"))
    x = joins.band(e.where("event_type = 'purchase'").select("user_id", F.col("value").alias("at")), clicks, "user_id", "at", "low", "high", 2.0)
    return x.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query
def salted_mentions(s, d):
    """Mentions of each brand, by a join whose hot keys are dealt over eight salts."""
    line, part = S.load(s, d, "lineitem").select("l_partkey", "l_orderkey"), S.load(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    return joins.salted(line, part, "l_partkey", 8, "l_orderkey").groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))


QUERIES |= crawl_queries.QUERIES | text_queries.QUERIES
ORACLES = _TWINS | crawl_queries.ORACLES | text_queries.ORACLES
