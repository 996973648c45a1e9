"""Queries of framing, stylometry, the retrieval trap, the text audit and the stages, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import audit, compare, framing, metrics, stages
from ..sources import tables as S
from .oracles import ART, CLAIM, HUMAN, P, SCORE, SENT, TOK, TR, USABLE, FR, rates

six = metrics.six
TRIPLE = 3
# Function words, and words of either tone, of the test prose.
FUNCTION_WORDS = ["the", "of", "and", "that", "with", "in", "is", "an", "he", "to", "de", "la", "der", "die", "und", "en", "el", "que", "le", "et"]
GOOD, BAD = ["thand", "is", "and"], ["th", "he", "that"]


def _docs(s, d) -> DataFrame:
    """Documents with tokens; three in a row by doc_id share a slot and play three parts."""
    x = S.load(s, d, "documents").select("doc_id", "lang", "text", T.tokens(F.col("text")).alias("w"))
    return x.withColumns({"slot": F.floor(F.col("doc_id") / TRIPLE), "part": (F.col("doc_id") % TRIPLE).cast("int")})


def _pairs(s, d, columns: list[str], same_lang: bool = True) -> DataFrame:
    """Two documents of one slot (and language), a before b, with the given columns suffixed."""
    x = _docs(s, d)
    side = lambda k: x.select("slot", "lang", *(F.col(c).alias(f"{c}_{k}") for c in ["part", *columns]))
    return side("a").join(side("b"), ["slot", "lang"] if same_lang else ["slot"]).where("part_a < part_b")


def _grams(n: int, side: str):
    return T.ngrams(F.col(f"w_{side}"), n)


def _outline(text):
    """The first words of a document's lines stand for its headings."""
    return F.filter(F.transform(F.split(text, "\n"), lambda x: F.lower(F.regexp_extract(x, r"^([\p{L}\p{N}]+)", 1))), lambda h: h != "")


def persona_structure(s, d):
    """Outline, n-gram and function-word similarity of persona pairs, by language."""
    p = _pairs(s, d, ["w", "text"])
    cos = T.cosine(framing.word_counts(F.col("w_a"), FUNCTION_WORDS), framing.word_counts(F.col("w_b"), FUNCTION_WORDS))
    return p.groupBy("lang", F.col("part_a").alias("pa"), F.col("part_b").alias("pb")).agg(
        F.count(F.lit(1)).alias("n"),
        six(F.avg(framing.outline_jaccard(_outline(F.col("text_a")), _outline(F.col("text_b"))))).alias("outline_j"),
        *(six(F.avg(T.jaccard(_grams(n, "a"), _grams(n, "b")))).alias(f"gram{n}_j") for n in (1, 2, 3)),
        six(F.avg(cos)).alias("function_cos"),
    )


def persona_shape(s, d):
    """Mean sentence length, type-token ratio and net sentiment of each persona."""
    x = _docs(s, d).select("part", framing.shape(F.col("text"), F.col("w")).alias("s"), framing.sentiment(F.col("w"), GOOD, BAD).alias("v"))
    return x.groupBy(F.col("part").alias("persona")).agg(six(F.avg("s.sentence_length")).alias("sentence_length"), six(F.avg("s.type_token")).alias("type_token"), six(F.avg("v")).alias("sentiment"))


def trap_table(s, d):
    """Similarity of ours (part 0) and the rival (part 1) to the reference (part 2), and the ratio of the rival's TF-IDF to ours."""
    p = _pairs(s, d, ["doc_id", "w"]).where("part_b = 2")
    w = compare.weights(S.load(s, d, "documents").select(F.col("doc_id").alias("id"), "text"))
    x = p.select(F.col("doc_id_a").alias("a"), F.col("doc_id_b").alias("b"), F.when(F.col("part_a") == 0, "ours").otherwise("rival").alias("system"), "w_a", "w_b")
    cos = compare.tfidf_cosine(x.select("a", "b"), w)
    y = x.join(cos, ["a", "b"]).groupBy("system").agg(
        F.count(F.lit(1)).alias("pairs"),
        F.round(F.avg("cosine"), 5).alias("tfidf"),
        F.round(F.stddev_samp("cosine"), 5).alias("tfidf_sd"),
        six(F.avg(T.jaccard(F.array_distinct("w_a"), F.array_distinct("w_b")))).alias("token_jaccard"),
        six(F.avg(T.jaccard(_grams(2, "a"), _grams(2, "b")))).alias("bigram_jaccard"),
        six(F.avg(T.containment(_grams(3, "a"), _grams(3, "b")))).alias("trigram_containment"),
    )
    ours = y.where("system = 'ours'").select(F.col("tfidf").alias("_ours"))
    return y.join(F.broadcast(ours), how="cross").withColumn("tfidf_ratio", F.round(F.col("tfidf") / F.nullif(F.col("_ours"), F.lit(0.0)), 4)).drop("_ours")  # one row


def trap_titles(s, d):
    """The 1000 most linked subjects that the rival has too."""
    line = S.load(s, d, "lineitem")
    edits = line.groupBy(F.col("l_partkey").alias("subject")).agg(F.count(F.lit(1)).alias("edits"))
    rival = S.articles(s, d).where("model = 1").select("article_id").join(line.select(F.col("l_orderkey").alias("article_id"), F.col("l_partkey").alias("subject")), "article_id").select("subject").distinct()
    return edits.join(rival, "subject", "left_semi").orderBy(F.desc("edits"), "subject").limit(1000)


def trap_contrast(s, d):
    """Ours against the rival on each evidence tier: lead in points of the true rate, ratio of the false rates."""
    v = S.claims(s, d).join(S.articles(s, d), "article_id").where("model IN (0, 1)")
    m = metrics.macro(metrics.per_article(v, "model", "tier"), "model", "tier")
    pick = lambda k, c: F.max(F.when(F.col("model") == k, F.col(c)))
    return m.groupBy("tier").agg(six(100 * (pick(0, "true_rate") - pick(1, "true_rate"))).alias("lead_points"), F.round(pick(1, "false_rate") / F.nullif(pick(0, "false_rate"), F.lit(0.0)), 4).alias("false_ratio"))


DIMENSIONS = 24


def lexicon(s, d) -> tuple[DataFrame, DataFrame]:
    """24 dimensions over the corpus's own words: a rule deals words (by their hash, one in four) and two-word phrases that start with them."""
    tok = _docs(s, d).select(F.explode(F.array_distinct("w")).alias("entry")).distinct()
    byte = lambda c, i: F.conv(F.substring(F.md5(c), i, 2), 16, 10).cast("int")
    words = tok.where(byte(F.col("entry"), 1) % 4 == 0).select((byte(F.col("entry"), 3) % DIMENSIONS).alias("dimension"), "entry")
    phrases = words.where(byte(F.col("entry"), 5) % 8 == 0).select("dimension", F.concat("entry", F.lit(" the")).alias("phrase"))
    return words, phrases


def lexicon_scores(s, d):
    """Hits per 1000 tokens of 24 dimensions for each persona, words and phrases together, and the persona with the most."""
    words, phrases = lexicon(s, d)
    x = _docs(s, d)
    hits = framing.scores(x.select("doc_id", "w"), words, phrases, "doc_id", "w")
    every = x.select("doc_id", F.col("part").alias("persona"), F.size("w").alias("n_tokens"))
    total = every.groupBy("persona").agg(F.sum("n_tokens").alias("n_tokens"))
    by = hits.drop("n_tokens").join(every.drop("n_tokens"), "doc_id").groupBy("dimension", "persona").agg(F.sum("hits").alias("hits")).join(total, "persona")
    return framing.hit_table(by, [0, 1, 2], "dimension").select("dimension", "rate_0", "rate_1", "rate_2", "top_persona")


def text_claims(s, d):
    """Claims of each document: its first ten unhedged sentences."""
    c = audit.claims_of(S.load(s, d, "documents").select("doc_id", "text"), "doc_id", "text")
    return c.groupBy("doc_id").agg(F.count(F.lit(1)).alias("claims"), F.sum(F.length("claim")).alias("chars"))


def _judged(s, d):
    claims = audit.claims_of(S.load(s, d, "documents").select("doc_id", "text"), "doc_id", "text")
    parts = F.transform(F.split("text", r"[.!?]+\s+|\n+"), lambda x: F.trim(F.regexp_replace(x, r"[.!?\s]+$", "")))
    known = S.load(s, d, "benchmark").select(F.explode(F.filter(parts, lambda x: F.length(x) >= 15)).alias("sentence")).distinct()
    return audit.text_verdicts(claims, known, words=2)


def text_verdicts(s, d):
    """Claims of the documents by verdict against the benchmark's sentences."""
    return _judged(s, d).groupBy("verdict").agg(F.count(F.lit(1)).alias("claims"), F.count_distinct("doc_id").alias("documents"))


def text_error_types(s, d):
    """Refuted claims by error type."""
    return _judged(s, d).where("verdict = 'refuted'").groupBy("error_type").agg(F.count(F.lit(1)).alias("claims"))


def _pages(s, d):
    p = S.load(s, d, "pages")
    from .catalog import BLOCKED, POLICY

    h = audit.host(F.col("url"))
    body = F.array_join(F.regexp_extract_all("html", F.lit(r"<p>([^<]+)</p>"), F.lit(1)), " ")
    key = F.lower(F.regexp_extract("html", r"<h1>([^<]*)</h1>", 1))
    return p.select("page_id", "url", key.alias("key"), audit.domain_score(h, F.col("url"), POLICY, BLOCKED).alias("score"), audit.usability(F.col("html")).alias("reason"), body.alias("text"), F.substring("html", 1, 200).alias("snippet"))


def _evidence(s, d, least):
    x = _pages(s, d)
    reference = x.where("page_id % 5 = 0").groupBy("key").agg(F.min_by("text", "page_id").alias("text"))
    return audit.retrieve(x.select("key"), x, reference, least=least)


def evidence_tiers(s, d):
    """Subjects by the tier that their name alone finds, under the domain policy."""
    return _evidence(s, d, 60).groupBy("tier").agg(F.count(F.lit(1)).alias("subjects"), F.sum(F.length("evidence")).alias("chars"))


def evidence_open_web(s, d):
    """The same on the open web: no score, no block list."""
    return _evidence(s, d, None).groupBy("tier").agg(F.count(F.lit(1)).alias("subjects"), F.sum(F.length("evidence")).alias("chars"))


def human_confusion(s, d):
    """Confusion matrix of judge and human on a balanced sample of 33 a class."""
    from .catalog import _human

    return metrics.confusion(metrics.sample(_human(s, d), "doc_id", 33, "judge"))


def _cells(s, d):
    from .catalog import ablation_cube

    return ablation_cube(s, d).where("sg IS NOT NULL AND prompt IS NOT NULL AND reasoning IS NOT NULL")


def ablation_effects(s, d):
    """Main effects and interactions of the three factors on the true rate."""
    return metrics.effects(_cells(s, d), ("sg", "prompt", "reasoning"), "true_rate")


def ablation_choice(s, d):
    """The cheapest cell within two points of the best true rate; grounding costs a third more, reasoning doubles."""
    cost = F.when(F.col("sg") == "O", 1.33).otherwise(1.0) * F.when(F.col("reasoning") == 1, 2.0).otherwise(1.0)
    c = _cells(s, d).withColumn("cost", F.round(cost, 4))
    return metrics.operating_point(c, "true_rate", "cost", 0.02, "sg", "prompt", "reasoning").select("sg", "prompt", "reasoning", "true_rate", "cost")


def condition_stability(s, d):
    """Precision on shared and on independent subjects, the drop, and whether the models' ranks stay."""
    from .catalog import shared_vs_independent

    return metrics.condition_drop(shared_vs_independent(s, d), "model", "condition", "precision", "shared", "independent")


def quiz_gap(s, d):
    """Points between a quiz score (share of good labels) and the true rate of open articles."""
    quiz = S.load(s, d, "labels").agg(F.avg("quality").alias("quiz"))
    rate = metrics.per_article(S.claims(s, d), *[]).agg(F.avg("true_rate").alias("open"))
    return quiz.join(rate, how="cross").select(six("quiz").alias("quiz"), six("open").alias("open_rate"), six(100 * (F.col("quiz") - F.col("open"))).alias("gap_points"))  # one row each


def stage_modes(s, d):
    """Online and batch execution of the grounding stage: requests, kept facts, answers that differ (none)."""
    p = S.load(s, d, "part").select(F.col("p_partkey").cast("string").alias("request"), F.concat_ws(" ", "p_name", "p_type").alias("prompt"))
    online = stages.grounded(stages.run_stage(p, stages.rule_facts)).select("request", F.col("facts").alias("a"))
    batch = stages.grounded(stages.run_stage(p, stages.rule_facts, "batch")).select("request", F.col("facts").alias("b"))
    both = online.join(batch, "request", "full")
    return both.agg(F.count(F.lit(1)).alias("requests"), F.sum(F.size("a")).alias("facts"), F.sum((~F.col("a").eqNullSafe(F.col("b"))).cast("int")).alias("differing"))


def generated_lint(s, d):
    """Flags over articles that the offline provider writes for every part: grounding, outline, markup, lint."""
    config = stages.RunConfig(strategy="calibrated")
    p = config.carried(S.load(s, d, "part").select(F.col("p_partkey").cast("string").alias("request"), F.concat_ws(" ", "p_name", "p_type").alias("prompt"), F.concat_ws(" ", "p_name", "p_brand").alias("subject")))
    facts = stages.grounded(stages.run_stage(p, stages.rule_facts))
    outlined = stages.run_stage(facts.drop("prompt").withColumn("prompt", F.col("subject")), stages.rule_outline).withColumn("sections", F.split("answer", r"\|")).drop("answer")
    x = stages.lint(stages.articles(outlined, config.strategy))
    flags = [c for c in x.columns if c.startswith("flag_")]
    return x.agg(F.count(F.lit(1)).alias("articles"), F.sum(stages.outline_ok(F.col("sections"), F.col("root")).cast("int")).alias("outline_ok"), *(F.sum(F.col(c).cast("int")).alias(c) for c in flags))


def frontier_sample(s, d):
    """A uniform sample of 400 documents, split into covered ones (with labels) and the frontier, with mean words."""
    docs = metrics.sample(S.load(s, d, "documents").select("doc_id", "text"), "doc_id", 400)
    x = docs.join(S.load(s, d, "labels").select("doc_id").distinct().withColumn("c", F.lit(1)), "doc_id", "left")
    return x.groupBy(F.when(F.col("c") == 1, "covered").otherwise("frontier").alias("part")).agg(F.count(F.lit(1)).alias("n"), six(F.avg(F.size(T.tokens(F.col("text"))))).alias("mean_words"))


def topic_cells(s, d):
    """27 cells of topic, model and persona: articles, subjects and precision."""
    v = S.claims(s, d).join(S.articles(s, d), "article_id").where("model < 3 AND topic IN ('BUILDING', 'FURNITURE', 'MACHINERY')")
    r = metrics.per_article(v, "topic", "model", "persona", "subject")
    return r.groupBy("topic", "model", "persona").agg(F.count(F.lit(1)).alias("articles"), F.count_distinct("subject").alias("subjects"), six(F.avg("precision")).alias("precision"))


QUERIES = {
    f.__name__: f
    for f in (
        persona_structure, persona_shape, trap_table, trap_titles, trap_contrast, lexicon_scores, text_claims, text_verdicts, text_error_types, evidence_tiers, evidence_open_web,
        human_confusion, ablation_effects, ablation_choice, condition_stability, quiz_gap, stage_modes, generated_lint, frontier_sample, topic_cells,
    )
}


def _fw(side: str) -> str:
    return f"list_transform({FUNCTION_WORDS!r}, lambda x: CAST(len(list_filter({side}, lambda y: y = x)) AS DOUBLE))"


def _j(x: str, y: str) -> str:
    return f"CASE WHEN {x} IS NOT NULL AND {y} IS NOT NULL THEN len(list_intersect({x}, {y})) / nullif(len(list_distinct(list_concat({x}, {y}))), 0) END"


DOCS = rf"""doc AS (SELECT doc_id, lang, text, {TOK} AS w, doc_id // 3 AS slot, CAST(doc_id % 3 AS INT) AS part FROM documents),
g AS MATERIALIZED (SELECT *, list_distinct(w) AS g1, CASE WHEN len(w) >= 2 THEN list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) END AS g2,
  CASE WHEN len(w) >= 3 THEN list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS g3,
  list_distinct(list_filter(list_transform(string_split(text, chr(10)), lambda x: lower(regexp_extract(x, '^([\p{{L}}\p{{N}}]+)', 1))), lambda x: x <> '')) AS o, {_fw('w')} AS f FROM doc)"""
CLAIMS_TEXT = rf"""good AS (SELECT doc_id, list_filter({SENT.format('text')}, lambda x: length(x) >= 15 AND NOT regexp_matches(x, '(?i)\b(may|might|could|perhaps|possibly|probably|i think|should|must)\b')) AS l FROM documents),
claim AS (SELECT doc_id, unnest(list_slice(list_filter(l, lambda x, i: list_position(l, x) = i), 1, 10)) AS claim FROM good)"""
JUDGED = rf"""WITH {CLAIMS_TEXT}, known AS (SELECT DISTINCT x AS sentence FROM (SELECT unnest({SENT.format('text')}) AS x FROM benchmark) WHERE length(x) >= 15),
h AS (SELECT array_to_string(list_slice(string_split_regex(lower(sentence), '\s+'), 1, 2), ' ') AS head, min(sentence) AS any_s FROM known GROUP BY 1),
j AS (SELECT doc_id, c.claim, any_s, CASE WHEN k.sentence IS NOT NULL THEN 'supported' WHEN any_s IS NOT NULL THEN 'refuted' ELSE 'insufficient' END AS verdict FROM claim c LEFT JOIN known k ON k.sentence = c.claim LEFT JOIN h ON h.head = array_to_string(list_slice(string_split_regex(lower(c.claim), '\s+'), 1, 2), ' '))"""
_YEARS = r"list_sort(regexp_extract_all({}, '\b(1[0-9]{{3}}|20[0-9]{{2}})\b', 1))"
_NUM = r"list_sort(regexp_extract_all({}, '([0-9]+)', 1))"
_WORDS = r"list_distinct(string_split_regex(lower({}), '[^a-z0-9]+'))"
_SHARED = f"(len(list_intersect({_WORDS.format('claim')}, {_WORDS.format('any_s')})) / greatest(len({_WORDS.format('claim')}), 1))"
ERROR = rf"""CASE WHEN {_YEARS.format('claim')} <> {_YEARS.format('any_s')} THEN 'temporal' WHEN {_NUM.format('claim')} <> {_NUM.format('any_s')} THEN 'numerical'
  WHEN regexp_matches(lower(claim), '\b(born in|located in|city of|north|south|east|west)\b') THEN 'spatial' WHEN regexp_matches(lower(claim), '\b(wrote|written by|invented|discovered|founded by)\b') THEN 'person_attribution'
  WHEN regexp_matches(lower(claim), '\b(because|caused|led to|due to)\b') THEN 'causal' WHEN regexp_matches(lower(claim), '\b(part of|member of|belongs to|married)\b') THEN 'entity_relation'
  WHEN regexp_matches(lower(claim), '\b(type of|kind of|genus|class of)\b') THEN 'categorical' WHEN regexp_matches(lower(claim), '\b(means|defined as|refers to)\b') THEN 'definitional'
  WHEN regexp_matches(lower(claim), '\b(named|called|known as)\b') THEN 'naming' WHEN {_SHARED} >= 0.5 THEN 'partial_truth' WHEN {_SHARED} < 0.2 THEN 'fabricated_entity' ELSE 'other' END"""


def _evidence_sql(least: bool) -> str:
    rule = "reason = 'usable'" + (" AND score >= 60" if least else "")
    return rf"""WITH x AS (SELECT page_id, url, lower(regexp_extract(html, '<h1>([^<]*)</h1>', 1)) AS key, {SCORE} AS score, {USABLE} AS reason, array_to_string(regexp_extract_all(html, '<p>([^<]+)</p>', 1), ' ') AS text, substr(html, 1, 200) AS snippet FROM pages),
t1 AS (SELECT key, arg_min(text, page_id) AS evidence FROM x WHERE page_id % 5 = 0 GROUP BY key),
r AS (SELECT *, row_number() OVER (PARTITION BY key ORDER BY score DESC NULLS LAST, url) AS rank FROM x WHERE {rule}),
t2 AS (SELECT key, string_agg(CASE WHEN text = '' THEN snippet ELSE text END, chr(10) ORDER BY rank) AS evidence FROM r WHERE rank <= 3 AND key NOT IN (SELECT key FROM t1) GROUP BY key),
e AS (SELECT key, 1 AS tier, evidence FROM t1 UNION ALL SELECT key, 2, evidence FROM t2)
SELECT tier, count(*) AS subjects, CAST(sum(length(evidence)) AS BIGINT) AS chars FROM (SELECT DISTINCT key FROM x) LEFT JOIN e USING (key) GROUP BY tier"""


CELLS = f"""{CLAIM}, v AS (SELECT article_id, verdict, l_linestatus AS sg, CAST(l_suppkey % 2 AS INT) AS prompt, CAST(l_partkey % 2 AS INT) AS reasoning FROM claim), {rates('sg, prompt, reasoning')},
c AS (SELECT sg, prompt, reasoning, {TR} FROM (SELECT *, row_number() OVER (PARTITION BY sg, prompt, reasoning ORDER BY md5('42:' || article_id), article_id) AS i FROM r) WHERE i <= 500 GROUP BY ALL)"""
_SIGN = {"sg": "CASE WHEN sg = (SELECT max(sg) FROM c) THEN 1 ELSE -1 END", "prompt": "CASE WHEN prompt = 1 THEN 1 ELSE -1 END", "reasoning": "CASE WHEN reasoning = 1 THEN 1 ELSE -1 END"}


def _effects_sql() -> str:
    from itertools import combinations

    rows = []
    for k in (1, 2, 3):
        for group in combinations(_SIGN, k):
            sign = " * ".join(f"({_SIGN[f]})" for f in group)
            rows.append(f"SELECT '{' x '.join(group)}' AS effect, round(avg(true_rate) FILTER (WHERE {sign} > 0) - avg(true_rate) FILTER (WHERE {sign} < 0) + 1e-9, 6) AS points FROM c")
    return f"WITH {CELLS} " + " UNION ALL ".join(rows)


def _byte(c: str, i: int) -> str:
    return f"CAST('0x' || substr(md5({c}), {i}, 2) AS INT)"


LEXICON = f"""WITH {DOCS}, words AS (SELECT DISTINCT {_byte('entry', 3)} % 24 AS dimension, entry, {_byte('entry', 5)} % 8 = 0 AS ph FROM (SELECT DISTINCT unnest(w) AS entry FROM doc) WHERE {_byte('entry', 1)} % 4 = 0),
one AS (SELECT part, unnest(w) AS entry FROM doc), two AS (SELECT part, unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS phrase FROM doc WHERE len(w) >= 2),
hit AS (SELECT part, dimension FROM one JOIN words USING (entry) UNION ALL SELECT part, dimension FROM two JOIN words ON phrase = entry || ' the' AND ph),
n AS (SELECT part, sum(len(w)) AS n FROM doc GROUP BY part), rate AS (SELECT dimension, part, round(1000 * count(*) / any_value(n) + 1e-9, 6) AS rate FROM hit JOIN n USING (part) GROUP BY ALL),
wide AS (SELECT dimension, coalesce(max(rate) FILTER (WHERE part = 0), 0) AS rate_0, coalesce(max(rate) FILTER (WHERE part = 1), 0) AS rate_1, coalesce(max(rate) FILTER (WHERE part = 2), 0) AS rate_2 FROM rate GROUP BY dimension)
SELECT *, CASE greatest(rate_0, rate_1, rate_2) WHEN rate_0 THEN '0' WHEN rate_1 THEN '1' ELSE '2' END AS top_persona FROM wide"""
SHARED = f"""both_c AS (SELECT key FROM m GROUP BY key HAVING count(*) = 3), v AS (SELECT article_id, verdict, model, CASE WHEN l_partkey IN (SELECT key FROM both_c) THEN 'shared' ELSE 'independent' END AS condition FROM claim JOIN (SELECT article_id, CAST(model AS INT) AS model FROM art) USING (article_id) JOIN (SELECT model, key AS l_partkey FROM m) USING (model, l_partkey))"""
TFIDF = f"""tf AS MATERIALIZED (SELECT doc_id AS id, term, count(*) AS tf FROM (SELECT doc_id, unnest(w) AS term FROM doc) GROUP BY ALL), df AS (SELECT term, count(*) AS df FROM tf GROUP BY term),
raw AS (SELECT id, term, tf * (ln((1 + (SELECT count(*) FROM documents)) / (1 + df)) + 1) AS w FROM tf JOIN df USING (term)), wt AS MATERIALIZED (SELECT id, term, w / sqrt(sum(w * w) OVER (PARTITION BY id)) AS w FROM raw)"""

from .oracles import MEMBERS  # noqa: E402

ORACLES = {
    "persona_structure": f"WITH {DOCS} SELECT a.lang, a.part AS pa, b.part AS pb, count(*) AS n, round(avg({_j('a.o', 'b.o')}) + 1e-9, 6) AS outline_j, "
    + ", ".join(f"round(avg({_j(f'a.g{n}', f'b.g{n}')}) + 1e-9, 6) AS gram{n}_j" for n in (1, 2, 3))
    + ", round(avg(CASE WHEN list_sum(a.f) > 0 AND list_sum(b.f) > 0 THEN list_cosine_similarity(a.f, b.f) END) + 1e-9, 6) AS function_cos FROM g a JOIN g b ON a.slot = b.slot AND a.lang = b.lang AND a.part < b.part GROUP BY ALL",
    "persona_shape": f"WITH {DOCS} SELECT part AS persona, round(avg(len(w) / nullif(len(list_filter(string_split_regex(text, '[.!?]+'), lambda x: trim(x) <> '')), 0)) + 1e-9, 6) AS sentence_length, round(avg(len(g1) / nullif(len(w), 0)) + 1e-9, 6) AS type_token, round(avg(1000 * (len(list_filter(w, lambda x: x IN {tuple(GOOD)})) - len(list_filter(w, lambda x: x IN {tuple(BAD)}))) / nullif(len(w), 0)) + 1e-9, 6) AS sentiment FROM g GROUP BY part",
    "trap_table": f"WITH {DOCS}, {TFIDF}, p AS (SELECT a.doc_id AS a, b.doc_id AS b, CASE a.part WHEN 0 THEN 'ours' ELSE 'rival' END AS system, {_j('a.g1', 'b.g1')} AS j1, {_j('a.g2', 'b.g2')} AS j2, CASE WHEN b.g3 IS NOT NULL THEN len(list_intersect(a.g3, b.g3)) / nullif(len(a.g3), 0) END AS c3 FROM g a JOIN g b ON a.slot = b.slot AND a.lang = b.lang AND a.part < 2 AND b.part = 2), dot AS (SELECT a, b, sum(x.w * y.w) AS c FROM p JOIN wt x ON x.id = a JOIN wt y ON y.id = b AND y.term = x.term GROUP BY ALL), y AS (SELECT system, count(*) AS pairs, round(avg(coalesce(c, 0)), 5) AS tfidf, round(stddev_samp(coalesce(c, 0)), 5) AS tfidf_sd, round(avg(j1) + 1e-9, 6) AS token_jaccard, round(avg(j2) + 1e-9, 6) AS bigram_jaccard, round(avg(c3) + 1e-9, 6) AS trigram_containment FROM p LEFT JOIN dot USING (a, b) GROUP BY system) SELECT *, round(tfidf / nullif((SELECT tfidf FROM y WHERE system = 'ours'), 0), 4) AS tfidf_ratio FROM y",
    "trap_titles": f"WITH {ART} SELECT l_partkey AS subject, count(*) AS edits FROM lineitem WHERE l_partkey IN (SELECT l_partkey FROM lineitem JOIN art ON l_orderkey = article_id WHERE model = 1) GROUP BY 1 ORDER BY edits DESC, subject LIMIT 1000",
    "trap_contrast": f"WITH {ART}, {CLAIM}, v AS (SELECT * FROM claim JOIN art USING (article_id) WHERE model IN (0, 1)), {rates('model, tier')}, m AS (SELECT model, tier, {TR}, {FR} FROM r GROUP BY ALL) SELECT tier, round(100 * (max(true_rate) FILTER (WHERE model = 0) - max(true_rate) FILTER (WHERE model = 1)) + 1e-9, 6) AS lead_points, round(max(false_rate) FILTER (WHERE model = 1) / nullif(max(false_rate) FILTER (WHERE model = 0), 0), 4) AS false_ratio FROM m GROUP BY tier",
    "lexicon_scores": LEXICON,
    "text_claims": f"WITH {CLAIMS_TEXT} SELECT doc_id, count(*) AS claims, CAST(sum(length(claim)) AS BIGINT) AS chars FROM claim GROUP BY doc_id",
    "text_verdicts": f"{JUDGED} SELECT verdict, count(*) AS claims, count(DISTINCT doc_id) AS documents FROM j GROUP BY verdict",
    "text_error_types": f"{JUDGED} SELECT {ERROR} AS error_type, count(*) AS claims FROM j WHERE verdict = 'refuted' GROUP BY 1",
    "evidence_tiers": _evidence_sql(True),
    "evidence_open_web": _evidence_sql(False),
    "human_confusion": f"WITH {HUMAN}, b AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY judge ORDER BY md5('42:' || doc_id), doc_id) AS r FROM h) WHERE r <= 33) SELECT judge AS class, count(*) FILTER (WHERE human = 'supported') AS human_supported, count(*) FILTER (WHERE human = 'refuted') AS human_refuted, count(*) FILTER (WHERE human = 'insufficient') AS human_insufficient FROM b GROUP BY judge",
    "ablation_effects": _effects_sql(),
    "ablation_choice": f"WITH {CELLS}, k AS (SELECT *, round(CASE WHEN sg = 'O' THEN 1.33 ELSE 1.0 END * CASE WHEN reasoning = 1 THEN 2.0 ELSE 1.0 END, 4)::DOUBLE AS cost FROM c) SELECT sg, prompt, reasoning, true_rate, cost FROM k WHERE true_rate >= (SELECT max(true_rate) FROM k) - 0.02 ORDER BY cost, true_rate DESC, sg, prompt, reasoning LIMIT 1",
    "condition_stability": f"WITH {MEMBERS}, {CLAIM}, {SHARED}, {rates('model, condition')}, q AS (SELECT model, condition, {P} FROM r GROUP BY ALL), wd AS (SELECT model, max(precision) FILTER (WHERE condition = 'shared') AS first, max(precision) FILTER (WHERE condition = 'independent') AS second FROM q GROUP BY model), k AS (SELECT x.*, 1 + (SELECT count(*) FROM wd y WHERE y.first > x.first) AS rank_first, 1 + (SELECT count(*) FROM wd y WHERE y.second > x.second) AS rank_second FROM wd x) SELECT *, round(first - second + 1e-9, 6) AS drop, rank_first = rank_second AS stable FROM k",
    "quiz_gap": f"WITH {CLAIM}, r AS (SELECT avg(CAST(verdict = 'supported' AS INT)) AS t FROM claim GROUP BY article_id), a AS (SELECT (SELECT avg(quality) FROM labels) AS q, (SELECT avg(t) FROM r) AS o) SELECT round(q + 1e-9, 6) AS quiz, round(o + 1e-9, 6) AS open_rate, round(100 * (q - o) + 1e-9, 6) AS gap_points FROM a",
    "stage_modes": "WITH w AS (SELECT p_partkey, unnest(string_split(p_name || ' ' || p_type, ' ')) AS x FROM part) SELECT (SELECT count(*) FROM part) AS requests, (SELECT count(*) FROM w WHERE least(1.0, 0.5 + length(x) / 16) >= 0.75) AS facts, CAST(0 AS BIGINT) AS differing",
    "frontier_sample": f"SELECT CASE WHEN doc_id IN (SELECT doc_id FROM labels) THEN 'covered' ELSE 'frontier' END AS part, count(*) AS n, round(avg(len({TOK})) + 1e-9, 6) AS mean_words FROM (SELECT doc_id, text FROM documents ORDER BY md5('42:' || doc_id), doc_id LIMIT 400) GROUP BY 1",
    "topic_cells": f"WITH {ART}, {CLAIM}, v AS (SELECT * FROM claim JOIN art USING (article_id) WHERE model < 3 AND topic IN ('BUILDING', 'FURNITURE', 'MACHINERY')), {rates('topic, model, persona, subject')} SELECT topic, model, persona, count(*) AS articles, count(DISTINCT subject) AS subjects, {P} FROM r GROUP BY ALL",
}
