"""DuckDB SQL for the queries of catalog.py."""

from __future__ import annotations

ART = "art AS (SELECT o_orderkey AS article_id, o_custkey AS subject, n_regionkey AS model, c_mktsegment AS topic, o_orderstatus AS persona, CAST(substr(o_orderpriority, 1, 1) AS INT) AS hop, o_orderdate AS written FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)"
CLAIM = """claim AS (SELECT l_orderkey AS article_id, CASE l_returnflag WHEN 'A' THEN 'supported' WHEN 'R' THEN 'refuted' ELSE 'insufficient' END AS verdict, CASE WHEN l_linestatus = 'O' THEN 1 ELSE 2 END AS tier, l_partkey, l_suppkey, l_linestatus
  FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS i FROM lineitem) WHERE i <= 10)"""
V = f"{ART}, {CLAIM}, v AS (SELECT * FROM claim JOIN art USING (article_id))"


def rates(keys: str, source: str = "v") -> str:
    return f"""r AS (SELECT article_id, {keys}, s / nullif(s + f, 0) AS p, s / n AS t, f / n AS fr, u / n AS ur FROM (SELECT article_id, {keys}, CAST(count(*) AS DOUBLE) AS n,
  CAST(count(*) FILTER (WHERE verdict = 'supported') AS DOUBLE) AS s, CAST(count(*) FILTER (WHERE verdict = 'refuted') AS DOUBLE) AS f, CAST(count(*) FILTER (WHERE verdict = 'insufficient') AS DOUBLE) AS u FROM {source} GROUP BY article_id, {keys}))"""


P, TR, FR, UR = "round(avg(p) + 1e-9, 6) AS precision", "round(avg(t) + 1e-9, 6) AS true_rate", "round(avg(fr) + 1e-9, 6) AS false_rate", "round(avg(ur) + 1e-9, 6) AS unv_rate"
LINK = "link AS (SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber AND a.l_partkey <> b.l_partkey WHERE a.l_returnflag = 'A' AND b.l_returnflag = 'A')"


def bfs(links: str, seed: str, depth: int) -> str:
    return f"WITH RECURSIVE {links}, walk(key, hop) AS ({seed} UNION SELECT dst, hop + 1 FROM walk JOIN link ON src = key WHERE hop < {depth}), found AS (SELECT key, min(hop) AS hop FROM walk GROUP BY key)"


def levels(links: str, seed: str, waves: int = 16) -> str:
    """CTEs up to found (key, hop) of a walk to its fixed point, a CTE for each wave: every key is kept once."""
    parts = [links, f"v0 AS ({seed})", "s0 AS (SELECT key FROM v0)"]
    for t in range(1, waves + 1):
        parts.append(f"v{t} AS MATERIALIZED (SELECT DISTINCT dst AS key, {t} AS hop FROM v{t - 1} JOIN link ON src = key WHERE dst NOT IN (SELECT key FROM s{t - 1}))")
        parts.append(f"s{t} AS MATERIALIZED (SELECT key FROM s{t - 1} UNION ALL SELECT key FROM v{t})")
    return "WITH " + ", ".join(parts) + ", found AS (" + " UNION ALL ".join(f"SELECT * FROM v{t}" for t in range(waves + 1)) + ")"


TEXT_LINK = r"""word AS (SELECT DISTINCT doc_id, lower(regexp_extract(x, '^([\p{L}\p{N}]+)', 1)) AS key FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE regexp_matches(x, '^[\p{L}\p{N}]')),
home AS (SELECT key, arg_min(doc_id, md5('42:' || key || ':' || doc_id)) AS doc_id FROM word GROUP BY key),
link AS (SELECT home.key AS src, word.key AS dst FROM home JOIN word USING (doc_id) WHERE home.key <> word.key)"""
TOK = r"regexp_extract_all(lower(text), '[\p{L}\p{N}_]+')"
MEMBERS = f"""{ART}, first AS (SELECT model, l_partkey AS key, min(written) AS t FROM lineitem JOIN art ON l_orderkey = article_id WHERE model < 3 GROUP BY ALL),
m AS (SELECT CAST(model AS INT) AS model, key FROM (SELECT *, row_number() OVER (PARTITION BY model ORDER BY t, key) AS r FROM first) WHERE r <= 600)"""


def funnel(by: str) -> str:
    return f"""WITH {ART}, x AS (SELECT {by}, article_id, l_partkey AS key, p_size, p_name FROM lineitem JOIN art ON l_orderkey = article_id JOIN part ON p_partkey = l_partkey)
SELECT {by}, count(*) AS raw, count(DISTINCT (article_id, key)) AS pre_filter, count(DISTINCT key) AS after_canon, count(DISTINCT key) FILTER (WHERE p_size > 10) AS after_filter,
  count(DISTINCT p_name) FILTER (WHERE p_size > 10) AS after_sim, round(count(DISTINCT p_name) FILTER (WHERE p_size > 10) / count(*), 6) AS raw_to_queue FROM x GROUP BY {by}"""


HUMAN = "h AS (SELECT doc_id, CASE WHEN toxic = 1 THEN 'refuted' WHEN quality = 1 THEN 'supported' ELSE 'insufficient' END AS human, CASE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 2) AS INT) % 3 WHEN 0 THEN 'supported' WHEN 1 THEN 'refuted' ELSE 'insufficient' END AS judge FROM labels)"
HOST = "lower(regexp_extract(url, '^[a-zA-Z]+://([^/:?#]+)', 1))"
SCORE = f"CASE WHEN {HOST} = 'example.org' OR {HOST} LIKE '%.example.org' THEN NULL WHEN {HOST} = 'blog.thering.example.net' OR {HOST} LIKE '%.blog.thering.example.net' THEN 65 WHEN {HOST} = 'example.com' OR {HOST} LIKE '%.example.com' THEN 80 WHEN regexp_matches({HOST}, '\\.(edu|gov|org)$') THEN 70 WHEN url LIKE 'https://%' THEN 35 ELSE 0 END"
BODY = r"length(regexp_replace(regexp_replace(html, '<script.*?</script>|<style.*?</style>', '', 'gs'), '<[^>]*>', '', 'g'))"
USABLE = rf"CASE WHEN regexp_matches(html, '(?i)captcha|are you a robot') THEN 'captcha' WHEN regexp_matches(html, '(?i)subscribe to (read|continue)') THEN 'paywall' WHEN {BODY} < 200 THEN 'too_short' ELSE 'usable' END"
SENT = r"list_transform(string_split_regex({}, '[.!?]+\s+|\n+'), lambda x: trim(regexp_replace(x, '[.!?\s]+$', '')))"


def tests(models: str, topics: str, dims: int) -> str:
    return f"""WITH {ART}, a AS (SELECT * FROM art WHERE model IN ({models}) AND topic IN ({topics})),
chosen AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY model, topic ORDER BY md5('42:' || subject), subject) AS r FROM (SELECT model, topic, subject FROM a GROUP BY ALL HAVING count(DISTINCT persona) = 3)) WHERE r <= 30),
x AS (SELECT a.model, a.topic, a.subject, a.persona, CAST(regexp_extract(p_brand, '(\\d+)$', 1) AS INT) AS dim, l_quantity FROM lineitem JOIN a ON l_orderkey = article_id JOIN chosen USING (model, topic, subject) JOIN part ON p_partkey = l_partkey),
size AS (SELECT model, topic, subject, persona, sum(l_quantity) AS q FROM x GROUP BY ALL), hits AS (SELECT model, topic, subject, persona, dim, count(*) AS h FROM x GROUP BY ALL),
rate AS (SELECT s.*, g.dim, round(1000 * coalesce(h, 0) / q, 9) AS rate FROM size s CROSS JOIN (SELECT CAST(unnest(range(1, {dims + 1})) AS INT) AS dim) g LEFT JOIN hits USING (model, topic, subject, persona, dim)),
df AS (SELECT a.model, a.topic, a.persona AS pa, b.persona AS pb, a.dim, round(a.rate - b.rate, 9) AS d FROM rate a JOIN rate b USING (model, topic, subject, dim) WHERE a.persona < b.persona),
rk AS (SELECT *, rank() OVER (PARTITION BY model, topic, pa, pb, dim ORDER BY abs(d)) + (count(*) OVER (PARTITION BY model, topic, pa, pb, dim, abs(d)) - 1) / 2.0 AS rank, count(*) OVER (PARTITION BY model, topic, pa, pb, dim, abs(d)) AS ties FROM df WHERE d <> 0),
w AS (SELECT model, topic, pa, pb, dim, count(*) AS n, CAST(coalesce(sum(rank) FILTER (WHERE d > 0), 0) AS DOUBLE) AS w_plus, CAST(coalesce(sum(rank) FILTER (WHERE d < 0), 0) AS DOUBLE) AS w_minus, sum(CAST(ties AS DOUBLE) * ties - 1) AS tie_sum FROM rk GROUP BY ALL),
z AS (SELECT *, round((w_plus - n * (n + 1) / 4.0) / sqrt(n * (n + 1) * (2 * n + 1) / 24.0 - tie_sum / 48.0), 6) AS z, round((w_plus - w_minus) / (w_plus + w_minus), 6) AS r_rb FROM w)"""


# The null distribution of the smaller rank sum: c[s + 1] subsets of 1..k have the sum s. erf by its series without cancellation.
NULLS = """ways(k, c) AS (SELECT 0, [1.0::DOUBLE] UNION ALL SELECT k + 1, list_transform(range(1, len(c) + k + 2), lambda i: coalesce(c[i], 0) + CASE WHEN i - k - 1 >= 1 THEN coalesce(c[i - k - 1], 0) ELSE 0 END) FROM ways WHERE k < 50)"""
ERF = "(exp(-z * z / 2) * list_sum(list_transform(range(0, 120), lambda i: pow(abs(z) / sqrt(2), 2 * i + 1) / gamma(i + 1.5))))"


def with_p(models: str, topics: str, dims: int, m: int) -> str:
    """CTEs up to t: the tests with p and p_bonf over m tests."""
    return tests(models, topics, dims).replace("WITH ", f"WITH RECURSIVE {NULLS}, ", 1) + f""",
mean AS (SELECT model, topic, pa, pb, dim, round(avg(d) + 1e-12, 6) AS mean_d FROM df GROUP BY ALL),
t AS (SELECT z.*, mean_d, CASE WHEN tie_sum = 0 AND n <= 50 THEN least(1.0, 2 * list_sum(c[1:CAST(floor(least(w_plus, w_minus)) AS INT) + 1]) / pow(2, n)) ELSE 1 - {ERF} END AS p, {m} AS m FROM z JOIN mean USING (model, topic, pa, pb, dim) LEFT JOIN ways ON k = n)"""


GRADIENT = " SELECT topic, count(*) AS tests, CAST(sum(CAST(p < 0.05 AS INT)) AS BIGINT) AS raw_significant, max(abs(z)) AS max_z FROM t GROUP BY topic"
PRIMARY_P = with_p("0, 1, 2", "'BUILDING', 'FURNITURE', 'MACHINERY'", 24, 648)


ORACLES = {
    "embed_lsh_recall": "WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) SELECT count(*) AS pairs, true AS enough FROM v a JOIN v b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.e, b.e) > 0.3",
    "reject_reasons_stage2": r"SELECT reason, count(*) AS n, round(count(*) / sum(count(*)) OVER () + 1e-9, 6) AS share FROM (SELECT CASE WHEN regexp_matches(x, '(?i)^https?://|\.(com|org|net)$') THEN 'url' WHEN regexp_matches(x, '^[\d.,\s%-]+$') THEN 'number_or_date' WHEN lower(x) IN ('history', 'culture', 'science', 'people', 'language', 'music', 'art', 'war', 'city', 'country', 'year', 'author', 'member', 'system') THEN 'generic' WHEN len(string_split_regex(x, '\s+')) > 8 THEN 'too_long' WHEN length(x) < 2 THEN 'too_short' ELSE 'accepted' END AS reason FROM (SELECT unnest(string_split(text, chr(10))) AS x FROM documents)) GROUP BY reason",
    "user_sessions": "WITH x AS (SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS first, ts FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT user_id, sum(first) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM x), z AS (SELECT user_id, k, count(*) AS n FROM y GROUP BY ALL) SELECT count(DISTINCT user_id) AS users, count(*) AS sessions, CAST(sum(n) AS BIGINT) AS events, max(n) AS longest FROM z",
    "late_events": "SELECT event_type, count(*) AS n, CAST(sum(CAST(coalesce(ts < ahead - INTERVAL 1 HOUR, false) AS INT)) AS BIGINT) AS late FROM (SELECT *, max(ts) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS ahead FROM events) GROUP BY event_type",
    "as_of_price": "WITH p AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY ALL) SELECT count(*) AS clicks, count(p.value) AS priced, round(sum(p.value), 2) AS total FROM (SELECT * FROM events WHERE event_type = 'click') c ASOF LEFT JOIN p ON c.user_id = p.user_id AND c.ts >= p.ts",
    "band_counts": "SELECT p.user_id, count(*) AS n FROM events p JOIN events c ON p.user_id = c.user_id AND p.event_type = 'purchase' AND c.event_type = 'click' AND p.value BETWEEN c.value - 1 AND c.value + 1 GROUP BY 1",
    "salted_mentions": "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY 1",
    "contest_gradient": "SELECT * FROM (" + with_p("0, 2", "'BUILDING', 'FURNITURE', 'MACHINERY'", 8, 216) + GRADIENT + ") UNION ALL SELECT * FROM (" + with_p("0, 2", "'AUTOMOBILE', 'HOUSEHOLD'", 8, 96) + GRADIENT + ")",
    "shift_report": PRIMARY_P + " SELECT model, topic, dim, CASE WHEN mean_d > 0 THEN pa ELSE pb END AS higher, CASE WHEN mean_d > 0 THEN pb ELSE pa END AS lower, round(abs(mean_d) + 1e-9, 6) AS shift, round(p, 6) AS p FROM t WHERE p < 0.05 AND abs(mean_d) >= 0.5",
    "wilcoxon_significance": PRIMARY_P + " SELECT count(*) AS tests, CAST(sum(CAST(least(1.0, p * m) < 0.05 AS INT)) AS BIGINT) AS significant, round(min(p), 6) AS least_p, round(avg(p), 6) AS mean_p FROM t",
    "hop_factuality": f"WITH {V}, {rates('hop')} SELECT hop, count(*) AS articles, count(p) AS decided_articles, {P}, {TR}, {FR}, {UR} FROM r GROUP BY hop",
    "hop_factuality_micro": f"WITH {V} SELECT hop, count(*) AS claims, round(avg(CAST(verdict = 'supported' AS INT)), 6) AS true_rate, round(avg(CAST(verdict = 'refuted' AS INT)), 6) AS false_rate, round(avg(CAST(verdict = 'insufficient' AS INT)), 6) AS unv_rate FROM v GROUP BY hop",
    "tier_factuality": f"WITH {V}, {rates('tier')} SELECT tier, count(*) AS articles, {P}, {TR}, {FR}, {UR}, round(stddev_samp(t), 6) AS true_sd FROM r GROUP BY tier",
    "persona_cells": f"WITH {V}, {rates('topic, model, persona')} SELECT topic, model, persona, count(*) AS articles, count(p) AS decided_articles, {P}, {FR}, {UR} FROM r GROUP BY ALL",
    "topic_model_table": f"WITH {V}, {rates('topic, model, persona')}, c AS (SELECT topic, model, persona, {P}, {FR}, {UR} FROM r GROUP BY ALL) SELECT topic, model, round(avg(precision) + 1e-9, 6) AS precision, round(avg(false_rate) + 1e-9, 6) AS false_rate, round(avg(unv_rate) + 1e-9, 6) AS unv_rate, round(max(precision) - min(precision) + 1e-9, 6) AS persona_gap FROM c GROUP BY ALL",
    "binary_scorer": f"WITH {V}, b AS (SELECT article_id, hop, CASE WHEN verdict = 'supported' THEN verdict ELSE 'refuted' END AS verdict FROM v), {rates('hop', 'b')} SELECT hop, count(*) AS articles, {TR}, {FR} FROM r GROUP BY hop",
    "silence_rule_off": f"WITH {V}, b AS (SELECT article_id, hop, CASE WHEN verdict = 'insufficient' THEN 'refuted' ELSE verdict END AS verdict FROM v), {rates('hop', 'b')} SELECT hop, {P}, {FR} FROM r GROUP BY hop",
    "depth_trend": f"WITH {V}, {rates('hop')}, h AS (SELECT hop, {TR} FROM r GROUP BY hop) SELECT arg_min(true_rate, hop) AS first, arg_max(true_rate, hop) AS last, round(corr(hop, true_rate), 6) AS corr FROM h",
    "stratified_sample": f"WITH {ART} SELECT article_id, hop FROM (SELECT *, row_number() OVER (PARTITION BY hop ORDER BY md5('42:' || article_id), article_id) AS r FROM art) WHERE r <= 50",
    "coverage_by_source": "SELECT lang, count(*) AS sampled, count(l.doc_id) AS found, round(count(l.doc_id) / count(*), 6) AS coverage FROM documents d LEFT JOIN (SELECT DISTINCT doc_id FROM labels) l USING (doc_id) GROUP BY lang",
    "ablation_cube": f"WITH {CLAIM}, v AS (SELECT *, l_linestatus AS sg, CAST(l_suppkey % 2 AS INT) AS prompt, CAST(l_partkey % 2 AS INT) AS reasoning FROM claim), {rates('sg, prompt, reasoning')}, c AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY sg, prompt, reasoning ORDER BY md5('42:' || article_id), article_id) AS k FROM r) WHERE k <= 500) SELECT sg, prompt, reasoning, count(*) AS n, {P}, {TR}, {FR}, {UR} FROM c GROUP BY CUBE (sg, prompt, reasoning)",
    "bfs_rel_hops": levels(LINK, "SELECT CAST(0 AS BIGINT) AS key, 0 AS hop") + " SELECT hop, count(*) AS new_subjects FROM found GROUP BY hop",
    "bfs_text_hops": levels(TEXT_LINK, "SELECT 'and' AS key, 0 AS hop", 24) + " SELECT hop, count(*) AS new_subjects FROM found GROUP BY hop",
    "bfs_budget": bfs(LINK, "SELECT CAST(0 AS BIGINT), 0", 20) + ", cut AS (SELECT *, row_number() OVER (ORDER BY hop, key) AS r FROM found) SELECT hop, count(*) AS committed, max(key) AS largest FROM cut WHERE r <= 200 GROUP BY hop",
    "bfs_topic": bfs(
        "e0 AS (SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber AND a.l_partkey <> b.l_partkey WHERE a.l_returnflag = 'A' AND b.l_returnflag = 'A'), link AS (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM e0 UNION SELECT dst, src FROM e0) JOIN part ON p_partkey = dst WHERE p_type = 'ECONOMY')",
        "SELECT p_partkey, 0 FROM part WHERE p_type = 'ECONOMY' AND p_brand = 'Brand#2'",
        2,
    )
    + " SELECT hop, count(*) AS new_subjects FROM found GROUP BY hop",
    "coverage_rollup": levels(LINK, "SELECT CAST(0 AS BIGINT) AS key, 0 AS hop") + ", x AS (SELECT hop, CASE WHEN key IN (SELECT src FROM link) THEN 1 END AS e FROM found) SELECT hop, count(*) AS total, count(e) AS expanded, count(*) - count(e) AS terminal, round((count(*) - count(e)) / count(*), 6) AS terminal_share FROM x GROUP BY ROLLUP (hop)",
    "funnel_by_model": funnel("model"),
    "funnel_by_hop": funnel("hop"),
    "survival_bands": f"WITH {ART}, x AS (SELECT hop, article_id, count(DISTINCT l_partkey) FILTER (WHERE p_size > 10) / count(*) AS s FROM lineitem JOIN art ON l_orderkey = article_id JOIN part ON p_partkey = l_partkey GROUP BY ALL) SELECT hop, count(*) AS parents, round(avg(s), 6) AS mean_survival, round(stddev_samp(s), 6) AS sd_survival FROM x GROUP BY hop",
    "parse_modes": """WITH r AS (SELECT CASE event_id % 7 WHEN 1 THEN 'answer: ' || props || ' end' WHEN 2 THEN substr(props, 1, length(props) - 1) WHEN 3 THEN 'none' ELSE props END AS raw FROM events)
SELECT CASE WHEN regexp_matches(raw, '^\\s*\\{.*\\}\\s*$') THEN 'native' WHEN regexp_matches(raw, '\\{[^{}]*\\}') THEN 'substring' WHEN regexp_matches(raw, '"k"\\s*:\\s*\\d+') THEN 'regex' ELSE 'exception' END AS mode, count(*) AS n FROM r GROUP BY mode""",
    "insert_loss": levels(LINK, "SELECT CAST(0 AS BIGINT) AS key, 0 AS hop") + ", o AS (SELECT dst FROM link JOIN found a ON a.key = src JOIN found b ON b.key = dst WHERE b.hop > a.hop) SELECT count(*) AS accepted, count(DISTINCT dst) AS inserted, round(1 - count(DISTINCT dst) / count(*), 6) AS loss FROM o",
    "alias_summary": "WITH g AS (SELECT count(*) - 1 AS a FROM documents GROUP BY text HAVING count(*) > 1) SELECT count(*) AS entities, CAST(sum(a) AS BIGINT) AS aliases, round(avg(a), 6) AS mean_aliases FROM g",
    "alias_top30": "SELECT min(doc_id) AS canon, count(*) - 1 AS aliases FROM documents GROUP BY text HAVING count(*) > 1 ORDER BY aliases DESC, canon LIMIT 30",
    "embed_pairs": "WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) SELECT a.vec_id AS id_a, b.vec_id AS id_b, round(list_cosine_similarity(a.e, b.e), 5) AS cosine FROM v a JOIN v b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.e, b.e) > 0.3",
    "subject_overlap": f"WITH {MEMBERS}, g AS (SELECT key, count(*) AS c FROM m GROUP BY key) SELECT count(*) AS union_n, count(*) FILTER (WHERE c = 3) AS inter_n, round(count(*) FILTER (WHERE c = 3) / count(*), 6) AS share FROM g",
    "pairwise_jaccard": f"WITH {MEMBERS}, i AS (SELECT a.model AS model_a, b.model AS model_b, count(*) AS c FROM m a JOIN m b USING (key) WHERE a.model < b.model GROUP BY ALL), n AS (SELECT model, count(*) AS n FROM m GROUP BY model) SELECT model_a, model_b, round(c / (x.n + y.n - c), 6) AS jaccard FROM i JOIN n x ON x.model = model_a JOIN n y ON y.model = model_b",
    "entity_jaccard": f"WITH {ART}, l AS (SELECT DISTINCT topic, CAST(model AS INT) AS model, l_partkey AS key FROM lineitem JOIN art ON l_orderkey = article_id WHERE model < 3), n AS (SELECT topic, model, count(*) AS n FROM l GROUP BY ALL), i AS (SELECT a.topic, a.model AS model_a, b.model AS model_b, count(*) AS c FROM l a JOIN l b USING (topic, key) WHERE a.model < b.model GROUP BY ALL) SELECT model_a, model_b, round(avg(c / (x.n + y.n - c)), 6) AS jaccard FROM i JOIN n x ON x.model = model_a AND x.topic = i.topic JOIN n y ON y.model = model_b AND y.topic = i.topic GROUP BY ALL",
    "corpus_profile": f"WITH x AS (SELECT lang, len({TOK}) AS w, len(string_split(text, chr(10))) AS l FROM documents) SELECT lang, count(*) AS articles, round(avg(w), 6) AS mean_words, quantile_cont(w, 0.5) AS median_words, round(avg(l), 6) AS mean_lines FROM x GROUP BY lang",
    "shared_vs_independent": f"WITH {MEMBERS}, {CLAIM}, b AS (SELECT key FROM m GROUP BY key HAVING count(*) = 3), v AS (SELECT article_id, verdict, m.model, CASE WHEN b.key IS NULL THEN 'independent' ELSE 'shared' END AS condition FROM claim JOIN art USING (article_id) JOIN m ON m.model = art.model AND m.key = l_partkey LEFT JOIN b ON b.key = m.key), {rates('model, condition')} SELECT model, condition, count(*) AS n, {P}, {TR} FROM r GROUP BY ALL",
    "trap_similarity": f"""WITH t AS (SELECT doc_id AS id, unnest({TOK}) AS term FROM documents), tf AS (SELECT id, term, count(*) AS tf FROM t GROUP BY ALL), df AS (SELECT term, count(*) AS df FROM tf GROUP BY term),
raw AS (SELECT id, term, tf * (ln((1 + (SELECT count(*) FROM documents)) / (1 + df)) + 1) AS w FROM tf JOIN df USING (term)), nm AS (SELECT id, sqrt(sum(w * w)) AS n FROM raw GROUP BY id), u AS (SELECT id, term, w / n AS w FROM raw JOIN nm USING (id)),
p AS (SELECT x.doc_id AS a, y.doc_id AS b FROM documents x JOIN documents y ON y.doc_id = x.doc_id + 1 AND x.lang = y.lang AND x.source = y.source), dot AS (SELECT a, b, sum(x.w * y.w) AS c FROM p JOIN u x ON x.id = a JOIN u y ON y.id = b AND y.term = x.term GROUP BY ALL)
SELECT count(*) AS pairs, round(avg(coalesce(c, 0)), 5) AS mean_cosine, round(stddev_samp(coalesce(c, 0)), 5) AS sd_cosine FROM p LEFT JOIN dot USING (a, b)""",
    "text_overlap": f"""WITH w AS (SELECT doc_id, {TOK} AS w FROM documents), g AS (SELECT doc_id, list_distinct(w) AS u, CASE WHEN len(w) >= 3 THEN list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS t FROM w),
p AS (SELECT x.doc_id AS a, y.doc_id AS b FROM documents x JOIN documents y ON y.doc_id = x.doc_id + 1 AND x.lang = y.lang AND x.source = y.source)
SELECT round(avg(len(list_intersect(x.u, y.u)) / nullif(len(list_distinct(list_concat(x.u, y.u))), 0)), 6) AS token_jaccard, round(avg(CASE WHEN x.t IS NULL OR y.t IS NULL THEN NULL ELSE len(list_intersect(x.t, y.t)) / nullif(len(list_distinct(list_concat(x.t, y.t))), 0) END), 6) AS trigram_jaccard FROM p JOIN g x ON x.doc_id = a JOIN g y ON y.doc_id = b""",
    "trap_lengths": f"WITH x AS (SELECT CASE WHEN doc_id % 2 = 0 THEN 'ours' ELSE 'rival' END AS system, len({TOK}) AS w FROM documents) SELECT system, round(avg(w), 6) AS mean, quantile_cont(w, 0.5) AS median FROM x GROUP BY system",
    "trap_factuality": f"WITH {V}, s AS (SELECT *, CASE model WHEN 0 THEN 'ours' ELSE 'rival' END AS system FROM v WHERE model IN (0, 1)), {rates('system, tier', 's')} SELECT system, tier, count(*) AS articles, {P}, {TR}, {FR}, {UR}, round(stddev_samp(t), 6) AS true_sd FROM r GROUP BY ALL",
    "tool_traces": "SELECT conv_id, CAST(len(regexp_extract_all(string_agg(concat_ws(': ', role, text), chr(10) ORDER BY turn, role, text), '(?m)^(user|assistant|system|tool): ')) AS INT) AS markers FROM conversations GROUP BY conv_id HAVING markers > 0",
    "slot_verdicts": """WITH x AS (SELECT l_shipdate < o_orderdate AS late, s_nationkey, c_nationkey, floor(l_quantity) AS q, CASE WHEN p_retailprice > 0 THEN floor(l_extendedprice / p_retailprice) END AS e FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey),
s AS (SELECT 'temporal' AS predicate, CASE WHEN late THEN 'refuted' ELSE 'supported' END AS verdict FROM x UNION ALL SELECT 'spatial', CASE WHEN s_nationkey = c_nationkey THEN 'supported' ELSE 'refuted' END FROM x UNION ALL SELECT 'numerical', CASE WHEN e IS NULL THEN 'insufficient' WHEN q = e OR abs(q - e) <= 0.01 * abs(e) THEN 'supported' ELSE 'refuted' END FROM x)
SELECT predicate, verdict, CASE WHEN verdict = 'refuted' THEN predicate END AS error_type, count(*) AS n FROM s GROUP BY ALL""",
    "coercion_rate": "SELECT count(*) AS initially_refuted, count(*) FILTER (WHERE event_type IN ('view', 'error')) AS coerced, round(count(*) FILTER (WHERE event_type IN ('view', 'error')) / count(*), 6) AS rate FROM events",
    "human_agreement": f"WITH {HUMAN}, c AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY judge ORDER BY md5('42:' || doc_id), doc_id) AS r FROM h) WHERE r <= 33) SELECT judge AS class, count(*) AS n, count(*) FILTER (WHERE judge = human) AS agree, round(count(*) FILTER (WHERE judge = human) / count(*), 6) AS rate FROM c GROUP BY judge",
    "human_drift": f"WITH {HUMAN}, j AS (SELECT judge AS class, count(*) AS judge_n FROM h GROUP BY judge), k AS (SELECT human AS class, count(*) AS human_n FROM h GROUP BY human) SELECT class, coalesce(judge_n, 0) AS judge_n, coalesce(human_n, 0) AS human_n, coalesce(human_n, 0) - coalesce(judge_n, 0) AS drift FROM j FULL JOIN k USING (class)",
    "domain_scores": f"SELECT page_id, {HOST} AS host, {SCORE} AS score, coalesce({SCORE} >= 60, false) AS eligible FROM pages",
    "page_usability": f"SELECT {USABLE} AS reason, count(*) AS n FROM pages GROUP BY reason",
    "evidence_top3": f"WITH x AS (SELECT page_id, url, lower(regexp_extract(html, '<h1>([^<]*)', 1)) AS subject, {SCORE} AS score, {USABLE} AS reason FROM pages) SELECT subject, CAST(rank AS INT) AS rank, page_id, score FROM (SELECT *, row_number() OVER (PARTITION BY subject ORDER BY score DESC, url) AS rank FROM x WHERE score >= 60 AND reason = 'usable') WHERE rank <= 3",
    "markup_links": r"""SELECT page_id, CAST(i - 1 AS BIGINT) AS position, trim(string_split(l[i], '|')[1]) AS target FROM (SELECT page_id, l, unnest(range(1, len(l) + 1)) AS i FROM (SELECT page_id, list_filter(regexp_extract_all(html, '<a href="/[^"]*">([^<]*)</a>', 1), lambda x: x <> '' AND NOT regexp_matches(x, '[\[\]]')) AS l FROM pages))""",
    "conflation": "SELECT l_partkey AS subject, 'supplier' AS predicate, count(DISTINCT l_suppkey) AS n_objects FROM lineitem GROUP BY l_partkey HAVING count(DISTINCT l_suppkey) > 1",
    "run_cost": "WITH g AS (SELECT event_type AS stage, count(*) AS calls, round(sum(value), 2) AS tokens, round(sum(value * CASE event_type WHEN 'view' THEN 0.5 WHEN 'purchase' THEN 2.0 ELSE 1.0 END / 1000), 4) AS cost_online FROM events GROUP BY event_type) SELECT *, round(cost_online / 2, 4) AS cost_batch FROM g",
    "framing_hits": f"WITH t AS (SELECT lang, unnest({TOK}) AS tok FROM documents), n AS (SELECT lang, count(*) AS n_tokens FROM t GROUP BY lang), x(dimension, entry) AS (VALUES ('hedging', 'that'), ('hedging', 'with'), ('assertive', 'the'), ('assertive', 'is'), ('rare', 'scum'), ('rare', 'clown')), h AS (SELECT lang, dimension, count(*) AS hits FROM t JOIN x ON tok = entry GROUP BY ALL) SELECT lang, dimension, n_tokens, coalesce(hits, 0) AS hits, round(1000 * coalesce(hits, 0) / n_tokens, 6) AS hits_per_1k FROM n CROSS JOIN (SELECT DISTINCT dimension FROM x) LEFT JOIN h USING (lang, dimension)",
    "wilcoxon_648": tests("0, 1, 2", "'BUILDING', 'FURNITURE', 'MACHINERY'", 24) + " SELECT model, topic, pa, pb, dim, n, w_plus, z, r_rb FROM z",
    "actor_spread": f"WITH t AS (SELECT CAST(doc_id % 3 AS VARCHAR) AS persona, unnest({TOK}) AS tok FROM documents), n AS (SELECT persona, count(*) AS n FROM t GROUP BY persona), r AS (SELECT tok AS actor, persona, 1000 * count(*) / max(n) AS rate FROM t JOIN n USING (persona) WHERE tok IN ('that', 'with', 'this', 'from', 'por') GROUP BY ALL) SELECT actor, round(max(rate) - min(rate), 6) AS spread, arg_max(persona, (rate, persona)) AS top_persona, round(max(rate), 6) AS rate FROM r GROUP BY actor",
    "persona_structure": f"""WITH g AS (SELECT lang, (r % 3)::INT AS persona, r // 3 AS slot, list_distinct(w) AS u, CASE WHEN len(w) >= 3 THEN list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS t FROM (SELECT lang, {TOK} AS w, row_number() OVER (PARTITION BY lang ORDER BY doc_id) - 1 AS r FROM documents))
SELECT lang, x.persona AS pa, y.persona AS pb, count(*) AS n, round(avg(len(list_intersect(x.u, y.u)) / nullif(len(list_distinct(list_concat(x.u, y.u))), 0)), 6) AS uni_j, round(avg(CASE WHEN x.t IS NULL OR y.t IS NULL THEN NULL ELSE len(list_intersect(x.t, y.t)) / nullif(len(list_distinct(list_concat(x.t, y.t))), 0) END), 6) AS tri_j FROM g x JOIN g y USING (lang, slot) WHERE x.persona < y.persona GROUP BY ALL""",
    "stage_funnel": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS window_start, event_type AS stage, count(*) AS n FROM events GROUP BY ALL",
    "stream_funnel": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS window_start, event_type AS stage, count(*) AS n FROM events GROUP BY ALL",
    "stream_completion": "SELECT count(*) AS requests, CAST(sum(CASE WHEN EXISTS (SELECT 1 FROM events p WHERE p.event_type = 'purchase' AND p.user_id = c.user_id AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 24 HOUR) THEN 1 ELSE 0 END) AS BIGINT) AS done FROM events c WHERE event_type = 'click'",
}
