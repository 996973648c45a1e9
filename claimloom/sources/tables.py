"""Tables, and the views of them that carry the workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

CLAIMS = 10


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def articles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order as an article: subject = customer, model = region, topic = segment, persona = status, hop = priority digit."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "o_orderdate")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    n = load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    return (
        o.join(c, o.o_custkey == c.c_custkey)
        .join(n, c.c_nationkey == n.n_nationkey)
        .select(
            F.col("o_orderkey").alias("article_id"),
            F.col("o_custkey").alias("subject"),
            F.col("n_regionkey").alias("model"),
            F.col("c_mktsegment").alias("topic"),
            F.col("o_orderstatus").alias("persona"),
            F.substring("o_orderpriority", 1, 1).cast("int").alias("hop"),
            F.col("o_orderdate").alias("written"),
        )
    )


LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def claims(spark: SparkSession, sf_dir: str, k: int = CLAIMS) -> DataFrame:
    """The first k order lines as an article's claims; the flag is the verdict, the status the evidence tier."""
    line = load(spark, sf_dir, "lineitem").select("l_orderkey", *LINE_ORDER)
    n = F.row_number().over(W.partitionBy("l_orderkey").orderBy(*LINE_ORDER))
    verdict = F.when(F.col("l_returnflag") == "A", "supported").when(F.col("l_returnflag") == "R", "refuted").otherwise("insufficient")
    return (
        line.withColumn("claim_idx", n)
        .where(F.col("claim_idx") <= k)
        .select(F.col("l_orderkey").alias("article_id"), "claim_idx", verdict.alias("verdict"), F.when(F.col("l_linestatus") == "O", 1).otherwise(2).alias("tier"), "l_partkey", "l_suppkey", "l_linestatus")
    )


def accepted_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links part to part: two accepted lines of one order, from the smaller to the larger line number."""
    line = load(spark, sf_dir, "lineitem").where("l_returnflag = 'A'").select("l_orderkey", "l_linenumber", "l_partkey")
    a, b = line.alias("a"), line.alias("b")
    return a.join(b, (F.col("a.l_orderkey") == F.col("b.l_orderkey")) & (F.col("a.l_linenumber") < F.col("b.l_linenumber")) & (F.col("a.l_partkey") != F.col("b.l_partkey"))).select(
        F.col("a.l_partkey").alias("src"), F.col("b.l_partkey").alias("dst")
    ).distinct()


def text_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links between first words of document lines; a word's article is the document of least md5 that has a line with it."""
    line = load(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("x"))
    key = F.lower(F.regexp_extract("x", r"^([\p{L}\p{N}]+)", 1))
    word = line.select("doc_id", key.alias("key")).where("key <> ''").distinct()
    home = word.groupBy("key").agg(F.min_by("doc_id", F.md5(F.concat(F.lit("42:"), "key", F.lit(":"), F.col("doc_id").cast("string")))).alias("doc_id"))
    return home.join(word.withColumnRenamed("key", "dst"), "doc_id").where("key <> dst").select(F.col("key").alias("src"), "dst")


def markup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as wiki markup: title as bold subject, navigation anchors as links, paragraphs as body."""
    p = load(spark, sf_dir, "pages").select("page_id", "url", "html")
    anchors = F.transform(F.regexp_extract_all("html", F.lit(r'<a href="/[^"]*">([^<]*)</a>'), F.lit(1)), lambda a: F.concat(F.lit("[["), a, F.lit("]]")))
    title = F.regexp_extract("html", r"<h1>([^<]*)</h1>", 1)
    body = F.array_join(F.regexp_extract_all("html", F.lit(r"<p>([^<]+)</p>"), F.lit(1)), "\n")
    return p.select("page_id", "url", F.concat(F.lit("'''"), title, F.lit("'''\n"), F.array_join(anchors, " "), F.lit("\n== "), title, F.lit(" ==\n"), body).alias("wikitext"))
