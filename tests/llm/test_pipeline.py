import corpus_pipeline
from claimloom.llm import decontamination, quality, simhash

SF = "/root/testdata/sf0.001"


def test_stages_take_effect(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, {r.doc_id for r in docs.select("doc_id").collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == columns
        out = spark.createDataFrame(out.collect(), docs.schema)
        kept = {r.doc_id for r in out.select("doc_id").collect()}
        assert kept <= seen
        if name == "quality":
            scorer = quality.fit(docs, spark.read.parquet(f"{SF}/labels.parquet"))
            assert kept == {r.doc_id for r in docs.collect() if max(scorer.score(r.text.encode())) < 0.5}
        if name == "lines":
            assert kept == seen
        if name == "near_duplicates":
            fps = {r.doc_id: simhash.fingerprint((r.text or "").encode()) for r in docs.collect() if (r.text or "").split()}
            assert all(bin(fps[a] ^ fps[b]).count("1") > 2 for a in kept & set(fps) for b in kept & set(fps) if a < b)
        if name == "decontamination":
            items = [decontamination.normal(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            assert not any(i in decontamination.normal(r.text) for r in out.collect() for i in items)
        docs, seen = out, kept
    last = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert {r.doc_id for r in last.collect()} == seen
    assert {r.doc_id for r in corpus_pipeline.run(spark, SF).collect()} == seen


def test_wordless_documents_are_one_group(spark):
    rows = [(1, "one two three four five six"), (2, ""), (3, None), (4, " \n\t"), (5, "quite another text of other words"), (None, "")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    assert sorted(str(r.doc_id) for r in corpus_pipeline.near_duplicate_stage(spark, docs, SF).collect()) == ["1", "2", "5", "None"]


def test_kept_groups_are_not_broadcast(spark):
    docs = spark.createDataFrame([(k, f"text number {k} of a few") for k in range(4)], "doc_id bigint, text string")
    plan = corpus_pipeline.near_duplicate_stage(spark, docs, SF)._jdf.queryExecution().executedPlan().toString()
    semi = [line for line in plan.split("\n") if "LeftSemi" in line]
    assert semi and all("SortMergeJoin" in line for line in semi)
