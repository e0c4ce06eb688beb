import corpus_pipeline
from facetsel.llm.decontam import leaks
from facetsel.llm.lines import duplicate_lines
from facetsel.llm.near import near_duplicates


def test_stages_one_by_one(spark, sf_dir):
    """Each stage's decisions hold in what it returns."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, kept = docs.columns, docs
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        before, kept = kept, corpus_pipeline.staged(stage(spark, kept, sf_dir))
        ids = {r.doc_id for r in kept.select("doc_id").collect()}
        assert ids <= {r.doc_id for r in before.select("doc_id").collect()} and ids
        if k < 4:
            assert kept.columns == columns and kept.dtypes == docs.dtypes
        if k == 1:
            assert duplicate_lines(kept).count() == 0
            assert kept.where("n_chars <> length(text)").count() == 0
        if k == 2:
            assert near_duplicates(kept).where("not kept").count() == 0
        if k == 3:
            assert leaks(kept, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).count() == 0
    sums = kept.groupBy("source").agg({"taken": "sum", "target": "max"}).collect()
    assert all(abs(r["sum(taken)"] - r["max(target)"]) <= 0.5 for r in sums)
    assert kept.count() == corpus_pipeline.run(spark, sf_dir).count()


def test_registered():
    import __spark_entry__ as entry

    names = set(entry.queries())
    assert "pipeline" in names and all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11))
    assert len(corpus_pipeline.STAGES) == 5 and corpus_pipeline.ORACLE_SQL is None
