import corpus_pipeline
from knnscope.io import materialize, table
from tests.llm.test_duplicates import brute

SF = "/root/testdata/sf0.001"


def test_stages_in_order_and_columns(spark):
    docs = table(spark, SF, "documents")
    columns, kept = docs.columns, docs.count()
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "quality_rules", "near_dedup", "personal_data", "best_fit_packing"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs
        docs = materialize(stage(spark, docs, SF), name)
        assert docs.columns == columns
        assert docs.count() <= kept
        kept = docs.count()
        if name == "near_dedup":
            rows = sorted((r.doc_id, r.text) for r in before.select("doc_id", "text").collect())
            _, group = brute([t for _, t in rows], 5, 80)
            assert {r.doc_id for r in docs.select("doc_id").collect()} == {rows[i][0] for i, g in enumerate(group) if g == i}
        if name == "personal_data":
            assert docs.filter("text rlike '[a-z]+[.][0-9]{2}@mail'").count() == 0
            assert docs.count() == before.count()
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert packed.select("doc_id").distinct().count() == kept


def test_run(spark):
    assert corpus_pipeline.run(spark, SF).count() > 0


def test_odd_tables(spark, make_docs):
    odd = make_docs([None, "", "short", *(f"these are the words of text number {i} and of no other one at all {i * 7919}" for i in range(12))])
    for docs in (odd, odd.limit(0), odd.unionByName(odd).withColumn("lang", odd.lang)):
        columns = docs.columns
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = materialize(stage(spark, docs, SF), "odd")
            assert docs.columns == columns
        packed = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
        assert packed.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()
