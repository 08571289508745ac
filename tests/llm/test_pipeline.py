import corpus_pipeline as P
from spanfocus.llm import language_id
from tests.llm.fixtures import edge_docs, no_docs


def test_stages_keep_the_columns_of_documents(spark, sf):
    assert [n for n, _ in P.STAGES] == ["language_id", "toxicity", "near_duplicates", "source_mixing", "bpe"]
    for make in (edge_docs, no_docs):
        docs = make(spark)
        for _, stage in P.STAGES[:-1]:
            assert tuple(stage(spark, docs, sf).columns) == P.COLUMNS
            stage(spark, docs, sf).count()
        assert P.encoded(spark, docs, sf).count() == docs.count()


def test_each_stage_acts(spark, sf):
    docs = edge_docs(spark)
    left = P.identified(spark, docs, sf)
    assert {r.doc_id for r in left.collect()} == {3, 4, 5, 7, 9, None}
    once = P.distinct(spark, docs.where("doc_id IS NOT NULL"), sf)
    assert sorted(r.doc_id for r in once.collect()) == [1, 3, 5, 7, 8, 9]


def test_whole_run_equals_its_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    step = docs
    for _, stage in P.STAGES:
        step = spark.createDataFrame(stage(spark, step, sf).collect(), stage(spark, step, sf).schema)
    assert sorted(map(str, P.run(spark, sf).collect())) == sorted(map(str, step.collect()))
    assert language_id.UNDETERMINED == "und"
