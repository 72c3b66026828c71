import corpus_pipeline
import __spark_entry__ as driver
from stablegrammar.llm import queries

SF = "/root/testdata/sf0.001"


def test_stages_keep_clean_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns, name
        assert 0.8 * docs.count() <= after.count() <= docs.count(), name
        docs = spark.createDataFrame(after.collect(), docs.schema)
    out = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert out.count() == docs.count() and out.agg({"n_tokens": "sum"}).first()[0] > 0


def test_near_copies_from_four_fifths_on_go(spark):
    words = [f"w{k}" for k in range(204)]  # 200 shingles; five go with each changed word
    changed = lambda n: " ".join(f"z{k}" if k % 20 == 10 and k < 20 * n else w for k, w in enumerate(words))
    docs = spark.createDataFrame([(1, changed(0)), (2, changed(4)), (3, " ".join(words[::-1])), (4, changed(5).replace("w", "v"))], "doc_id long, text string")
    assert 0.8 <= 180 / 220 < 0.85
    assert sorted(r["doc_id"] for r in corpus_pipeline.drop_near_duplicates(spark, docs, SF).collect()) == [1, 3, 4]


def test_every_operator_has_its_query(spark):
    names = driver.queries()
    assert {n.split("_")[0] for n in queries.queries()} == {f"op{i}" for i in range(1, 11)} and "pipeline" in names
    for name, query in queries.queries().items():
        df = query(spark, SF)
        assert "doc_id" in df.columns and df.count() > 0, name


def test_encode_bounds_its_batches(spark):
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    spark.conf.set(name, "10000")
    docs = spark.range(3).selectExpr("id AS doc_id", "'a b c' AS text")
    assert corpus_pipeline.encode(spark, docs, SF).count() == 3
    assert 0 < int(spark.conf.get(name)) <= 1000
