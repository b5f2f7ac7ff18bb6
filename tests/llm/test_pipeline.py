"""The pipeline end to end on a small table, against its stages' plain versions."""

import corpus_pipeline
from test_documents import components, contaminated


def test_stages_keep_columns_and_clean_documents(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    bench = [tuple(r) for r in spark.read.parquet(f"{small}/benchmark.parquet").select("item_id", "text").collect()]
    at = docs
    stages = dict(corpus_pipeline.STAGES)
    assert list(stages) == ["language ID", "MinHash near-dedup", "benchmark decontamination", "best-fit packing"]

    after = stages["language ID"](spark, at, small)
    assert after.columns == docs.columns
    left = after.collect()
    assert len(left) >= 0.98 * docs.count()

    after = stages["MinHash near-dedup"](spark, after, small)
    rows = [tuple(r) for r in left]
    assert {r["doc_id"] for r in after.collect()} == {r[0] for r in components(rows, corpus_pipeline.SIMILAR_PERCENT) if r[-1]}

    rows = [tuple(r) for r in after.collect()]
    after = stages["benchmark decontamination"](spark, after, small)
    assert {r["doc_id"] for r in after.collect()} == {r[0] for r in contaminated(rows, bench) if not r[-1]}

    packed = stages["best-fit packing"](spark, after, small)
    assert {r["doc_id"] for r in packed.collect()} == {r["doc_id"] for r in after.collect()}
    assert packed.groupBy("sequence_id").sum("length").where("`sum(length)` > 2048").count() == 0


def test_run(spark, small):
    got = corpus_pipeline.run(spark, small)
    assert got.count() > 0
    assert set(got.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"}


def _tables(spark, folder, docs, bench):
    docs.write.parquet(f"{folder}/documents.parquet")
    bench.write.parquet(f"{folder}/benchmark.parquet")
    return str(folder)


def test_run_on_awkward_rows(spark, docs, tmp_path):
    """Nulls, repeats, and columns with the names that the stages use themselves."""
    bench = spark.createDataFrame([(1, "kurz und gut"), (None, None), (2, "")], "item_id long, text string")
    folder = _tables(spark, tmp_path, docs, bench)
    at = spark.read.parquet(f"{folder}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, folder)
        assert at.columns == docs.columns
    # null and blank texts and those without a letter are gone, near copies and repeats are one
    got = sorted((repr(r["doc_id"]) for r in at.collect()))
    assert got == sorted(["1", "None", "7", "9", "10", "11"])
    packed = corpus_pipeline.run(spark, folder)
    assert sorted({repr(r["doc_id"]) for r in packed.collect()}) == sorted(set(got))


def test_run_on_empty_tables(spark, docs, empty, tmp_path):
    bench = spark.createDataFrame([], "item_id long, text string")
    assert corpus_pipeline.run(spark, _tables(spark, tmp_path / "none", empty, bench)).count() == 0
    assert corpus_pipeline.run(spark, _tables(spark, tmp_path / "some", docs, bench)).count() > 0
