"""The pipeline's stages on the given tables and on planted cases."""

import pytest
from conftest import SF
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from privfreq.llm import common


@pytest.fixture(scope="module")
def stages(spark):
    docs, out = common.read(spark, SF, "documents"), []
    for name, stage in pipeline.STAGES:
        after = common.materialize(stage(spark, docs, SF), "stage")
        out.append((name, docs, after))
        docs = after
    return out


def test_columns_and_order(stages):
    assert [n for n, _, _ in stages] == [n for n, _ in pipeline.STAGES] and len(stages) == 5
    for _, before, after in stages[:-1]:
        assert after.columns == list(pipeline.COLUMNS) and after.dtypes == before.dtypes


def test_quality_keeps_the_good(stages, spark):
    labels = common.read(spark, SF, "labels")
    _, before, after = stages[0]
    gone = before.join(after, "doc_id", "left_anti").join(labels, "doc_id")
    assert gone.where("quality = 1").count() <= 1 and gone.count() >= 5


def test_lines_near_and_benchmark(stages, spark):
    _, before, after = stages[1]
    assert after.count() <= before.count() and after.where("n_chars <> length(text)").count() == 0
    _, before, after = stages[2]
    from privfreq.llm import near

    assert near.near_duplicates(after).where("not kept").count() == 0
    _, before, after = stages[3]
    benchmark = common.read(spark, SF, "benchmark")
    held = after.crossJoin(benchmark.select(F.col("text").alias("item"))).where("contains(text, item)")
    assert held.count() == 0


def test_lines_are_rewritten_once(spark):
    docs = common.read(spark, SF, "documents")
    with common.temporary():
        plan = pipeline.line_stage(spark, docs, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("ArrowEvalPython") == 1  # each one takes a worker, which stays for the stages to come


def test_packing_is_complete(stages):
    _, before, after = stages[4]
    assert after.select("doc_id").distinct().count() == before.count()
    assert after.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 4096").count() == 0


def test_empty_documents(spark):
    docs = common.read(spark, SF, "documents").where("false")
    for _, stage in pipeline.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0


def test_run_leaves_its_result_alone(spark, stages):
    """The pieces of a whole run are those of the stages, and nothing else stays in the shared folder."""
    import os

    folder = spark.conf.get("spark.checkpoint.dir").removeprefix("file://")
    before = set(os.listdir(folder))
    out = pipeline.run(spark, SF)
    assert len(set(os.listdir(folder)) - before) == 1
    assert sorted(map(tuple, out.select("doc_id", "piece", "ids_crc32").collect())) == sorted(map(tuple, stages[-1][2].select("doc_id", "piece", "ids_crc32").collect()))


def test_stages_on_odd_rows(spark):
    """Nulls in any column, empty and very long texts, repeated rows and extra columns go through every stage."""
    long = " ".join(f"word{i % 4999} of" for i in range(40_000))
    rows = [(1, None), (2, ""), (3, long), (4, "same text here now and then " * 8), (4, "same text here now and then " * 8), (5, "same text here now and then " * 8), (None, "no id at all"), (None, None)]
    docs = spark.createDataFrame([(i, t, None, None, None) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs = docs.withColumns({c: F.lit(c) for c in ("score", "node", "comp", "label", "level", "kept", "bucket")})
    for name, stage in pipeline.STAGES[1:]:  # the classifier of the given labels may reject texts as odd as these
        docs = common.materialize(stage(spark, docs, SF), "odd")
        if name == "near-duplicates":
            assert {r["doc_id"] for r in docs.collect()} == {1, 2, 3, 4, None}
    assert docs.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 4096").count() == 0
    assert common.materialize(pipeline.quality_stage(spark, spark.createDataFrame([(None, None, None, None, None)], "doc_id bigint, text string, lang string, source string, n_chars bigint"), SF), "odd").count() <= 1
