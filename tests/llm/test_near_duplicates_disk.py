"""What the near-duplicate stage moves and leaves in the shared folder."""

import os

import corpus_pipeline
from orderdep.llm import common, simhash

ROWS = [(k, " ".join(f"{k % 7}w{n}" for n in range(80)) + f" {k}") for k in range(30)]


def tables(spark):
    return set(os.listdir(common.shared_dir(spark).removeprefix("file:")))


def test_only_the_result_is_left(spark):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string")
    before = tables(spark)
    got = simhash.one_of_each(docs)
    assert [t.rsplit("-", 1)[0] for t in tables(spark) - before] == ["simhash-kept"]
    assert sorted(r["doc_id"] for r in got.collect()) == list(range(7))


def test_pipeline_leaves_what_its_result_reads(spark, sf_dir):
    before = tables(spark)
    got = corpus_pipeline.run(spark, sf_dir)
    left = {os.path.dirname(f).rsplit("/", 1)[-1] for f in got.inputFiles()}
    last = corpus_pipeline.STAGES[-2][0]
    assert {t.rsplit("-", 1)[0] for t in tables(spark) - before - left} <= {f"pipeline-{last}"}
    assert got.count()


def test_rows_are_picked_without_moving(spark):
    """By bitmap: first and last bits of words, the sign bit, words without a row, numbers of later partitions."""
    there = [0, 1, 62, 63, 64, 127, 128, 1000, (1 << 33) - 1, 1 << 33, (5 << 33) + 63]
    wanted = [0, 63, 64, 1000, 1 << 33, (5 << 33) + 63, 7 << 33]
    df = spark.createDataFrame([(x, f"text {x}") for x in there], "n long, text string")
    rows = spark.createDataFrame([(x,) for x in wanted for _ in range(2)], "row long")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        got = simhash.picked(df, "n", rows)
        assert "hashpartitioning" not in got._jdf.queryExecution().executedPlan().toString()
        assert sorted(map(tuple, got.collect())) == [(x, f"text {x}") for x in there if x in wanted]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_large_bitmaps_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(simhash, "MOST_WORDS", 0)
    docs = spark.createDataFrame(ROWS, "doc_id long, text string")
    assert sorted(r["doc_id"] for r in simhash.one_of_each(docs).collect()) == list(range(7))
