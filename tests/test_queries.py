"""Registered queries against DuckDB on the smallest tables."""

import duckdb
import pytest
from pyspark.sql import functions as F

from intentaudit.plans import oracles, workloads

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = ["psi_bits", "quota_draw", "wrong_headers", "score_rows", "paired_wilcoxon", "dissociation", "uptake", "outcome", "wrong_vs_none_decision", "bootstrap_exact", "decode_prefix", "nll", "page_audit", "integrity", "arm_levels", "detector_agreement", "contamination", "asof_orders", "interval_pairs", "stream_windows"]


def norm(df):
    cols = sorted(df.columns)
    one = lambda v: "~" if v is None or v != v else repr(round(v, 6)) if isinstance(v, float) else str(v)
    return cols, sorted(tuple(one(x) for x in r) for r in df[cols].astype(object).itertuples(index=False))


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", CHECKED)
def test_against_sql(spark, con, name):
    assert norm(workloads.QUERIES[name](spark, DIR).toPandas()) == norm(con.execute(oracles.ORACLES[name]).df())


def test_every_oracle_has_a_query():
    assert set(oracles.ORACLES) <= set(workloads.QUERIES)


def test_stream_matches_batch(spark, tmp_path):
    from intentaudit.streaming import monitor

    ev = spark.read.parquet(f"{DIR}/events.parquet").select([f.name for f in monitor.EVENTS])
    for i, d in enumerate(ev.orderBy("ts").randomSplit([1.0] * 2, 1)):
        d.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = monitor.window_counts(monitor.read_events(spark, str(tmp_path / "in"), 10), late="60 days")
    q = stream.writeStream.outputMode("complete").format("memory").queryName("w").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "ck")).start()
    q.awaitTermination(120)
    assert sorted(map(tuple, spark.table("w").collect())) == sorted(map(tuple, monitor.window_counts(ev).collect()))


def test_manifest_counts_prompts_of_the_sample(spark):
    rows = workloads.QUERIES["job_manifest"](spark, DIR).collect()
    assert len(rows) == 21 and len({r["n"] for r in rows}) == 1 and rows[0]["n"] > 0


def test_second_decoding_deals_training_rows_without_a_shuffle(spark, monkeypatch):
    from intentaudit.operators import generator

    plans, complete = [], generator.complete

    def spy(prompt, train):
        plans.append(train._jdf.queryExecution().executedPlan().toString())
        return complete(prompt, train)

    train = workloads.training(spark, DIR)
    size = spark.conf.get("spark.sql.files.maxPartitionBytes")
    monkeypatch.setattr(generator, "complete", spy)
    monkeypatch.setattr(workloads, "scores", lambda s, d: complete(workloads.prompts_of(s, d), train).withColumn("adh6", F.lit(0)))
    spark.conf.set("spark.sql.files.maxPartitionBytes", "1k")
    try:
        assert train.rdd.getNumPartitions() > 1
        workloads.run_agreement(spark, DIR)
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", size)
    assert "Exchange" not in plans[0]
