"""The online monitor: windows, sessions, repeats, joins, drift, sink and late rows."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from intentaudit.streaming import monitor

DIR = "/root/testdata/sf0.001"
START = dt.datetime(2026, 1, 1)


def event(i, minutes, kind, value=60.0, user=1, k="s0"):
    return i, START + dt.timedelta(minutes=minutes), user, kind, value, f'{{"k": "{k}"}}'


@pytest.fixture
def feed(spark, tmp_path):
    """Writes batches of events, one file each, and reads them as a stream, a file at a time."""

    def make(*batches):
        for n, rows in enumerate(batches):
            spark.createDataFrame(rows, monitor.EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / f"b{n}"))
            part = next((tmp_path / f"b{n}").glob("part-*"))
            (tmp_path / "in").mkdir(exist_ok=True)
            part.rename(tmp_path / "in" / f"{n:03d}.parquet")
        return monitor.read_events(spark, str(tmp_path / "in"))

    return make


def drain(df, mode, name, tmp_path):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / f"ck-{name}")).start()
    q.awaitTermination(120)
    return q, df.sparkSession.table(name).collect()


@pytest.mark.parametrize("fn", [monitor.sliding_counts, monitor.sessions])
def test_windows_stream_as_in_batch(spark, tmp_path, fn):
    ev = spark.read.parquet(f"{DIR}/events.parquet").select([f.name for f in monitor.EVENTS])
    ev.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    _, got = drain(fn(monitor.read_events(spark, str(tmp_path / "in")), late="60 days"), "complete" if fn is monitor.sliding_counts else "append", fn.__name__, tmp_path)
    want = sorted(map(tuple, fn(ev).collect()))
    # sessions close only as the watermark passes them
    assert sorted(map(tuple, got)) == want if fn is monitor.sliding_counts else set(map(tuple, got)) <= set(want)


def test_sessions_close(feed, tmp_path):
    rows = [event(1, 0, "view"), event(2, 20, "view"), event(3, 90, "view")]
    _, got = drain(monitor.sessions(feed(rows, [event(4, 600, "view", user=2)], [event(5, 601, "view", user=2)]), late="1 hour"), "append", "sess", tmp_path)
    assert sorted((r["seed"], r["n"]) for r in got) == [(1, 1), (1, 2)]


def test_repeats_and_static_join(spark, feed, tmp_path):
    stream = feed([event(1, 0, "click"), event(2, 1, "purchase")], [event(1, 0, "click"), event(3, 2, "view", k="s9")])
    _, got = drain(monitor.without_repeats(stream), "append", "once", tmp_path)
    assert sorted(r["event_id"] for r in got) == [1, 2, 3]
    intents = spark.createDataFrame([("s0", 5)], "sample_id string, intent4 int")
    _, got = drain(monitor.with_intents(stream, intents), "append", "joined", tmp_path)
    assert sorted((r["event_id"], r["intent4"]) for r in got) == [(1, 5), (1, 5), (2, 5), (3, None)]


def test_pairs_within_a_day(feed, tmp_path):
    stream = feed([event(1, 0, "click", 120.0), event(2, 10, "purchase", 20.0)], [event(3, 3000, "purchase", 20.0)])
    _, got = drain(monitor.pairs(stream), "append", "pairs", tmp_path)
    assert [r["d6"] for r in got] == [-5]


def test_drift_alarm(spark, tmp_path):
    """The alarm of a key rises once enough pairs are in and their mean is low; the other key stays quiet."""
    for n, (low, high) in enumerate(((0, 0), (-2, 1))):
        spark.createDataFrame([("text", low)] * 20 + [("token", high)] * 20, "form string, d6 int").coalesce(1).write.parquet(str(tmp_path / f"b{n}"))
        (tmp_path / "in").mkdir(exist_ok=True)
        next((tmp_path / f"b{n}").glob("part-*")).rename(tmp_path / "in" / f"{n}.parquet")
    stream = spark.readStream.schema("form string, d6 int").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    _, got = drain(monitor.drift(stream), "update", "drift", tmp_path)
    assert sorted((r["form"], r["n"], r["mean6"], r["alarm"]) for r in got) == [("text", 20, 0.0, False), ("text", 40, -1.0, True), ("token", 20, 0.0, False), ("token", 40, 0.5, False)]


def test_sink_takes_a_batch_once(spark, tmp_path):
    sink = monitor.write_once(str(tmp_path / "out"))
    df = spark.range(5).withColumn("v", F.col("id") * 2)
    sink(df, 0)
    sink(df, 0)
    sink(df, 1)
    assert spark.read.parquet(str(tmp_path / "out")).count() == 10


def test_late_rows_are_counted(feed, tmp_path):
    stream = feed([event(1, 0, "view"), event(2, 3000, "view")], [event(3, 3010, "view")], [event(4, 1, "view"), event(5, 2, "click")], [event(6, 6000, "view")])
    q, got = drain(monitor.window_counts(stream), "append", "late", tmp_path)
    assert monitor.late_rows(q) == 2
    assert sum(r["n"] for r in got if r["start"].startswith("2026-01-01")) == 1
