"""Online monitoring: events replayed as scored generations."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Fixed values of the replay: event type to arm; errors are outputs that do not run.
ARMS = {"view": "uncond", "click": "correct", "purchase": "wrong", "signup": "masked", "error": "failed"}
EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def as_scores(events: DataFrame) -> DataFrame:
    """(ts, event_id, sample_id, arm, seed, adh6, ok) from an event."""
    arm = F.coalesce(*[F.when(F.col("event_type") == k, v) for k, v in ARMS.items()], F.lit("uncond"))
    ok = F.col("event_type") != "error"
    six = F.least(F.greatest(F.floor(F.coalesce("value", F.lit(0.0)) / 20).cast("int"), F.lit(0)), F.lit(6))
    return events.select("ts", "event_id", F.coalesce(F.get_json_object("props", "$.k"), F.lit("")).alias("sample_id"), arm.alias("arm"), F.col("user_id").alias("seed"), F.when(ok, six).otherwise(0).alias("adh6"), ok.alias("ok"))


def window_counts(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Executability and adherence by arm and tumbling window; works on batch and stream alike."""
    s = as_scores(events).withWatermark("ts", late)
    return s.groupBy(F.window("ts", width).alias("w"), "arm").agg(F.count("*").alias("n"), F.sum(F.col("ok").cast("int")).alias("runnable"), F.sum("adh6").alias("adh6")).select(F.col("w.start").cast("string").alias("start"), "arm", "n", "runnable", "adh6")


def sliding_counts(events: DataFrame, width: str = "1 day", step: str = "6 hours", late: str = "1 hour") -> DataFrame:
    s = as_scores(events).withWatermark("ts", late)
    return s.groupBy(F.window("ts", width, step).alias("w"), "arm").agg(F.count("*").alias("n"), F.sum("adh6").alias("adh6")).select(F.col("w.start").cast("string").alias("start"), "arm", "n", "adh6")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    s = as_scores(events).withWatermark("ts", late)
    return s.groupBy(F.session_window("ts", gap).alias("w"), "seed").agg(F.count("*").alias("n")).select(F.col("w.start").cast("string").alias("start"), "seed", "n")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Deliveries of the same event within the watermark count once."""
    return as_scores(events).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_intents(stream: DataFrame, intents: DataFrame) -> DataFrame:
    """Stream-static join to intents on the sample."""
    return as_scores(stream).join(intents, "sample_id", "left")


def pairs(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Correct and wrong outputs of a sample within a day of each other; state is bounded by both watermarks."""
    s = as_scores(stream)
    c = s.filter("arm = 'correct'").select("sample_id", F.col("ts").alias("cts"), F.col("adh6").alias("c6")).withWatermark("cts", late)
    w = s.filter("arm = 'wrong'").select(F.col("sample_id").alias("sid"), F.col("ts").alias("wts"), F.col("adh6").alias("w6")).withWatermark("wts", late)
    return c.join(w, F.expr("sample_id = sid and wts >= cts and wts <= cts + interval 1 day")).select("sample_id", "cts", "wts", (F.col("w6") - F.col("c6")).alias("d6"))


def drift(differences: DataFrame, limit: float = -0.5, least: int = 30, key: str = "form") -> DataFrame:
    """Running paired difference with an alarm: (key, n, mean6, alarm) per key and micro-batch.

    differences: a stream of (key, d6), one row per pair (``pairs``), d6 a whole number of sixths from -6 to 6. The
    state of a key is thirteen counts, however many pairs have come. The alarm is raised
    once ``least`` pairs are in and their mean is below ``limit`` sixths.
    """

    def step(group, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        counts = list(state.get[0]) if state.exists else [0] * 13
        for b in batches:
            for d, n in b["d6"].clip(-6, 6).value_counts().items():
                counts[int(d) + 6] += int(n)
        state.update((counts,))
        n = sum(counts)
        mean = sum((i - 6) * c for i, c in enumerate(counts)) / n if n else 0.0
        yield pd.DataFrame({key: [group[0]], "n": [n], "mean6": [mean], "alarm": [bool(n >= least and mean < limit)]})

    return differences.groupBy(key).applyInPandasWithState(step, f"{key} string, n long, mean6 double, alarm boolean", "counts array<long>", "update", "NoTimeout")


def late_rows(query) -> int:
    """Rows that a query's state operators dropped as later than the watermark, over its progress reports; a windowed aggregate counts them after its partial sums (one a window, arm and task)."""
    return sum(s.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for s in json.loads(p.json).get("stateOperators", []))


def write_once(path: str):
    """A foreachBatch sink that a repeated batch overwrites rather than repeats."""

    def sink(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return sink


def read_events(spark: SparkSession, folder: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(folder)
