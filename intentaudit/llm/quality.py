"""Quality filter by importance resampling.

Two hashed n-gram models, of target text (labelled good) and of raw text (all
documents), give each document a log importance weight; the k largest
weights plus Gumbel noise are kept, which samples k documents without
replacement in proportion to their weights. k defaults to the number of
documents that the target model explains better than the raw one.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BINS, WordIds, blobs, map_batches, materialize, settled, text_of, uniform

BUCKETS, SMOOTH, SEED = 1 << 14, 1.0, "gumbel"
_TOKEN = re.compile(rb"[A-Za-z0-9_\x80-\xff]+|[!-/:-@\[-^`{-~]+")
_MIX = np.uint64(0x9E3779B97F4A7C15)


def features(text: bytes, ids: WordIds, buckets: int) -> np.ndarray:
    """Buckets of the words, punctuation runs and pairs of neighbours in a whole text.

    All pairs of a token with itself are one feature.
    """
    h = ids.array(_TOKEN.findall(text))
    pairs = np.where(h[:-1] == h[1:], _MIX, (h[:-1] * _MIX) ^ (h[1:] >> np.uint64(7)))
    return (np.concatenate([h, pairs]) % np.uint64(buckets)).astype(np.int64)


def bucket_counts(texts: DataFrame, buckets: int = BUCKETS) -> np.ndarray:
    """Feature counts by bucket over all texts; each task sends at most ``buckets`` rows."""

    def count(batches):
        ids, total = WordIds(), np.zeros(buckets, np.int64)
        for b in batches:
            for t in blobs(b.column(0)):
                total += np.bincount(features(t, ids, buckets), minlength=buckets)
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at.astype(np.int32)), pa.array(total[at])], ["bucket", "n"])

    rows = map_batches(texts, count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).collect()  # at most `buckets` rows
    out = np.zeros(buckets, np.int64)
    for r in rows:
        out[r["bucket"]] = r["n"]
    return out


def log_ratio(target: np.ndarray, raw: np.ndarray, smooth: float = SMOOTH) -> np.ndarray:
    """Log of smoothed target over raw probability, by bucket."""
    p = (target + smooth) / (target.sum() + smooth * len(target))
    q = (raw + smooth) / (raw.sum() + smooth * len(raw))
    return np.log(p) - np.log(q)


def top_k(df: DataFrame, key: str, k: int, tie: str, levels: int = 2) -> DataFrame:
    """Add ``kept``: the k rows with the largest key (ties by smaller ``tie``, equal pairs together).

    The key is binned after squashing; the bin holding the k-th row is binned again, and
    only the last bin's rows meet in one window. Nothing is sorted as a whole.
    """
    df = df.withColumn("__x", -F.col(key) / (1 + F.abs(F.col(key))))
    lo, hi, before, inner = -1.0, 1.0, 0, df
    for _ in range(levels):
        width = (hi - lo) / BINS
        b = F.least(F.greatest(F.floor((F.col("__x") - lo) / width), F.lit(0)), F.lit(BINS - 1)).cast("int")
        counts = dict(inner.groupBy(b.alias("b")).count().collect())  # at most BINS rows
        edge = BINS
        for i in range(BINS):
            if before + counts.get(i, 0) > k:
                edge = i
                break
            before += counts.get(i, 0)
        if edge == BINS:
            return df.withColumn("kept", F.lit(True)).drop("__x")
        inner = inner.filter(b == edge)
        lo, hi = lo + edge * width, lo + (edge + 1) * width
        if hi - lo < 1e-12:
            break
    run = inner.withColumn("__n", F.count("*").over(Window.orderBy("__x", tie))).filter(F.col("__n") <= k - before)
    last = run.agg(F.max(F.struct("__x", tie)).alias("m")).collect()[0]["m"]
    floor = inner.agg(F.min("__x")).collect()[0][0]
    below = F.col("__x") < F.lit(floor)
    if last is not None:
        below = below | (F.col("__x") < F.lit(last[0])) | ((F.col("__x") == F.lit(last[0])) & (F.coalesce(F.col(tie), F.lit(-(2**63))) <= F.lit(last[1] if last[1] is not None else -(2**63))))
    return df.withColumn("kept", below).drop("__x")


def resample(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int | None = None, buckets: int = BUCKETS, seed: str = SEED) -> DataFrame:
    """One row per document: doc_id, log_weight, gumbel_key, kept.

    The target model learns from all documents with quality 1, the raw model from all documents. Null texts count as
    empty and weigh 0. Rows that share an identifier share the noise. With
    no labelled document every weight is 0 and all are kept. An empty table gives an empty result.
    """
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).cast("binary").alias("text"))
    good = settled(labels.filter("quality = 1").select(F.col("doc_id").cast("long").alias("doc_id")).distinct())  # no text is shuffled where these are few
    target = bucket_counts(base.join(good, "doc_id", "left_semi").select("text"), buckets)
    raw = bucket_counts(base.select("text"), buckets)
    ratio = log_ratio(target, raw) if target.sum() else np.zeros(buckets)

    def weigh(batches):
        ids = WordIds()
        for b in batches:
            w = [float(ratio[features(t, ids, buckets)].sum()) for t in blobs(b.column("text"))]
            yield pa.record_batch([b.column("doc_id"), pa.array(w, pa.float64())], ["doc_id", "log_weight"])

    scored = materialize(map_batches(base, weigh, "doc_id long, log_weight double"))
    noisy = scored.withColumn("gumbel_key", F.col("log_weight") - F.ln(-F.ln(uniform(seed, F.col("doc_id")))))
    if k is None:
        k = scored.filter("log_weight >= 0").count()
    return top_k(noisy, "gumbel_key", k, "doc_id")
