"""Document fingerprints by consistent weighted sampling.

A text is a weighted set of hashed words and word pairs. For every sample,
gamma and uniform variates fixed by (term, sample) give each weighted term an
arrival value; the least one and its quantised weight form the sample. Two
texts agree in a sample with probability equal to their generalised Jaccard
similarity (sum of minima over sum of maxima of the weights).

Terms are 64-bit hashes and never merged: the sample holds the hash, and the
three variates come from three rows of a fixed table, each chosen by other bits of the hash.
"""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordIds, map_batches, text_of

SAMPLES, ROWS, SEED = 64, 1 << 16, 97
_MULT = np.uint64(0x9E3779B97F4A7C15)


@functools.cache
def variates(samples: int = SAMPLES, rows: int = ROWS, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Per (row, sample): gamma(2,1) step, its inverse, uniform shift, and log gamma(2,1); a fixed table."""
    rng = np.random.Generator(np.random.PCG64(seed))
    step = rng.gamma(2.0, 1.0, (rows, samples)).astype(np.float32) + np.float32(1e-6)
    level = np.log(rng.gamma(2.0, 1.0, (rows, samples)) + 1e-12).astype(np.float32)
    return step, np.float32(1) / step, rng.random((rows, samples), dtype=np.float32), level


def weighted_terms(text: bytes, ids: WordIds) -> tuple[np.ndarray, np.ndarray]:
    """(term hashes, weights): words by root of count, then pairs of neighbours by count."""
    h = ids.array(text.lower().split())
    if not len(h):
        return np.zeros(0, np.uint64), np.zeros(0, np.float32)
    words, n = np.unique(h * _MULT, return_counts=True)
    pair = (h[:-1] * _MULT) ^ (h[1:] + (h[1:] << np.uint64(9)))
    pair ^= pair >> np.uint64(31)
    pairs, m = np.unique(pair * _MULT, return_counts=True)
    return np.concatenate([words, pairs]), np.concatenate([np.sqrt(n), m]).astype(np.float32)


def sample_signature(at: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """One 32-bit value per sample; zeros for a text without terms."""
    best, key = np.full(SAMPLES, np.inf, np.float32), np.zeros(SAMPLES, np.uint64)
    step, inverse, shift, level = variates()
    every, log = np.arange(SAMPLES), np.log(weights)[:, None]
    for lo in range(0, len(at), 512):  # blocks that stay in the cache
        k = at[lo : lo + 512]
        a, b, c = ((k >> np.uint64(x) & np.uint64(ROWS - 1)).astype(np.int64) for x in (48, 32, 16))
        d = shift.take(b, axis=0)
        t = inverse.take(a, axis=0)
        t *= log[lo : lo + 512]
        t += d
        np.floor(t, out=t)
        np.subtract(t, d, out=d)
        d += np.float32(1)
        d *= step.take(a, axis=0)
        arrival = np.subtract(level.take(c, axis=0), d, out=d)
        i = arrival.argmin(axis=0)
        least = arrival[i, every]
        new = least < best
        best[new] = least[new]
        code = k[i] * _MULT + t[i, every].astype(np.int64).view(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(1)
        key[new] = code[new]
    return ((key ^ (key >> np.uint64(29))) >> np.uint64(8)).astype(np.uint32) | np.uint32(1) if len(at) else np.zeros(SAMPLES, np.uint32)


def fingerprint(text: bytes, ids: WordIds) -> np.ndarray:
    return sample_signature(*weighted_terms(text, ids))


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    return float((a == b).mean())


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_chars, fingerprint) for every text, no shuffle."""

    def sketch(batches):
        ids = WordIds()
        for b in batches:
            texts = [t or "" for t in b.column("text").to_pylist()]
            yield pa.record_batch([b.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array([fingerprint(t.encode(), ids).astype(">u4").tobytes().hex() for t in texts])], ["doc_id", "n_chars", "fingerprint"])

    return map_batches(docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")), sketch, "doc_id long, n_chars long, fingerprint string")


def in_order_with_next(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows (bin, carried, doc_id, text) dealt so that each task holds whole bins in descending identifier.

    Bins are identifier ranges. The first row of the next bin (of the first
    bin, for the last) is carried along at the end of each, so every document
    meets its successor with one shuffle of the texts. Null identifiers come
    last; equal identifiers are ordered by text.
    """
    from pyspark.ml.feature import Bucketizer

    spark = docs.sparkSession
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("text")).withColumn("__k", F.coalesce("doc_id", F.lit(-(2**63))).cast("double"))
    n = max(2, 2 * int(spark.conf.get("spark.sql.shuffle.partitions")))
    cuts = base.approxQuantile("__k", [i / n for i in range(1, n)], 0.2 / n)  # n numbers
    edges = [float("-inf"), *sorted(set(cuts)), float("inf")]
    placed = Bucketizer(splits=edges, inputCol="__k", outputCol="__b").transform(base) if len(edges) > 2 else base.withColumn("__b", F.lit(0))
    binned = placed.withColumn("bin", -F.col("__b").cast("int")).drop("__b")
    heads = sorted((r["bin"], r["k"]) for r in binned.groupBy("bin").agg(F.max(F.coalesce("doc_id", F.lit(-(2**63)))).alias("k")).collect())  # a row per bin
    if not heads:
        return binned.select("bin", F.lit(0).alias("carried"), "doc_id", "text")
    carry: dict[int, list[int]] = {}
    for i, (_, k) in enumerate(heads):
        carry.setdefault(k, []).append(heads[i - 1][0])
    to = spark.createDataFrame(list(carry.items()), "__head long, __to array<int>")
    key = F.coalesce(F.col("doc_id"), F.lit(-(2**63)))
    own = F.array(F.struct(F.col("bin").alias("bin"), F.lit(0).alias("carried")))
    others = F.transform(F.coalesce("__to", F.array().cast("array<int>")), lambda b: F.struct(b.alias("bin"), F.lit(1).alias("carried")))
    spread = binned.join(F.broadcast(to), key == F.col("__head"), "left").withColumn("__e", F.explode(F.concat(own, others)))
    dealt = spread.select("__e.bin", "__e.carried", "doc_id", "text").repartition(n // 2, "bin")
    return dealt.sortWithinPartitions("bin", "carried", F.desc_nulls_last("doc_id"), F.desc("text"))


def edited_likeness(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of every text, of its half-replaced text, and their likeness.

    The edited text's last floor(n/2) code points are replaced by the first as
    many of the next document in descending identifier. One row per row;
    empty texts have the all-zero fingerprint, which is only like itself. An
    empty table gives an empty result. Extra columns are ignored.
    """

    def compare(batches):
        ids = WordIds()
        held = None  # bin, doc_id, text, fingerprint
        done = None
        for b in batches:
            rows = []
            for bin_, carried, doc, text in zip(*(b.column(c).to_pylist() for c in ("bin", "carried", "doc_id", "text"))):
                if carried and done == bin_:
                    continue
                fp = fingerprint(text.encode(), ids)
                if held is not None and held[0] == bin_:
                    _, d, t, f = held
                    half = len(t) // 2
                    edited = (t[: len(t) - half] + text[:half]).encode()
                    ef = fingerprint(edited, ids)
                    rows.append((d, len(t), hashlib.sha256(edited).hexdigest(), f.astype(">u4").tobytes().hex(), ef.astype(">u4").tobytes().hex(), likeness(f, ef), likeness(f, fp)))
                held = (bin_, doc, text, fp)
                if carried:
                    done = bin_
                    held = None
            if rows:
                c = list(zip(*rows))
                yield pa.record_batch([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), *(pa.array(x) for x in c[2:5]), *(pa.array(x, pa.float64()) for x in c[5:])], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    return map_batches(in_order_with_next(docs, id_col, text_col), compare, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
