"""Helpers shared by the training-data operators."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..shipping import ship

#: ASCII white space, the only separators of the word rule ``[^\x20\x09-\x0D]+``.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def session(df: DataFrame) -> SparkSession:
    """The frame's session, with the package shipped and Arrow batches small enough for very long texts."""
    spark = df.sparkSession
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1024")
    return spark


def scratch(spark: SparkSession) -> str:
    """A fresh path in the shared folder of ``spark.checkpoint.dir``.

    The folder is the session's; one is made only where it is unset and Spark runs in one process (tests).
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="scratch-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/llm-{uuid.uuid4().hex}"


def materialize(df: DataFrame, compression: str | None = None) -> DataFrame:
    """Cut the lineage: write to the shared folder, read back."""
    spark = df.sparkSession
    path = scratch(spark)
    (df.write.option("compression", compression) if compression else df.write).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of frames that are written down and no longer held; it does so when the driver's JVM collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    session(df)
    return df.mapInArrow(fn, schema)


def fold(id_col: Column, k: int) -> Column:
    """crc32 of the identifier as text, modulo k (a null identifier is '')."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % k


def text_of(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def uniform(seed: str, *cols: Column) -> Column:
    """A reproducible uniform in (0,1) from the first 13 hex digits of an md5."""
    key = F.concat_ws(":", F.lit(seed), *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    return (F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("double") + 0.5) / F.lit(float(16**13))


def bounded_sample(df: DataFrame, n: int, seed: str, *key: str) -> DataFrame:
    """At most n rows, the smallest by md5 of the key (top-n per task, then merged)."""
    order = F.md5(F.concat_ws(":", F.lit(seed), *[F.col(c).cast("string") for c in key]).cast("binary"))
    return df.orderBy(order, *key).limit(n)


class WordIds(dict):
    """bytes -> 64-bit hash, remembered up to a limit."""

    def __init__(self, limit: int = 400_000, seed: int = 0):
        super().__init__()
        import xxhash

        self._hash, self._limit, self._seed = xxhash.xxh64_intdigest, limit, seed

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self._limit:
            self.clear()
        h = self[word] = self._hash(word, self._seed)
        return h

    def array(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def blobs(column: pa.Array) -> list[bytes]:
    """Binary or string column to bytes; null becomes empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


BINS = 4096


def take_in_order(df: DataFrame, groups: DataFrame, group: str, place: str, mass: str, budget: str, tie: str) -> DataFrame:
    """Per group, the cut of an ordered running sum without sorting the group in one task.

    ``place`` in [0,1) orders the rows of a group, ``tie`` breaks ties. Rows
    are binned by place; bin sums (at most BINS a group) locate the bin in
    which the running ``mass`` passes the group's ``budget``; only that bin's
    rows, a 1/BINS share, are sorted. Adds ``__in`` (running sum within the
    budget, peers together). Nulls in ``group`` must be replaced beforehand.
    """
    binned = df.withColumn("__bin", F.least(F.floor(F.col(place) * BINS), F.lit(BINS - 1)).cast("int"))
    sums = binned.groupBy(group, "__bin").agg(F.sum(mass).alias("__mass"))
    run = Window.partitionBy(group).orderBy("__bin")
    cut = (
        sums.withColumn("__upto", F.sum("__mass").over(run))
        .join(groups.select(group, F.col(budget).alias("__budget")), group)
        .filter(F.col("__upto") > F.col("__budget"))
        .groupBy(group)
        .agg(F.min_by(F.struct("__bin", (F.col("__upto") - F.col("__mass")).alias("__before"), "__budget"), "__bin").alias("__cut"))
        .select(group, F.col("__cut.__bin").alias("__edge"), F.col("__cut.__before").alias("__before"), F.col("__cut.__budget").alias("__budget"))
    )
    placed = binned.join(settled(cut), group, "left")
    edge = placed.filter(F.col("__bin") == F.col("__edge"))
    upto = Window.partitionBy(group).orderBy(place, tie)
    last = (
        edge.withColumn("__sum", F.col("__before") + F.sum(mass).over(upto))
        .filter(F.col("__sum") <= F.col("__budget"))
        .groupBy(group)
        .agg(F.max(F.struct(F.col(place).alias("p"), F.col(tie).alias("t"))).alias("__last"))
    )
    here = F.struct(F.col(place).alias("p"), F.col(tie).alias("t"))
    inside = F.col("__edge").isNull() | (F.col("__bin") < F.col("__edge")) | ((F.col("__bin") == F.col("__edge")) & F.coalesce(here <= F.col("__last"), F.lit(False)))
    return placed.join(settled(last), group, "left").withColumn("__in", inside).drop("__bin", "__edge", "__before", "__budget", "__last")


BROADCAST_ROWS = 1_000_000


def sized(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A narrow frame of identifiers, broadcast if it is counted and found small, else left to shuffle."""
    return F.broadcast(df) if df.count() <= rows else df


def settled(df: DataFrame) -> DataFrame:
    """A table with one row per group, written down and broadcast where it is small, so that joins with it leave large groups spread."""
    return sized(materialize(df))


def free(df: DataFrame, name: str) -> str:
    """The name, with underscores added until no column of the frame has it (in any case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def without(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The documents whose identifier is not in ``gone`` (one column); all columns stay."""
    name = free(docs, "__gone")
    return docs.join(sized(gone.toDF(name).distinct()), F.col(id_col).eqNullSafe(F.col(name)), "left_anti")


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, str]:
    """The documents with a key column, and its name: the identifier where one row has it, else a hash of identifier and text, so that different texts under one identifier are documents of their own and repeated rows share a key."""
    key = free(docs, "__key")
    ids = F.col(id_col).cast("long")
    again = materialize(docs.groupBy(ids.alias("i")).count().filter("count > 1 or i is null").select("i"))
    if again.isEmpty():
        return docs.withColumn(key, ids), key
    twice = free(docs, "__twice")
    marked = docs.join(sized(again.select(F.col("i").alias(twice), F.lit(True).alias(f"{twice}y"))), ids.eqNullSafe(F.col(twice)), "left")
    own = F.xxhash64(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    return marked.withColumn(key, F.when(F.col(f"{twice}y"), own).otherwise(ids)).drop(twice, f"{twice}y"), key
