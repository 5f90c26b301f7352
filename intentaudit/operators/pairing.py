"""Derangements of headers, and the checks that pairing is all that differs."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..shipping import ship


def global_rank(df: DataFrame, bucket: Column, *order: Column) -> DataFrame:
    """Add ``rank`` from 0 in the order of (bucket, order...), without one task holding all rows.

    Rows are ranked inside their bucket; bucket offsets come from the counts, a
    table with one row per bucket.
    """
    b = df.withColumn("__b", bucket)
    counts = b.groupBy("__b").agg(F.count("*").alias("__n"))
    before = Window.partitionBy(F.lit(0)).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("__b", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__o"))
    inside = F.row_number().over(Window.partitionBy("__b").orderBy(*order)) - 1
    return b.withColumn("__i", inside).join(offsets, "__b").withColumn("rank", F.col("__o") + F.col("__i")).drop("__b", "__i", "__o")


def _md5(seed: str, id_col: str) -> Column:
    return F.md5(F.concat_ws(":", F.lit(seed), F.col(id_col)).cast("binary"))


def bucket_of(order: Column, n: int, rows: int = 50_000) -> Column:
    """The leading digits of an md5, as many as leave about ``rows`` of n rows to a bucket."""
    return F.substring(order, 1, max(1, math.ceil(math.log(max(1, n / rows), 16))))


def derange(df: DataFrame, id_col: str, header: str, seed: str, shift: int = 1) -> DataFrame:
    """(id, given): every row gets the header of the row ``shift`` places on in md5 order. No fixed point for 1 <= shift < n; the marginal is unchanged."""
    n = df.count()
    if n < 2:
        raise ValueError("a derangement needs two rows")
    ranked = global_rank(df.select(id_col, header), bucket_of(_md5(seed, id_col), n), _md5(seed, id_col), F.col(id_col))
    donor = ranked.select(((F.col("rank") - shift + n) % n).alias("rank"), F.col(header).alias("given"))
    return ranked.join(donor, "rank").select(id_col, F.col(header).alias("own"), "given")


def derange_shuffled(df: DataFrame, id_col: str, header: str, seed: str) -> DataFrame:
    """Another plan: pair two independent orders; fixed points are repaired by a cyclic shift among themselves and one more row.

    Two random orders have one fixed point on average, whatever the number of rows, so the repair's window is small.
    """
    n = df.count()
    a = global_rank(df.select(id_col, header), bucket_of(_md5(seed, id_col), n), _md5(seed, id_col), F.col(id_col))
    b = global_rank(df.select(F.col(id_col).alias("donor_id"), F.col(header).alias("given")), bucket_of(_md5(seed + "'", "donor_id"), n), _md5(seed + "'", "donor_id"), F.col("donor_id"))
    pairs = a.join(b, "rank").select("rank", id_col, F.col(header).alias("own"), "donor_id", "given")
    fixed = F.col(id_col) == F.col("donor_id")
    extra = pairs.filter(~fixed).agg(F.min("rank")).collect()[0][0]
    cycle = pairs.filter(fixed | (F.col("rank") == F.lit(extra)))
    if not pairs.filter(fixed).isEmpty():
        order = Window.partitionBy(F.lit(0)).orderBy("rank")
        last = F.last("given").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
        moved = cycle.withColumn("given", F.coalesce(F.lag("given").over(order), last))
        pairs = pairs.join(cycle.select("rank"), "rank", "left_anti").unionByName(moved)
    return pairs.select(id_col, "own", "given")


def wrong_headers(sample: DataFrame, id_col: str = "program_id", header: str = "intent5", seed: str = "plan") -> DataFrame:
    """(id, own, given): nobody gets an equal header.

    Rows are ordered by header; a shift by the largest group passes every equal
    header. Feasible if that group is at most half; else it raises.
    """
    groups = sample.groupBy(header).count()
    top = groups.agg(F.max("count"), F.sum("count")).collect()[0]
    if not top[1] or 2 * top[0] > top[1]:
        raise ValueError("one header holds more than half of the sample")
    ranked = global_rank(sample.select(id_col, header), F.col(header), _md5(seed, id_col), F.col(id_col))
    donor = ranked.select(((F.col("rank") - top[0] + top[1]) % top[1]).alias("rank"), F.col(header).alias("given"))
    return ranked.join(donor, "rank").select(id_col, F.col(header).alias("own"), "given")


def chance_match(plan: DataFrame) -> DataFrame:
    """Share of rows whose given header equals their own, beside the sum of squared header shares."""
    n = Window.partitionBy(F.lit(0))
    p2 = plan.groupBy("own").count().withColumn("p", F.col("count") / F.sum("count").over(n)).agg(F.sum(F.col("p") * F.col("p")).alias("expected"))
    return plan.agg(F.count("*").alias("n"), F.avg((F.col("own") == F.col("given")).cast("int")).alias("matched")).crossJoin(p2)


def assert_same_marginal(plan: DataFrame) -> DataFrame:
    """Headers whose count changed; raises if there is one."""
    a, b = plan.select(F.col("own").alias("h")), plan.select(F.col("given").alias("h"))
    changed = a.exceptAll(b).unionAll(b.exceptAll(a))
    if not changed.isEmpty():
        raise AssertionError("the header marginal changed")
    return changed


def assert_same_injection(a: DataFrame, b: DataFrame) -> int:
    """Cells of (sample_id, seed) in both; raises unless the injected headers are identical."""
    both = a.select("sample_id", "seed", F.col("injected_header").alias("x")).join(b.select("sample_id", "seed", F.col("injected_header").alias("y")), ["sample_id", "seed"], "full_outer")
    n, bad = both.agg(F.count("*"), F.count_if(~F.col("x").eqNullSafe(F.col("y")))).collect()[0]
    if bad:
        raise AssertionError(f"{bad} injected headers differ")
    return n


def retrieved_header(emb: DataFrame, labels: str = "label", block: int = 4096, every: int = 50) -> DataFrame:
    """(vec_id, own, given, cosine): the label of the nearest other vector.

    The query side is a stated set (every vector whose id is divisible by ``every``) against all rows, in
    blocks of ``block`` vectors: a block is broadcast, one scan multiplies it with the table batch by batch, and each task keeps
    one best row per query. Ties go to the smaller identifier; vectors of length 0 are like nothing.
    """
    spark = emb.sparkSession
    ship(spark)
    queries = emb.filter(F.col("vec_id") % every == 0).select("vec_id", F.col(labels).alias("own"), "embedding")
    rows = emb.select("vec_id", F.col(labels).alias("given"), "embedding")
    given_type = dict(rows.dtypes)["given"]
    ranked = global_rank(queries, F.floor(F.col("vec_id") / (every * block)), F.col("vec_id"))
    n = ranked.count()
    best = None
    for lo in range(0, n, block):
        part = ranked.filter((F.col("rank") >= lo) & (F.col("rank") < lo + block)).select("vec_id", "embedding").toArrow()  # at most ``block`` vectors
        held = spark.sparkContext.broadcast((part.column("vec_id").to_numpy(), _unit(part.column("embedding"))))

        def nearest(batches, held=held):
            ids, q = held.value
            top, at, label = np.full(len(ids), -np.inf), np.zeros(len(ids), np.int64), [None] * len(ids)
            for b in batches:
                vec, names = b.column("vec_id").to_numpy(), b.column("given").to_pylist()
                sims = np.round(q @ _unit(b.column("embedding")).T, 9)
                sims[ids[:, None] == vec[None, :]] = -np.inf
                order = np.argsort(vec, kind="stable")
                i = order[np.argmax(sims[:, order], axis=1)]
                value = sims[np.arange(len(ids)), i]
                for k in np.flatnonzero((value > top) | ((value == top) & np.isfinite(value) & (vec[i] < at))):
                    top[k], at[k], label[k] = value[k], vec[i[k]], names[i[k]]
            k = np.flatnonzero(np.isfinite(top))
            yield pa.record_batch([pa.array(ids[k]), pa.array(top[k]), pa.array(at[k]), pa.array([label[j] for j in k], b_type)], ["vec_id", "cosine", "other", "given"])

        b_type = part.schema.field("vec_id").type if given_type in ("bigint", "long") else {"int": pa.int32(), "string": pa.string()}[given_type]
        found = rows.mapInArrow(nearest, f"vec_id long, cosine double, other long, given {given_type}")
        best = found if best is None else best.union(found)
    if best is None:
        return queries.select("vec_id", "own", F.col("own").alias("given"), F.lit(0.0).alias("cosine"))
    one = best.groupBy("vec_id").agg(F.min_by(F.struct("given", "cosine"), F.struct((-F.col("cosine")).alias("c"), "other")).alias("b"))
    return queries.select("vec_id", "own").join(one, "vec_id").select("vec_id", "own", F.col("b.given").alias("given"), F.col("b.cosine").alias("cosine"))


def _unit(column) -> np.ndarray:
    """Arrow lists of equal length as rows of length one; a zero vector stays zero."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    x = column.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(column), -1) if len(column) else np.zeros((0, 0))
    n = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return x / np.where(n > 0, n, 1)
