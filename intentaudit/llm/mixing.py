"""Mixing sources to target weights by Pareto order sampling.

Each source's target in words gives every document the same whole copies, which are certain; the rest
of the target is drawn without replacement and with unequal probabilities. A
document's inclusion probability is proportional to its size, or to a given weight, and scaled so that the expected words
are the rest; where that passes one the document is certain too. Documents are ranked by random
odds over inclusion odds and taken in that order until the rest is used: the sample's size is fixed in words, the unit of the targets.
The ranking is cut on binned sums, so no source is sorted in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, settled, take_in_order, text_of, uniform, word_count

WEIGHTS, CAP, SEED = (1, 2, 3), 3, "mix"


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """Add ``target`` to one row per source (source, source_size).

    Sources by code point, null last, take the weights in turn and share the
    total; a source stops at cap times its size and the excess is shared anew
    by weight. Sorted by cap*size/weight the capped sources are the first, so one
    running sum finds the common rate. The table has one row per source.
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))
    pick = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.row_number().over(order) - 1) % len(weights) + 1).cast("int"))
    s = sizes.withColumn("__w", pick).withColumn("__top", F.lit(float(cap)) * F.col("source_size"))
    by = Window.orderBy(F.col("__top") / F.col("__w"), F.col("source").isNull(), F.col("source").cast("binary"))
    before, every = by.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    s = s.withColumn("__rate", (F.sum("source_size").over(every) - F.coalesce(F.sum("__top").over(before), F.lit(0.0))) / (F.sum("__w").over(every) - F.coalesce(F.sum("__w").over(before), F.lit(0.0))))
    # the common rate is that of the first source which it does not fill
    s = s.withColumn("__free", F.when(F.col("__rate") * F.col("__w") < F.col("__top"), F.col("__rate"))).withColumn("__common", F.first("__free", True).over(by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    return s.select("source", "source_size", F.least("__top", F.coalesce(F.col("__common") * F.col("__w"), F.col("__top"))).alias("target"))


def inclusion(rows: DataFrame, plan: DataFrame) -> DataFrame:
    """(__key, __rate): probability per unit of ``__q``, from (__key, size, __q) and the words ``__left`` of each key.

    With probabilities least(1, rate * q), the expected words are ``__left``. Sorted by falling q the certain documents
    come first, so running sums over the distinct values of q find the rate of every number of them, and
    the first that leaves no further one certain holds.
    """
    steps = rows.filter("__q > 0 and size > 0").groupBy("__key", "__q").agg(F.sum("size").cast("double").alias("__s"))
    down = Window.partitionBy("__key").orderBy(F.desc("__q"))
    above = F.coalesce(F.sum("__s").over(down.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rest = F.sum(F.col("__q") * F.col("__s")).over(down.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    rated = steps.join(plan.select("__key", "__left"), "__key").select("__key", "__q", ((F.col("__left") - above) / rest).alias("__rate"))
    return rated.filter("__rate * __q < 1").groupBy("__key").agg(F.max_by("__rate", "__q").alias("__rate"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weight_col: str | None = None, weights: tuple[int, ...] = WEIGHTS, cap: int = CAP, seed: str = SEED) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken, copies, inclusion.

    ``inclusion`` is the probability of a copy beyond the whole ones, proportional to the size or to ``weight_col`` (rounded to three
    digits; null counts as 1, what is not positive as 0). Words come near the target:
    documents are taken in Pareto order while they fit, then the one whose size
    is nearest to the gap if that helps. A null source is a source of its own,
    a null text has size 0, a text of any length is counted whole. Repeated rows share identifier and
    fate. Reruns agree: the random odds come from an md5 of the identifier. An empty table gives an empty result; extra columns are ignored.
    """
    if weight_col:
        w = F.greatest(F.coalesce(F.col(weight_col).cast("double"), F.lit(1.0)), F.lit(0.0))
        unit = F.pow(F.lit(10.0), F.floor(F.log10(F.when(w > 0, w).otherwise(1.0))) - 2)
        weight = F.round(w / unit) * unit
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(text_of(text_col)).alias("size"), *([weight.alias("__q")] if weight_col else []))
    base = materialize(base if weight_col else base.withColumn("__q", F.col("size").cast("double")))
    plan = source_targets(base.groupBy("source").agg(F.sum("size").alias("source_size")), weights, cap)
    plan = (
        plan.withColumn("__ratio", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
        .withColumn("__whole", F.floor("__ratio").cast("long"))
        .withColumn("__left", F.col("target") - F.col("__whole") * F.col("source_size"))
        .withColumn("__key", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("null")))
        .drop("source")
    )
    keyed = base.withColumn("__key", F.coalesce(F.concat(F.lit("s"), F.col("source")), F.lit("null"))).drop("source")
    plan = settled(plan)
    plan = settled(plan.join(inclusion(keyed, plan), "__key", "left").withColumn("__rate", F.coalesce("__rate", F.lit(0.0))))
    rows = keyed.join(plan, "__key").withColumn("inclusion", F.least(F.lit(1.0), F.col("__rate") * F.col("__q")))
    u = uniform(seed, F.col("doc_id"))
    p = F.least(F.greatest(F.col("inclusion"), F.lit(1e-9)), F.lit(1 - 1e-9))
    odds = (u / (1 - u)) / (p / (1 - p))
    place = F.when(F.col("inclusion") >= 1, F.lit(0.0)).otherwise(odds / (1 + odds))
    rows = rows.withColumn("__place", place).withColumn("__id", F.coalesce("doc_id", F.lit(-(2**63)))).drop("__q", "__rate")
    cut = take_in_order(rows, plan, "__key", "__place", "size", "__left", "__id")
    used = cut.groupBy("__key").agg((F.first("__left") - F.coalesce(F.sum(F.when(F.col("__in"), F.col("size"))), F.lit(0))).alias("__gap"))
    near = F.abs(F.col("size") - F.col("__gap"))
    fill = (
        cut.filter(~F.col("__in") & (F.col("size") > 0))
        .join(settled(used), "__key")
        .filter(near < F.col("__gap"))
        .groupBy("__key")
        .agg(F.min_by("__id", F.struct(near.alias("a"), F.col("__place").alias("b"), F.col("__id").alias("c"))).alias("__fill"))
    )
    once = F.when(F.col("__in") | F.coalesce(F.col("__id") == F.col("__fill"), F.lit(False)), 1).otherwise(0)
    return cut.join(settled(fill), "__key", "left").select("doc_id", "size", "source_size", "target", ((F.col("__whole") + once) * F.col("size")).cast("long").alias("taken"), (F.col("__whole") + once).cast("int").alias("copies"), "inclusion")


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text,''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
s1 AS (SELECT *, [1.0,2.0,3.0][((row_number() OVER (ORDER BY source IS NULL, encode(source)) - 1) % 3 + 1)::INT]::DOUBLE AS w, 3.0::DOUBLE * source_size AS top FROM s0),
s2 AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(top) OVER (ORDER BY top / w, source IS NULL, encode(source) ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) / (sum(w) OVER () - coalesce(sum(w) OVER (ORDER BY top / w, source IS NULL, encode(source) ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) AS rate FROM s1),
s3 AS (SELECT source, source_size, least(top, coalesce((SELECT min_by(rate, top / w) FROM s2 WHERE rate * w < top) * w, top)) AS target FROM s2),
s4 AS (SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS ratio FROM s3),
s5 AS (SELECT *, floor(ratio)::BIGINT AS whole, target - floor(ratio)::BIGINT * source_size AS rest FROM s4),
q0 AS (SELECT source, size::DOUBLE AS q, sum(size)::DOUBLE AS s FROM d WHERE size > 0 GROUP BY ALL),
q1 AS (SELECT q0.source, q, (rest - coalesce(sum(s) OVER (PARTITION BY q0.source ORDER BY q DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) / sum(q * s) OVER (PARTITION BY q0.source ORDER BY q DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rate FROM q0 JOIN s5 ON q0.source IS NOT DISTINCT FROM s5.source),
q2 AS (SELECT source, max_by(rate, q) AS rate FROM q1 WHERE rate * q < 1 GROUP BY source),
r0 AS (SELECT d.doc_id, d.source, d.size, s5.source_size, s5.target, whole, rest, (('0x' || substr(md5('mix:' || d.doc_id), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0 AS u,
       least(1.0, coalesce(rate, 0.0) * d.size) AS inclusion FROM d JOIN s5 ON d.source IS NOT DISTINCT FROM s5.source LEFT JOIN q2 ON d.source IS NOT DISTINCT FROM q2.source),
r00 AS (SELECT *, least(greatest(inclusion, 1e-9), 1 - 1e-9) AS p FROM r0),
r1 AS (SELECT *, CASE WHEN inclusion >= 1 THEN 0.0 ELSE ((u / (1 - u)) / (p / (1 - p))) / (1 + (u / (1 - u)) / (p / (1 - p))) END AS place FROM r00),
r2 AS (SELECT *, sum(size) OVER (PARTITION BY source ORDER BY place, doc_id RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) <= rest AS inside FROM r1),
g AS (SELECT source, any_value(rest) - coalesce(sum(size) FILTER (inside), 0) AS gap FROM r2 GROUP BY source),
f AS (SELECT r2.source, arg_min(doc_id, (abs(size - gap), place, doc_id)) AS fill FROM r2 JOIN g ON r2.source IS NOT DISTINCT FROM g.source WHERE NOT inside AND size > 0 AND abs(size - gap) < gap GROUP BY r2.source)
SELECT r2.doc_id, size, source_size, target, ((whole + CASE WHEN inside OR coalesce(r2.doc_id = f.fill, false) THEN 1 ELSE 0 END) * size)::BIGINT AS taken, round(inclusion, 9) AS inclusion
FROM r2 LEFT JOIN f ON r2.source IS NOT DISTINCT FROM f.source
"""
