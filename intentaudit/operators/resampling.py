"""Bootstrap intervals and retrospective power."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .ranktests import wilcoxon

#: The distribution function of Poisson(1) at 0 to 6.
POISSON = (0.36787944, 0.73575888, 0.91969860, 0.98101184, 0.99634015, 0.99940582, 0.99991676)


def _draw(n, *key) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[k.cast("string") for k in key]).cast("binary")), 1, 8), 16, 10).cast("long") % n


def _poisson(*key) -> Column:
    u = (_draw(2**31, *key).cast("double") + 0.5) / 2.0**31
    return sum((F.when(u > c, 1).otherwise(0) for c in POISSON), F.lit(0))


def _intervals(means: DataFrame, clusters: DataFrame) -> DataFrame:
    """(form, unit, estimate, lo, hi) from (form, unit, m); the unit is a seed or 'pooled'."""
    units = clusters.select("form", "d", F.explode(F.array(F.lit("pooled"), F.col("seed").cast("string"))).alias("unit"))
    est = units.groupBy("form", "unit").agg(F.avg("d").alias("estimate"))
    return means.groupBy("form", "unit").agg(F.percentile("m", 0.025).alias("lo"), F.percentile("m", 0.975).alias("hi")).join(est, ["form", "unit"]).select("form", "unit", "estimate", "lo", "hi")


def bootstrap_exact(clusters: DataFrame, replicates: int = 200) -> DataFrame:
    """Percentile intervals per form, pooled and per seed: for the pooled one seeds are drawn with replacement, then clusters
    within each drawn seed; for a seed's own its clusters are drawn.

    clusters: (form, seed, prefix_sha, d). Draws come from md5; the drawn
    table has replicates x seeds x clusters rows, for bounded samples, and meets the cluster means by join.
    """
    seeds = [r[0] for r in clusters.select("seed").distinct().orderBy("seed").collect()]
    if not seeds:
        return clusters.select("form", F.lit("pooled").alias("unit"), F.col("d").alias("estimate"), F.col("d").alias("lo"), F.col("d").alias("hi"))
    cell = Window.partitionBy("form", "seed")
    c = clusters.select("form", "seed", "d", (F.row_number().over(cell.orderBy("prefix_sha")) - 1).alias("i"), F.count("*").over(cell).alias("k"))
    size = c.groupBy("form").agg(F.max("k").alias("k"))
    # place s < number of seeds draws a seed; place 1000 + s is the seed of that place itself
    places = [*range(len(seeds)), *(1000 + s for s in range(len(seeds)))]
    draws = size.select("form", "k", F.explode(F.sequence(F.lit(1), F.lit(replicates))).alias("b")).withColumn("s", F.explode(F.array(*map(F.lit, places)))).withColumn("j", F.explode(F.sequence(F.lit(0), (F.col("k") - 1).cast("int"))))
    at = F.when(F.col("s") < 1000, _draw(len(seeds), F.lit("S"), F.col("b"), F.col("s"))).otherwise(F.col("s") - 1000)
    draws = draws.withColumn("seed", F.element_at(F.array(*map(F.lit, seeds)), (at + 1).cast("int"))).withColumn("i", _draw(F.col("k"), F.lit("C"), F.col("b"), F.col("s"), F.col("j")))
    unit = F.when(F.col("s") < 1000, F.lit("pooled")).otherwise(F.col("seed").cast("string"))
    means = draws.select("form", "b", unit.alias("unit"), "seed", "i").join(c.select("form", "seed", "i", "d"), ["form", "seed", "i"]).groupBy("form", "unit", "b").agg(F.avg("d").alias("m"))
    return _intervals(means, clusters)


def bootstrap_poisson(clusters: DataFrame, replicates: int = 200) -> DataFrame:
    """The same two levels with Poisson(1) weights in place of draws: of a cluster by (replicate, seed, cluster), and for the pooled interval of a seed by (replicate, seed); one pass, no draw table."""
    rows = clusters.withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("w", _poisson(F.lit("P"), F.col("b"), F.col("seed"), F.col("prefix_sha"))).withColumn("ws", _poisson(F.lit("S"), F.col("b"), F.col("seed")))
    each = F.array(F.struct(F.lit("pooled").alias("unit"), (F.col("w") * F.col("ws")).alias("w")), F.struct(F.col("seed").cast("string").alias("unit"), F.col("w").alias("w")))
    rows = rows.select("form", "b", "d", F.explode(each).alias("u"))
    means = rows.groupBy("form", "u.unit", "b").agg((F.sum(F.col("u.w") * F.col("d")) / F.nullif(F.sum("u.w"), F.lit(0))).alias("m")).filter("m is not null")
    return _intervals(means, clusters)


def power_by_resampling(d: DataFrame, replicates: int = 100, alternative: str = "less", alpha: float = 0.05, min_seeds: int = 2, unit: str = "program_id") -> DataFrame:
    """Probability that at least ``min_seeds`` seeds are significant when the units (programs, or clusters of equal prefixes) are drawn again with Poisson(1) weights, the same in every seed."""
    rows = d.withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("w", _poisson(F.lit("W"), F.col("b"), F.col(unit))).filter("w > 0")
    t = wilcoxon(rows, ["form", "seed", "b"], alternative=alternative, weight="w", alpha=alpha)
    return t.groupBy("form", "b").agg(F.count_if("significant").alias("k")).groupBy("form").agg(F.avg((F.col("k") >= min_seeds).cast("int")).alias("power"))
