"""Rank tests on counts of distinct values: no sort of the rows, one small window per cell."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tails import p_value


def value_counts(d: DataFrame, cell: list[str], col: str = "d", weight: str | None = None) -> DataFrame:
    """(cell, v, pos, neg): counts of rows by absolute difference and sign; 12 decimals identify equal values."""
    w = F.col(weight) if weight else F.lit(1)
    v = F.round(F.abs(F.col(col).cast("double")), 12)
    return d.groupBy(*cell, v.alias("v")).agg(F.sum(F.when(F.col(col) > 0, w).otherwise(0)).alias("pos"), F.sum(F.when(F.col(col) < 0, w).otherwise(0)).alias("neg"), F.sum(w).alias("c"))


def wilcoxon(d: DataFrame, cell: list[str], col: str = "d", alternative: str = "less", zeros: str = "pratt", weight: str | None = None, alpha: float = 0.05) -> DataFrame:
    """Signed-rank test per cell, asymptotic, no continuity correction.

    ``zeros``: 'pratt' ranks zeros and then drops their ranks; 'drop' removes
    them first; 'split' gives half of their rank sum to each side; 'sign'
    ignores magnitudes. The variance is a quarter of the sum of squared midranks
    that take part, which holds the corrections for ties and zeros. A cell
    without non-zero differences has p null and is not significant.
    """
    counts = value_counts(d, cell, col, weight)
    if zeros == "drop":
        ranked = counts.filter("v > 0")
    else:
        ranked = counts
    before = Window.partitionBy(*cell).orderBy("v").rowsBetween(Window.unboundedPreceding, -1)
    r = F.coalesce(F.sum("c").over(before), F.lit(0)) + (F.col("c") + 1) / 2.0
    if zeros == "sign":
        r = F.lit(1.0)
    ranked = ranked.withColumn("r", r)
    nz = F.col("v") > 0
    agg = ranked.groupBy(*cell).agg(
        F.sum(F.col("pos") * F.col("r")).alias("t_plus0"),
        F.sum(F.when(nz, F.col("c") * F.col("r")).otherwise(0.0)).alias("sr"),
        F.sum(F.when(nz, F.col("c") * F.col("r") * F.col("r")).otherwise(0.0)).alias("sr2"),
        F.sum(F.when(~nz, F.col("c") * F.col("r")).otherwise(0.0)).alias("zr"),
        F.sum(F.when(~nz, F.col("c") * F.col("r") * F.col("r")).otherwise(0.0)).alias("zr2"),
    )
    split = zeros == "split"
    t = F.col("t_plus0") + (F.col("zr") / 2 if split else F.lit(0.0))
    mean = (F.col("sr") + (F.col("zr") if split else F.lit(0.0))) / 2
    var = (F.col("sr2") + (F.col("zr2") if split else F.lit(0.0))) / 4
    agg = agg.withColumn("t_plus", t).withColumn("z", F.when(F.col("sr2") > 0, (t - mean) / F.sqrt(var)))
    totals = counts.groupBy(*cell).agg(F.sum("c").alias("n"), F.sum(F.when(~nz, F.col("c")).otherwise(0)).alias("n_zero"), F.sum("pos").alias("n_pos"), F.sum("neg").alias("n_neg"), (F.sum(F.col("v") * (F.col("pos") - F.col("neg"))) / F.sum("c")).alias("mean_d"))
    keys = [F.col(f"t.{c}").eqNullSafe(F.col(f"a.{c}")) for c in cell]
    cond = keys[0]
    for k in keys[1:]:
        cond = cond & k
    out = totals.alias("t").join(agg.alias("a"), cond, "left").select(*[F.col(f"t.{c}").alias(c) for c in cell], "n", "n_zero", "n_pos", "n_neg", "mean_d", "t_plus", "z")
    out = out.withColumn("p", p_value(F.col("z"), alternative))
    want = F.lit(1) if alternative == "greater" else F.lit(-1) if alternative == "less" else F.signum("mean_d")
    return out.withColumn("significant", F.coalesce(F.col("p") < alpha, F.lit(False))).withColumn("in_direction", F.coalesce(F.signum("mean_d") == want, F.lit(False)) & (F.col("mean_d") != 0))


def mann_whitney(df: DataFrame, cell: list[str], value: str, group: str) -> DataFrame:
    """Two-sided rank-sum test of group 1 against group 0, with ties; asymptotic, no continuity correction."""
    c = df.groupBy(*cell, value).agg(F.sum(F.when(F.col(group) == 1, 1).otherwise(0)).alias("x"), F.count("*").alias("c"))
    before = Window.partitionBy(*cell).orderBy(value).rowsBetween(Window.unboundedPreceding, -1)
    r = F.coalesce(F.sum("c").over(before), F.lit(0)) + (F.col("c") + 1) / 2.0
    s = c.withColumn("r", r).groupBy(*cell).agg(F.sum("x").alias("n1"), F.sum("c").alias("n"), F.sum(F.col("x") * F.col("r")).alias("rs"), F.sum(F.expr("1.0D * c * c * c - c")).alias("ties"))
    n1, n = F.col("n1"), F.col("n")
    n0 = n - n1
    u = F.col("rs") - n1 * (n1 + 1) / 2
    var = n1 * n0 / 12.0 * ((n + 1) - F.col("ties") / (n * (n - 1)))
    z = F.when((var > 0), (u - n1 * n0 / 2.0) / F.sqrt(var))
    return s.select(*cell, "n1", n0.alias("n0"), u.alias("u"), z.alias("z")).withColumn("p", p_value(F.col("z"), "two-sided"))


def sign_flip(d: DataFrame, cell: list[str], unit: str, replicates: int = 500, col: str = "d", alternative: str = "less") -> DataFrame:
    """Permutation p of the mean under random signs drawn by md5; zero differences keep their place."""
    b = F.explode(F.sequence(F.lit(1), F.lit(replicates)))
    rows = d.filter(F.col(col) != 0).select(*cell, unit, F.col(col).alias("__d"), b.alias("b"))
    flip = F.when(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("flip"), F.col("b").cast("string"), F.col(unit).cast("string")).cast("binary")), 1, 1), 16, 10).cast("int") % 2 == 0, 1).otherwise(-1)
    null = rows.groupBy(*cell, "b").agg(F.sum(flip * F.col("__d")).alias("s"))
    seen = d.groupBy(*cell).agg(F.sum(col).alias("obs"))
    s, obs = F.round("s", 9), F.round("obs", 9)  # sums in any order
    hit = s <= obs if alternative == "less" else s >= obs
    return null.join(seen, cell).groupBy(*cell).agg(((1 + F.count_if(hit)) / (1 + F.lit(replicates))).alias("p"))
