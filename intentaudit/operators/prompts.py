"""Prefix prompts: their clusters, leakage, first occurrences and completion cap."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.intent_text import phi
from ..schema import DEFAULTS, PRIMARY_MASK


def with_prefix(df: DataFrame, f: float = DEFAULTS.prefix_frac) -> DataFrame:
    """Add the first f of the characters as ``prefix``, and its hash."""
    out = df.withColumn("prefix", F.substring("program", F.lit(1), F.floor(F.length("program") * F.lit(int(round(f * 100))) / 100).cast("int")))
    return out.withColumn("prefix_sha", F.sha2("prefix", 256))


def prefix_clusters(df: DataFrame) -> DataFrame:
    return df.groupBy("prefix_sha").agg(F.count("*").alias("members"))


def prefix_leakage(df: DataFrame) -> DataFrame:
    """Share of programs whose prefix already shows an intended feature, with four and with five features."""
    hit = phi(F.col("prefix")).bitwiseAND(F.col("intent5"))
    return df.agg(F.count("*").alias("n"), F.avg((hit.bitwiseAND(PRIMARY_MASK) != 0).cast("int")).alias("leak4"), F.avg((hit != 0).cast("int")).alias("leak5"))


#: Feature to the pattern of its signature; the ratio features first show at the first raise.
SIGNATURES = {"CIRCLE": r"disc [0-9]+", "NGON": r"(seg [0-9]+ [0-9]+\n){4,}shut", "THIN": r"raise [0-9]+", "TALL": r"raise [0-9]+", "MULTI_PART": r"raise [0-9]+(.|\n)*raise [0-9]+"}


def first_occurrence(df: DataFrame) -> DataFrame:
    """Median place, as a share of the program's length, at which each intended feature's signature ends."""
    rows = []
    for i, (name, pattern) in enumerate(SIGNATURES.items()):
        before = F.regexp_extract("program", f"^((.|\n)*?{pattern})", 1)
        rows.append(F.when(F.col("intent5").bitwiseAND(1 << i) != 0, F.struct(F.lit(name).alias("feature"), (F.length(before) / F.length("program")).alias("at"))))
    return df.select(F.explode(F.array(*rows)).alias("s")).filter("s is not null").groupBy("s.feature").agg(F.count("*").alias("n"), F.percentile(F.col("s.at"), 0.5).alias("median_at"))


def calibrate_cap(train: DataFrame, k: int = DEFAULTS.calibration_k, q: float = DEFAULTS.cap_quantile) -> DataFrame:
    """Completion cap: the q-quantile of the completion length (statements) of k training programs chosen by md5."""
    few = train.orderBy(F.md5(F.concat(F.lit("cap:"), "program_id").cast("binary")), "program_id").limit(k)
    n = F.size(F.split(F.substring("program", F.length("prefix") + 1, F.length("program")), "\n"))
    return few.agg(F.count("*").alias("n"), F.percentile(n, q).alias("cap"))


def assert_same_sample(a: DataFrame, b: DataFrame, id_col: str = "sample_id") -> str:
    """The common hash of both samples; raises if they differ (two evaluations are never pooled)."""
    digest = lambda d: d.select(F.col(id_col).cast("string").alias("i")).distinct().agg(F.sha2(F.concat_ws(",", F.count("*").cast("string"), F.bit_xor(F.xxhash64("i")).cast("string"), F.sum(F.xxhash64("i").cast("decimal(38,0)")).cast("string")), 256)).collect()[0][0]
    x, y = digest(a), digest(b)
    if x != y:
        raise ValueError("different samples are never pooled")
    return x
