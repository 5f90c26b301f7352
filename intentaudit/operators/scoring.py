"""Scores of generations under both detectors, and the measures over them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import execute, psi
from ..functions.intent_text import phi
from ..schema import PRIMARY, PRIMARY_MASK
from ..shipping import ship

CELL = ["model", "form", "arm"]


def adh6(intent4: Column, bits: Column) -> Column:
    """Six times the share of intended primary features that are there: an exact integer."""
    return (6 * F.bit_count(intent4.bitwiseAND(bits)) / F.bit_count(intent4)).cast("int")


def score(generated: DataFrame, sample: DataFrame) -> DataFrame:
    """Score rows: ok, phi5, psi5, adh6 (executed), rec6 (text), gated6, beside intent, profile and prompt hash.

    Each distinct program text is executed once.
    """
    ship(generated.sparkSession)
    texts = generated.select("program").distinct()
    bits = execute(texts).select("program", F.col("solid.ok").alias("ok"), F.col("solid.fail_reason").alias("fail_reason"), psi(F.col("solid")).alias("psi5"), phi(F.col("program")).alias("phi5"))
    rows = generated.join(bits, "program").join(sample.select("program_id", "intent4", "intent5", "profile", "prefix_sha"), "program_id")
    a, r = adh6(F.col("intent4"), F.col("psi5")), adh6(F.col("intent4"), F.col("phi5"))
    return rows.withColumn("adh6", a).withColumn("rec6", r).withColumn("gated6", F.when(F.col("ok"), r).otherwise(0))


def arm_levels(scores: DataFrame) -> DataFrame:
    """Every measure per cell: mean within seed, then over seeds; micro measures pool hits within a seed."""
    hit = F.bit_count(F.col("intent4").bitwiseAND(F.col("psi5")))
    made = F.bit_count(F.col("psi5").bitwiseAND(PRIMARY_MASK))
    seed = scores.groupBy(*CELL, "seed").agg(
        F.count("*").alias("n"), F.countDistinct("prefix_sha").alias("inputs"), (F.sum("adh6") / (6 * F.count("*"))).alias("adherence"), (F.sum("rec6") / (6 * F.count("*"))).alias("regex_recall"), (F.sum("gated6") / (6 * F.count("*"))).alias("gated_recall"),
        F.avg(F.col("ok").cast("int")).alias("executability"), F.sum(hit).alias("h"), F.sum(made).alias("m"), F.sum(F.bit_count("intent4")).alias("w"), F.avg((F.col("psi5").bitwiseAND(PRIMARY_MASK) == F.col("intent4")).cast("int")).alias("exact_set"),
        F.avg(F.when(F.col("ok"), made)).alias("features_per_runnable"), F.avg(F.when(F.col("ok") & (made > 0), made)).alias("features_given_any"), F.avg(F.when(F.col("ok"), (made == 0).cast("int"))).alias("runnable_without"), F.avg(F.when(F.col("ok"), F.col("adh6") / 6)).alias("runnable_adherence"),
    )
    seed = seed.withColumn("micro_precision", F.col("h") / F.nullif("m", F.lit(0))).withColumn("micro_recall", F.col("h") / F.col("w")).withColumn("micro_f1", 2 * F.col("h") / F.nullif(F.col("m") + F.col("w"), F.lit(0)))
    measures = ["adherence", "regex_recall", "gated_recall", "executability", "micro_precision", "micro_recall", "micro_f1", "exact_set", "features_per_runnable", "features_given_any", "runnable_without", "runnable_adherence"]
    return seed.groupBy(*CELL).agg(F.sum("n").alias("n"), F.max("inputs").alias("distinct_inputs"), *[F.round(F.avg(m), 9).alias(m) for m in measures])


def detector_agreement(scored: DataFrame) -> DataFrame:
    """Per primary feature, over all programs and over runnable ones: the 2x2 of text against solid."""
    cells = F.array(*[F.struct(F.lit(n).alias("feature"), (F.col("intent5").bitwiseAND(1 << i) != 0).alias("t"), (F.col("psi5").bitwiseAND(1 << i) != 0).alias("s")) for i, n in enumerate(PRIMARY)])
    rows = scored.select("ok", F.explode(cells).alias("c"))
    both = rows.withColumn("rows", F.explode(F.when(F.col("ok"), F.array(F.lit("all"), F.lit("runnable"))).otherwise(F.array(F.lit("all")))))
    return both.groupBy("c.feature", "rows").agg(F.count("*").alias("n"), F.avg((F.col("c.t") == F.col("c.s")).cast("int")).alias("agree"), F.count_if(F.col("c.t") & F.col("c.s")).alias("both"), F.count_if(F.col("c.t") & ~F.col("c.s")).alias("text_only"), F.count_if(~F.col("c.t") & F.col("c.s")).alias("solid_only"))


def reference_scores(programs: DataFrame) -> DataFrame:
    """Reference programs through their own metric."""
    ship(programs.sparkSession)
    e = execute(programs).withColumn("psi5", psi(F.col("solid"))).withColumn("ok", F.col("solid.ok"))
    return e.withColumn("adh6", F.when(F.col("intent4") > 0, adh6(F.col("intent4"), F.col("psi5"))))


def reference_self_score(refs: DataFrame) -> DataFrame:
    r = refs.filter("intent4 > 0")
    return r.agg(F.count("*").alias("n"), (F.sum("adh6") / (6 * F.count("*"))).alias("self_score"), F.count_if(F.col("adh6") == 6).alias("full"), F.count_if((F.col("adh6") > 0) & (F.col("adh6") < 6)).alias("partial"), F.count_if(F.col("adh6") == 0).alias("none"), F.count_if(~F.col("ok")).alias("not_running"))


def multi_part(scores: DataFrame) -> DataFrame:
    """Runnable outputs with a multi-part intent, and how many are several solids."""
    s = scores.filter("ok and (intent5 & 16) != 0")
    return s.groupBy(*CELL).agg(F.count("*").alias("n"), F.count_if(F.col("psi5").bitwiseAND(16) != 0).alias("realized"))


def recovery(scores: DataFrame, refs: DataFrame) -> DataFrame:
    """Arms on the samples whose reference does not run: mean and share of full scores."""
    bad = refs.filter("not ok").select("program_id")
    return scores.join(bad, "program_id", "left_semi").groupBy(*CELL).agg(F.count("*").alias("n"), (F.sum("adh6") / (6 * F.count("*"))).alias("adherence"), F.avg((F.col("adh6") == 6).cast("int")).alias("full"))


def output_identity(scores: DataFrame) -> DataFrame:
    """Per model, form and seed: cells runnable under both headers, and those with the same realized features."""
    p = scores.filter("arm in ('correct', 'wrong')").groupBy("model", "form", "seed", "program_id").agg(
        F.min("ok").alias("ok"), F.max(F.when(F.col("arm") == "correct", F.col("psi5").bitwiseAND(PRIMARY_MASK))).alias("c"), F.max(F.when(F.col("arm") == "wrong", F.col("psi5").bitwiseAND(PRIMARY_MASK))).alias("w")
    )
    return p.filter("ok").groupBy("model", "form", "seed").agg(F.count("*").alias("runnable"), F.count_if(F.col("c") == F.col("w")).alias("same"))
