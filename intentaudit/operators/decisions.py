"""Frozen decision rules over cells of test results."""

from __future__ import annotations

import functools
import operator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import DEFAULTS, Options
from .contrasts import profile_means
from .ranktests import wilcoxon


def power_flags(cells: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Cells with fewer non-zero pairs than ``nonzero_frac`` of n."""
    nz = F.col("n") - F.col("n_zero")
    return cells.withColumn("nonzero", nz).withColumn("flagged", nz < o.nonzero_frac * F.col("n"))


def guardrail(d: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Per form: mean over profiles of at least ``profile_min_n`` programs of their mean difference."""
    return profile_means(d).filter(F.col("n") >= o.profile_min_n).groupBy("form").agg(F.avg("effect").alias("guardrail"))


def decide_wrong_vs_none(d: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """One verdict row for the wrong-minus-baseline differences of both forms.

    'underpowered' if enough seeds are flagged in either form, whatever else holds; 'REPLICATED'
    if text has enough seeds in direction and enough significant, token enough in direction, no reverse is significant
    anywhere, the guardrail is negative, and every majority survives without
    flagged seeds; else 'clean negative'.
    """
    less = power_flags(wilcoxon(d, ["form", "seed"], alternative="less", alpha=o.alpha), o)
    rev = wilcoxon(d, ["form", "seed"], alternative="greater", alpha=o.alpha).select("form", "seed", F.col("significant").alias("reverse"))
    c = less.join(rev, ["form", "seed"])
    text, token, way, sig, on = F.col("form") == "text", F.col("form") == "token", F.col("in_direction"), F.col("significant"), ~F.col("flagged")
    v = c.agg(
        F.count_if(text & way).alias("text_direction"), F.count_if(text & sig & way).alias("text_significant"), F.count_if(token & way).alias("token_direction"),
        F.coalesce(F.bool_or("reverse"), F.lit(False)).alias("veto"), F.count_if(text & ~on).alias("text_flagged"), F.count_if(token & ~on).alias("token_flagged"),
        F.count_if(text & way & on).alias("text_direction_unflagged"), F.count_if(text & sig & way & on).alias("text_unflagged"), F.count_if(token & way & on).alias("token_unflagged"),
    )
    g = guardrail(d, o).filter("form = 'text'").agg(F.max("guardrail").alias("guardrail"))
    v = v.crossJoin(g)
    enough = lambda *names: functools.reduce(operator.and_, [F.col(n) >= o.min_seeds for n in names])
    passed = enough("text_direction", "text_significant", "token_direction", "text_direction_unflagged", "text_unflagged", "token_unflagged") & ~F.col("veto") & F.coalesce(F.col("guardrail") < 0, F.lit(False))
    return v.withColumn("verdict", F.when(enough("text_flagged") | enough("token_flagged"), "underpowered").when(passed, "REPLICATED").otherwise("clean negative"))


def competence_gate(scores: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Seeds in which R reaches the adherence floor in both arms, its pooled executability against the baseline's, and whether the gate passes."""
    r = scores.filter("model = 'R'").groupBy("seed").agg(*[(F.sum(F.when(F.col("arm") == a, F.col("adh6"))) / (6 * F.count_if(F.col("arm") == a))).alias(a) for a in ("correct", "wrong")])
    seeds = r.agg(F.count_if((F.col("correct") >= o.gate_adherence) & (F.col("wrong") >= o.gate_adherence)).alias("seeds_ok"))
    e = scores.agg(F.avg(F.when(F.col("model") == "R", F.col("ok").cast("int"))).alias("exec_r"), F.avg(F.when(F.col("model") == "U", F.col("ok").cast("int"))).alias("exec_base"))
    return seeds.crossJoin(e).withColumn("passed", (F.col("seeds_ok") >= o.min_seeds) & (F.col("exec_r") >= F.col("exec_base") - o.gate_exec_margin))


def dissociation_cells(d: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Per seed: both drops, the interaction, its test, and the jointly runnable mean."""
    t = power_flags(wilcoxon(d, ["seed"], alternative="greater", alpha=o.alpha), o).select("seed", "n", "nonzero", "flagged", F.col("mean_d").alias("interaction"), "z", "p", "significant", "in_direction")
    m = d.groupBy("seed").agg(F.avg("drop_m").alias("drop_m"), F.avg("drop_r").alias("drop_r"), F.count_if("ok").alias("n_joint"), F.avg(F.when(F.col("ok"), F.col("d"))).alias("joint"))
    return t.join(m, "seed")


def outcome(scores: DataFrame, d: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """The outcome mapping of the control: a failed gate is 'control invalid' and forbids a confirmed dissociation; enough flagged
    seeds are 'underpowered'; a powered test that does not pass is a 'clean negative'."""
    c = dissociation_cells(d, o)
    rev = wilcoxon(d, ["seed"], alternative="less", alpha=o.alpha).agg(F.coalesce(F.bool_or("significant"), F.lit(False)).alias("veto"))
    hit = F.col("significant") & F.col("in_direction")
    s = c.agg(F.count_if(hit).alias("seeds"), F.count_if(hit & ~F.col("flagged")).alias("unflagged"), F.count_if("flagged").alias("flagged"), (F.sum(F.col("joint") * F.col("n_joint")) / F.sum("n_joint")).alias("joint"), F.sum("n_joint").alias("n_joint"))
    g = guardrail(d, o).agg(F.max("guardrail").alias("guardrail"))
    v = s.crossJoin(rev).crossJoin(g).crossJoin(competence_gate(scores, o).select("passed"))
    ok = (F.col("seeds") >= o.min_seeds) & (F.col("unflagged") >= o.min_seeds) & ~F.col("veto") & F.coalesce((F.col("guardrail") > 0) & (F.col("joint") > 0), F.lit(False))
    return v.withColumn("outcome", F.when(~F.coalesce("passed", F.lit(False)), "control invalid").when(F.col("flagged") >= o.min_seeds, "underpowered").when(ok, "dissociation confirmed").otherwise("clean negative"))


def dose_response(levels: DataFrame) -> DataFrame:
    """Arm means in order correct, corrupted, random, wrong, and whether they fall monotonically (supporting only)."""
    means = {a: F.max(F.when(F.col("arm") == a, F.col("adherence"))).alias(a) for a in ("correct", "corrupted", "random", "wrong")}
    return levels.agg(*means.values()).withColumn("monotone", (F.col("correct") >= F.col("corrupted")) & (F.col("corrupted") >= F.col("random")) & (F.col("random") >= F.col("wrong")))
