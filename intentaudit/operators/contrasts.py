"""Paired contrasts between arms: same seed, same program, one pivot instead of self-joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import DEFAULTS, Options
from .ranktests import wilcoxon


def value_of(model: str, form: str, arm: str, col: str = "adh6") -> Column:
    return F.max(F.when((F.col("model") == model) & (F.col("form") == form) & (F.col("arm") == arm), F.col(col)))


def paired(scores: DataFrame, arm: str, model: str = "M", forms=("text", "token"), ref=("U", "none", "uncond"), col: str = "adh6") -> DataFrame:
    """(form, seed, program_id, prefix_sha, profile, d, ok): arm minus reference at equal program and seed, in units of 1.

    One shuffle on (program, seed). A reference averaged over seeds is not offered.
    """
    aggs = [value_of(*ref, col).alias("ref"), value_of(*ref, "ok").alias("ref_ok")]
    for f in forms:
        aggs += [value_of(model, f, arm, col).alias(f"v_{f}"), value_of(model, f, arm, "ok").alias(f"ok_{f}")]
    wide = scores.groupBy("seed", "program_id", "prefix_sha", "profile").agg(*aggs)
    rows = F.array(*[F.struct(F.lit(f).alias("form"), ((F.col(f"v_{f}") - F.col("ref")) / 6.0).alias("d"), (F.col(f"ok_{f}") & F.col("ref_ok")).alias("ok")) for f in forms])
    return wide.select("seed", "program_id", "prefix_sha", "profile", F.explode(rows).alias("r")).select("r.form", "seed", "program_id", "prefix_sha", "profile", "r.d", "r.ok").filter("d is not null")


def dissociation_rows(scores: DataFrame, form: str = "text") -> DataFrame:
    """(seed, program_id, ..., drop_m, drop_r, d, ok) with d = M's drop minus R's drop, correct to wrong; four arms in one pivot."""
    parts = {f"{m}_{a}": (m, form, a) for m in ("M", "R") for a in ("correct", "wrong")}
    wide = scores.groupBy("seed", "program_id", "prefix_sha", "profile").agg(*[value_of(*c).alias(k) for k, c in parts.items()], *[value_of(*c, "ok").alias(f"ok_{k}") for k, c in parts.items()])
    m, r = (F.col("M_correct") - F.col("M_wrong")) / 6.0, (F.col("R_correct") - F.col("R_wrong")) / 6.0
    ok = F.col("ok_M_correct") & F.col("ok_M_wrong") & F.col("ok_R_correct") & F.col("ok_R_wrong")
    return wide.select(F.lit(form).alias("form"), "seed", "program_id", "prefix_sha", "profile", m.alias("drop_m"), r.alias("drop_r"), (m - r).alias("d"), ok.alias("ok")).filter("d is not null")


def clustered(d: DataFrame, key: str = "prefix_sha") -> DataFrame:
    """The mean difference of each (form, seed, cluster)."""
    return d.groupBy("form", "seed", key).agg((F.sum(F.round(F.col("d") * 6)) / (6 * F.count("*"))).alias("d"), F.count("*").alias("members"))


def largest_class(d: DataFrame, alternative: str = "less") -> DataFrame:
    """Share of the total effect from the largest prefix cluster, and the test without it."""
    sizes = d.groupBy("form", "seed", "prefix_sha").agg(F.count("*").alias("c"), F.sum(F.round(F.col("d") * 6)).alias("s"))
    cell = Window.partitionBy("form", "seed")
    top = sizes.withColumn("rk", F.row_number().over(cell.orderBy(F.desc("c"), "prefix_sha"))).withColumn("total", F.sum("s").over(cell)).filter("rk = 1")
    rest = wilcoxon(d.join(top.select("form", "seed", "prefix_sha"), ["form", "seed", "prefix_sha"], "left_anti"), ["form", "seed"], alternative=alternative)
    return top.select("form", "seed", F.col("c").alias("members"), F.when(F.col("total") != 0, F.col("s") / F.col("total")).alias("share")).join(rest.select("form", "seed", F.col("mean_d").alias("mean_without"), F.col("p").alias("p_without")), ["form", "seed"])


def profile_means(d: DataFrame) -> DataFrame:
    """Mean difference per form and profile, over seeds and programs."""
    return d.groupBy("form", "profile").agg(F.countDistinct("program_id").alias("n"), (F.sum(F.round(F.col("d") * 6)) / (6 * F.count("*"))).alias("effect"))


def reweight(d: DataFrame, weights: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Per form: the mean over profiles of at least ``profile_min_n`` programs (the guardrail), over all, and by natural weights (report only)."""
    p = profile_means(d).join(F.broadcast(weights.select("profile", "weight")), "profile")
    return p.groupBy("form").agg(F.avg(F.when(F.col("n") >= o.profile_min_n, F.col("effect"))).alias("guardrail"), F.avg("effect").alias("equal_all"), (F.sum(F.col("effect") * F.col("weight")) / F.sum("weight")).alias("natural"))


def by_reference_stratum(d: DataFrame, refs: DataFrame) -> DataFrame:
    """The contrast where the reference realizes its intent in full, in part, or not at all."""
    s = refs.select("program_id", F.when(F.col("adh6") == 6, "full").when(F.col("adh6") == 0, "none").otherwise("partial").alias("stratum"))
    return d.join(s, "program_id").groupBy("form", "seed", "stratum").agg(F.count("*").alias("n"), (F.sum(F.round(F.col("d") * 6)) / (6 * F.count("*"))).alias("effect"))


def metric_shift(scores: DataFrame) -> DataFrame:
    """Gain of the correct header under text recall, gated text recall and executed adherence, and its two parts."""
    m = scores.filter("arm in ('uncond', 'correct') and model in ('U', 'M')").groupBy("form", "seed").agg(*[(F.sum(c) / (6 * F.count("*"))).alias(c) for c in ("rec6", "gated6", "adh6")])
    base = m.filter("form = 'none'").select("seed", *[F.col(c).alias(f"b_{c}") for c in ("rec6", "gated6", "adh6")])
    g = m.filter("form <> 'none'").join(base, "seed").groupBy("form").agg(*[F.avg(F.col(c) - F.col(f"b_{c}")).alias(n) for c, n in (("rec6", "gain_text"), ("gated6", "gain_gated"), ("adh6", "gain_executed"))])
    return g.withColumn("execution_part", F.col("gain_gated") - F.col("gain_text")).withColumn("detector_part", F.col("gain_executed") - F.col("gain_gated"))


def control_offset(scores: DataFrame) -> DataFrame:
    """R's arms minus the baseline, by seed and arm."""
    base = scores.filter("model = 'U'").groupBy("seed").agg((F.sum("adh6") / (6 * F.count("*"))).alias("base"))
    return scores.filter("model = 'R'").groupBy("seed", "arm").agg((F.sum("adh6") / (6 * F.count("*"))).alias("level")).join(base, "seed").select("seed", "arm", "level", "base", (F.col("level") - F.col("base")).alias("offset"))


def per_profile(scores: DataFrame) -> DataFrame:
    """Arm levels by profile for text headers, wrong minus baseline and the interaction; descriptive, without p-values."""
    cells = {"baseline": ("U", "none", "uncond"), "m_correct": ("M", "text", "correct"), "m_wrong": ("M", "text", "wrong"), "r_correct": ("R", "text", "correct"), "r_wrong": ("R", "text", "wrong")}
    mean = lambda m, f, a: F.avg(F.when((F.col("model") == m) & (F.col("form") == f) & (F.col("arm") == a), F.col("adh6") / 6.0))
    t = scores.groupBy("profile").agg(F.countDistinct("program_id").alias("n"), *[mean(*c).alias(k) for k, c in cells.items()])
    return t.withColumn("wrong_minus_base", F.col("m_wrong") - F.col("baseline")).withColumn("interaction", (F.col("m_correct") - F.col("m_wrong")) - (F.col("r_correct") - F.col("r_wrong")))


def single_feature_order(table: DataFrame) -> DataFrame:
    """Single-feature profiles ranked by baseline, by gain and by interaction."""
    w = Window.partitionBy(F.lit(0))
    s = table.filter(~F.col("profile").contains("+") & (F.col("profile") != "")).withColumn("gain", F.col("m_correct") - F.col("baseline"))
    return s.select("profile", *[F.rank().over(w.orderBy(F.desc(c))).alias(f"rank_{c}") for c in ("baseline", "gain", "interaction")])


def regime(scores: DataFrame) -> DataFrame:
    """Per cell: inputs, runnable share, and whether a contrast with the baseline is defined (some baseline output runs)."""
    c = scores.groupBy("model", "form", "arm").agg(F.countDistinct("prefix_sha", "h").alias("distinct_prompts"), F.avg(F.col("ok").cast("int")).alias("executability"))
    base = scores.filter("model = 'U'").agg(F.max(F.col("ok").cast("int")).alias("base_runs"))
    return c.crossJoin(base).withColumn("defined", F.col("base_runs") == 1).drop("base_runs")


def offset_share(scores: DataFrame) -> DataFrame:
    """Of R's pooled gap to the baseline under a wrong header, the share already there under a correct one."""
    m = scores.filter("model in ('U', 'R')").agg(*[(F.sum(F.when(c, F.col("adh6"))) / (6 * F.count_if(c))).alias(k) for k, c in (("base", F.col("model") == "U"), ("right", (F.col("model") == "R") & (F.col("arm") == "correct")), ("wrong", (F.col("model") == "R") & (F.col("arm") == "wrong")))])
    return m.select((F.col("right") - F.col("base")).alias("offset_correct"), (F.col("wrong") - F.col("base")).alias("offset_wrong"), ((F.col("right") - F.col("base")) / F.nullif(F.col("wrong") - F.col("base"), F.lit(0.0))).alias("share"))


def joint_pooled(d: DataFrame) -> DataFrame:
    """The interaction over all (program, seed) pairs whose four arms run, pooled and by seed."""
    rows = d.filter("ok").select("d", F.explode(F.array(F.lit("pooled"), F.col("seed").cast("string"))).alias("unit"))
    return rows.groupBy("unit").agg(F.count("*").alias("n"), F.avg("d").alias("interaction"))


def retrieval_arm(scores: DataFrame, assigned: DataFrame, ref=("U", "none", "uncond")) -> DataFrame:
    """(form, seed, program_id, prefix_sha, profile, hit, d): M, text, whose header a retrieval step supplies, minus the baseline.

    assigned: (program_id, hit). Where the retrieved neighbour has the query's own label the
    program gets its own header, else the wrong one: a retrieval error acts as a wrong header.
    """
    wide = scores.groupBy("seed", "program_id", "prefix_sha", "profile").agg(value_of(*ref).alias("ref"), value_of("M", "text", "correct").alias("c"), value_of("M", "text", "wrong").alias("w"))
    got = wide.join(assigned.select("program_id", "hit"), "program_id")
    return got.select(F.lit("text").alias("form"), "seed", "program_id", "prefix_sha", "profile", "hit", ((F.when(F.col("hit"), F.col("c")).otherwise(F.col("w")) - F.col("ref")) / 6.0).alias("d")).filter("d is not null")
