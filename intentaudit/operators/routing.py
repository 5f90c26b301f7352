"""Uptake of falsely named features, with exact and permutation nulls."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tails import fisher_greater
from ..schema import PRIMARY


def feature_rows(scores: DataFrame) -> DataFrame:
    """One row per wrong-arm output and primary feature that the true intent lacks: named in the header or not, realized or not."""
    s = scores.filter("arm = 'wrong'").select("model", "form", "seed", "program_id", "ok", F.explode(F.array(*[F.struct(F.lit(n).alias("feature"), (F.col("intent4").bitwiseAND(1 << i) != 0).alias("intended"), (F.col("h").bitwiseAND(1 << i) != 0).alias("named"), (F.col("psi5").bitwiseAND(1 << i) != 0).alias("real")) for i, n in enumerate(PRIMARY)])).alias("f"))
    return s.select("model", "form", "seed", "program_id", "ok", "f.*").filter("not intended")


def uptake(scores: DataFrame, by_seed: bool = False) -> DataFrame:
    """Per model, form, feature and row set (all, runnable), pooled over seeds or by seed: realization rate when named minus when not, its 95 % interval (unpooled variance) and the exact one-sided p."""
    rows = feature_rows(scores).withColumn("rows", F.explode(F.when(F.col("ok"), F.array(F.lit("all"), F.lit("runnable"))).otherwise(F.array(F.lit("all")))))
    cell = ["model", "form", *(["seed"] if by_seed else []), "feature", "rows"]
    g = rows.groupBy(*cell).agg(F.count_if("named").alias("n_named"), F.count_if(~F.col("named")).alias("n_unnamed"), F.count_if(F.col("named") & F.col("real")).alias("a"), F.count_if(~F.col("named") & F.col("real")).alias("c"))
    x, y = F.col("a") / F.nullif("n_named", F.lit(0)), F.col("c") / F.nullif("n_unnamed", F.lit(0))
    half = 1.959964 * F.sqrt(x * (1 - x) / F.nullif("n_named", F.lit(0)) + y * (1 - y) / F.nullif("n_unnamed", F.lit(0)))
    return g.select(*cell, "n_named", "n_unnamed", "a", "c", (x - y).alias("diff"), (x - y - half).alias("lo"), (x - y + half).alias("hi"), fisher_greater(F.col("a"), F.col("n_named") - F.col("a"), F.col("c"), F.col("n_unnamed") - F.col("c")).alias("p"))


def neither_named(scores: DataFrame) -> DataFrame:
    """Rate of features in neither header nor intent, minus the baseline's rate on the same features."""
    masks = lambda: F.array(*[F.struct(F.lit(n).alias("feature"), F.lit(1 << i).alias("bit")) for i, n in enumerate(PRIMARY)])
    base = scores.filter("model = 'U'").select("seed", "program_id", F.col("psi5").alias("base"))
    w = scores.filter("arm = 'wrong'").join(base, ["seed", "program_id"]).select("model", "form", "h", "intent4", "psi5", "base", F.explode(masks()).alias("m"))
    w = w.filter((F.col("h").bitwiseAND(F.col("m.bit")) == 0) & (F.col("intent4").bitwiseAND(F.col("m.bit")) == 0))
    return w.groupBy("model", "form", "m.feature").agg(F.count("*").alias("n"), F.avg((F.col("psi5").bitwiseAND(F.col("m.bit")) != 0).cast("int")).alias("rate"), F.avg((F.col("base").bitwiseAND(F.col("m.bit")) != 0).cast("int")).alias("base_rate"))


def compress(scores: DataFrame) -> DataFrame:
    """Identical (model, form, seed, header, intent, realized) with counts: what a re-assignment needs, whatever the number of rows."""
    return scores.filter("arm = 'wrong'").groupBy("model", "form", "seed", F.col("h").bitwiseAND(15).alias("h"), "intent4", F.col("psi5").bitwiseAND(15).alias("psi4")).agg(F.count("*").alias("c"))


def uptake_reassigned(scores: DataFrame, replicates: int = 2000) -> DataFrame:
    """Null of the uptake, per model, form and unit (a seed, or 'pooled'), when each header goes to another program of its seed.

    Replicate b orders a seed's programs by md5 and hands every header to the next
    in that order, so nobody keeps its own and the outputs' margin stays.
    Replicates x programs rows; for bounded samples. ``uptake_permutation`` has a
    cost that does not depend on the number of rows.
    """
    ids = scores.filter("arm = 'wrong'").select("seed", "program_id").distinct()
    cell = Window.partitionBy("seed", "b")
    order = F.md5(F.concat_ws(":", F.lit("U"), F.col("b").cast("string"), F.col("seed").cast("string"), F.col("program_id")).cast("binary"))
    turn = ids.withColumn("b", F.explode(F.sequence(F.lit(1), F.lit(replicates)))).withColumn("r", F.row_number().over(cell.orderBy(order, "program_id")) - 1).withColumn("n", F.count("*").over(cell))
    given = turn.select("seed", "b", F.col("program_id").alias("donor"), ((F.col("r") + 1) % F.col("n")).alias("r"))
    moved = turn.select("seed", "b", "r", "program_id").join(given, ["seed", "b", "r"]).select("seed", "b", "program_id", "donor")
    seen = ids.select("seed", F.lit(0).alias("b"), "program_id", F.col("program_id").alias("donor"))
    wrong = scores.filter("arm = 'wrong'")
    outputs = wrong.select("model", "form", "seed", "program_id", F.col("intent4").bitwiseAND(15).alias("i"), F.col("psi5").bitwiseAND(15).alias("p"))
    heads = wrong.select("model", "form", "seed", F.col("program_id").alias("donor"), F.col("h").bitwiseAND(15).alias("h"))
    both = moved.union(seen).join(outputs, ["seed", "program_id"]).join(heads, ["model", "form", "seed", "donor"])
    lacks = F.bitwise_not("i").bitwiseAND(15)
    named, unnamed = lacks.bitwiseAND(F.col("h")), lacks.bitwiseAND(F.bitwise_not("h"))
    counts = (("n1", named), ("k1", named.bitwiseAND(F.col("p"))), ("n0", unnamed), ("k0", unnamed.bitwiseAND(F.col("p"))))
    sums = both.groupBy("model", "form", "seed", "b").agg(*[F.sum(F.bit_count(c)).alias(k) for k, c in counts])
    units = sums.withColumn("unit", F.explode(F.array(F.lit("pooled"), F.col("seed").cast("string")))).groupBy("model", "form", "unit", "b").agg(*[F.sum(k).alias(k) for k, _ in counts])
    u = units.select("model", "form", "unit", "b", (F.col("k1") / F.nullif("n1", F.lit(0)) - F.col("k0") / F.nullif("n0", F.lit(0))).alias("u"))
    w = Window.partitionBy("model", "form", "unit")
    u = u.withColumn("observed", F.max(F.when(F.col("b") == 0, F.col("u"))).over(w)).filter("b > 0")
    out = u.groupBy("model", "form", "unit").agg(F.first("observed").alias("observed"), F.avg("u").alias("null_mean"), F.stddev_pop("u").alias("null_sd"), ((1 + F.count_if(F.round("u", 12) >= F.round("observed", 12))) / (1 + F.count("*"))).alias("p_perm"))
    return out.withColumn("z", (F.col("observed") - F.col("null_mean")) / F.nullif("null_sd", F.lit(0.0)))


def uptake_permutation(scores: DataFrame, replicates: int = 2000, seed: int = 2000) -> DataFrame:
    """Null of the uptake when headers are re-assigned to outputs within a seed: z and p per model, form and unit (a seed, or 'pooled').

    Works on compressed states: a group holds at most a few thousand distinct
    (header, intent, realized) rows. A re-assignment draws, state by state, how
    many outputs get which header (multivariate hypergeometric), so its cost does not depend on the number of rows.
    """
    import numpy as np
    import pandas as pd

    bits = lambda x: sum((x >> k) & 1 for k in range(4))

    def drawn(g: pd.DataFrame, rng) -> tuple[np.ndarray, np.ndarray]:
        """Observed (1 x 4) and re-assigned (replicates x 4) sums of one seed: named and realized, then not named and realized."""
        heads = g.groupby("h")["c"].sum()
        h, left = heads.index.to_numpy(), np.tile(heads.to_numpy(np.int64), (replicates, 1))
        sums = lambda n, i, p: np.stack([n * bits(~i & 15 & h), n * bits(~i & 15 & h & p), n * bits(~i & 15 & ~h), n * bits(~i & 15 & ~h & p)], axis=-1).sum(axis=-2)
        seen, null = np.zeros(4), np.zeros((replicates, 4))
        for (i, p), state in g.groupby(["intent4", "psi4"]):
            own = state.groupby("h")["c"].sum().reindex(h, fill_value=0).to_numpy()
            seen = seen + sums(own, i, p)
            rest, got = np.full(replicates, int(own.sum())), np.zeros_like(left)
            for k in range(len(h)):
                got[:, k] = rng.hypergeometric(left[:, k], left[:, k + 1 :].sum(axis=1), rest)
                rest = rest - got[:, k]
            left = left - got
            null += sums(got, i, p)
        return seen[None, :], null

    def null(pdf: pd.DataFrame) -> pd.DataFrame:
        rng = np.random.default_rng(seed)
        each = {str(s): drawn(g, rng) for s, g in pdf.groupby("seed")}
        each["pooled"] = tuple(sum(x) for x in zip(*each.values()))
        rows = []
        with np.errstate(all="ignore"):
            uptake = lambda x: x[:, 1] / x[:, 0] - x[:, 3] / x[:, 2]
            for unit, (seen, draws) in each.items():
                got, u = float(uptake(seen)[0]), uptake(draws)
                sd = float(u.std())
                rows.append((pdf["model"].iloc[0], pdf["form"].iloc[0], unit, got, float(u.mean()), sd, (1 + int((u >= got - 1e-12).sum())) / (1 + replicates), (got - float(u.mean())) / sd if sd else float("nan")))
        return pd.DataFrame(rows, columns=["model", "form", "unit", "observed", "null_mean", "null_sd", "p_perm", "z"])

    return compress(scores).groupBy("model", "form").applyInPandas(null, "model string, form string, unit string, observed double, null_mean double, null_sd double, p_perm double, z double")


def leave_one_out(d: DataFrame, by: str = "profile") -> DataFrame:
    """Rows repeated for every fold that keeps them: one fold per profile (by='profile'), or per primary feature (by='feature')."""
    folds = sorted(r[0] for r in d.select("profile").distinct().collect()) if by == "profile" else list(PRIMARY)  # at most eleven
    keep = [F.when((F.col("profile") != f) if by == "profile" else ~F.array_contains(F.split("profile", r"\+"), f), F.lit(f)) for f in folds]
    return d.withColumn("left_out", F.explode(F.array_compact(F.array(*keep))))


def diff_mass(d: DataFrame) -> DataFrame:
    """Sum of differences by profile, sign and joint runnability, with all subtotals."""
    s = F.when(F.col("d") > 0, "up").when(F.col("d") < 0, "down").otherwise("tie")
    return d.withColumn("sign", s).withColumn("runs", F.col("ok").cast("string")).cube("form", "profile", "sign", "runs").agg(F.count("*").alias("n"), F.sum(F.round(F.col("d") * 6)).cast("long").alias("mass6"))
