"""Profile counts, floor-plus-common-rate quotas, the seeded draw, and its comparators."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..schema import DEFAULTS, Options


def profile_counts(pool: DataFrame) -> DataFrame:
    return pool.groupBy("profile").agg(F.count("*").alias("pool"))


def allocate(counts: dict[str, int], n: int = 400, floor: int = 15) -> dict[str, int]:
    """Quotas: profiles that the common rate leaves below min(floor, pool) are pinned there, the rate is renewed for the rest until stable, then largest remainders."""
    n = min(n, sum(counts.values()))
    pinned: dict[str, int] = {}
    while True:
        free = {k: v for k, v in counts.items() if k not in pinned}
        left = n - sum(pinned.values())
        if left < 0:
            raise ValueError("the floors exceed the budget")
        if not free:
            return pinned
        rate = left / sum(free.values())
        low = {k: min(floor, v) for k, v in free.items() if v * rate < floor}
        if not low:
            break
        pinned |= low
    whole = {k: math.floor(v * rate) for k, v in free.items()}
    spare = left - sum(whole.values())
    for k in sorted(free, key=lambda k: (-(free[k] * rate - whole[k]), k))[:spare]:
        whole[k] += 1
    return pinned | whole


def quotas(pool: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """(profile, pool, quota); the counts, one row per profile, pass through the driver."""
    counts = {r["profile"]: r["pool"] for r in profile_counts(pool).collect()}
    given = allocate(counts, o.n, o.floor)
    return pool.sparkSession.createDataFrame([(k, v, given[k]) for k, v in sorted(counts.items())], "profile string, pool long, quota long")


def draw(pool: DataFrame, quota: DataFrame, seed: str = DEFAULTS.draw_seed) -> DataFrame:
    """The first ``quota`` programs of each profile by md5 of seed and identifier."""
    order = Window.partitionBy("profile").orderBy(F.md5(F.concat_ws(":", F.lit(seed), "program_id").cast("binary")), "program_id")
    most = quota.agg(F.max("quota")).collect()[0][0] or 0
    ranked = pool.withColumn("__r", F.row_number().over(order)).filter(F.col("__r") <= most)
    return ranked.join(F.broadcast(quota.select("profile", "quota")), "profile").filter("__r <= quota").drop("__r", "quota")


def draw_simple(pool: DataFrame, n: int, seed: str = DEFAULTS.draw_seed) -> DataFrame:
    """An unstratified draw of n."""
    return pool.orderBy(F.md5(F.concat_ws(":", F.lit(seed), "program_id").cast("binary")), "program_id").limit(n)


def equal_quotas(counts: dict[str, int], n: int) -> dict[str, int]:
    """As equal a split as the pools allow."""
    left, out = n, {}
    for i, (k, v) in enumerate(sorted(counts.items(), key=lambda x: (x[1], x[0]))):
        out[k] = min(v, left // (len(counts) - i))
        left -= out[k]
    return out


def proportional_quotas(counts: dict[str, int], n: int) -> dict[str, int]:
    return allocate(counts, n, 0)


def natural_weights(counts: DataFrame) -> DataFrame:
    return counts.withColumn("weight", F.col("pool") / F.sum("pool").over(Window.partitionBy(F.lit(0))))


def sample_facts(sample: DataFrame, pool: DataFrame) -> DataFrame:
    """Mean features per intent, share with TALL in sample and pool, profiles, distinct inputs."""
    s = sample.agg(F.count("*").alias("n"), F.avg(F.bit_count("intent4")).alias("mean_tags"), F.avg((F.col("intent4").bitwiseAND(8) != 0).cast("int")).alias("tall_sample"), F.countDistinct("profile").alias("profiles"), F.countDistinct("prefix_sha").alias("distinct_inputs"))
    return s.crossJoin(pool.agg(F.avg((F.col("intent4").bitwiseAND(8) != 0).cast("int")).alias("tall_pool")))


def sample_overlap(sample: DataFrame, other: DataFrame) -> DataFrame:
    """One row: programs of the sample, those whose text is also in the other sample, profiles that the other lacks, and the sample's programs in these."""
    shared = sample.join(other.select("program_sha").distinct(), "program_sha", "left_semi").agg(F.count("*").alias("shared"))
    new = sample.join(other.select("profile").distinct(), "profile", "left_anti").agg(F.countDistinct("profile").alias("new_profiles"), F.count("*").alias("in_new_profiles"))
    return sample.agg(F.count("*").alias("n")).crossJoin(shared).crossJoin(new)


def effective_size(generated: DataFrame) -> DataFrame:
    """Per cell: rows, distinct prompts (prefix and header) and distinct generations."""
    return generated.groupBy("model", "form", "arm").agg(F.count("*").alias("n"), F.countDistinct("prefix_sha", "h").alias("distinct_prompts"), F.countDistinct("program").alias("distinct_generations"))


def comparators(counts: DataFrame, n: int = DEFAULTS.n) -> DataFrame:
    """(profile, pool, equal, proportional): the quotas of the designs not taken."""
    pools = {r["profile"]: r["pool"] for r in counts.collect()}  # one row per profile
    n = min(n, sum(pools.values()))
    even, share = equal_quotas(pools, n), proportional_quotas(pools, n)
    return counts.sparkSession.createDataFrame([(k, v, even[k], share[k]) for k, v in sorted(pools.items())], "profile string, pool long, equal long, proportional long")
