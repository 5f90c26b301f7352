"""Tails as Column expressions: the normal tail and the hypergeometric one."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Coefficients of the rational-exponential fit of erfc whose relative error is below 1.2e-7 everywhere.
ERFC = (-1.26551223, 1.00002368, 0.37409196, 0.09678418, -0.18628806, 0.27886807, -1.13520398, 1.48851587, -0.82215223, 0.17087277)


def ln_upper(z: Column) -> Column:
    """Natural log of the upper tail of the standard normal at |z|."""
    x = F.abs(z) / F.sqrt(F.lit(2.0))
    t = 1.0 / (1.0 + 0.5 * x)
    poly = F.lit(0.0)
    for c in reversed(ERFC):
        poly = poly * t + c
    return F.ln(t) - x * x + poly - F.ln(F.lit(2.0))


def normal_sf(z: Column) -> Column:
    """P(Z >= z), with relative accuracy 1.2e-7 in the tail."""
    up = F.exp(ln_upper(z))
    return F.when(z >= 0, up).otherwise(1.0 - up)


def p_value(z: Column, alternative: Column | str) -> Column:
    """p of a z statistic: 'greater', 'less' or 'two-sided'."""
    alt = F.lit(alternative) if isinstance(alternative, str) else alternative
    return F.when(alt == "greater", normal_sf(z)).when(alt == "less", normal_sf(-z)).otherwise(2.0 * F.exp(ln_upper(z)))


def fisher_greater(a: Column, b: Column, c: Column, d: Column) -> Column:
    """P(X >= a) for the 2x2 table (a b; c d) with fixed margins.

    Terms follow from their neighbour by a ratio of integers, summed in logs
    from the observed cell on; the first term uses sums of logs.
    """
    ln_fact = lambda n: F.aggregate(F.sequence(F.lit(1), F.greatest(n, F.lit(1)).cast("int")), F.lit(0.0), lambda s, i: s + F.ln(i.cast("double")))
    n = a + b + c + d
    ln_p = ln_fact(a + b) + ln_fact(c + d) + ln_fact(a + c) + ln_fact(b + d) - ln_fact(n) - ln_fact(a) - ln_fact(b) - ln_fact(c) - ln_fact(d)
    more = F.least(b, c)
    start = F.struct(F.lit(1.0).alias("term"), F.lit(1.0).alias("sum"))
    tail = F.aggregate(
        F.sequence(F.lit(1), F.greatest(more, F.lit(1)).cast("int")), start,
        lambda s, i: F.struct((s["term"] * F.when(i <= more, ((b - i + 1) * (c - i + 1)).cast("double") / ((a + i) * (d + i)).cast("double")).otherwise(0.0)).alias("term"), (s["sum"] + s["term"] * F.when(i <= more, ((b - i + 1) * (c - i + 1)).cast("double") / ((a + i) * (d + i)).cast("double")).otherwise(0.0)).alias("sum")),
    )["sum"]
    return F.least(F.lit(1.0), F.exp(ln_p + F.ln(tail)))
