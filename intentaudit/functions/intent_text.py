"""The text detector: intent bits read off program text by patterns only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import DEFAULTS, FEATURES, PRIMARY, PRIMARY_MASK, Options


def _numbers(program: Column, pattern: str, group: int = 1) -> Column:
    return F.transform(F.regexp_extract_all(program, F.lit(pattern), group), lambda s: s.cast("int"))


def phi(program: Column, o: Options = DEFAULTS) -> Column:
    """Bits of CIRCLE, NGON, THIN, TALL and MULTI_PART as one int.

    Depth is the largest raise, extent the largest planar coordinate or disc
    diameter; ratios are compared as integer products, strictly.
    """
    p = F.coalesce(program, F.lit(""))
    depth = F.array_max(_numbers(p, r"raise ([0-9]{1,8})"))
    extent = F.array_max(F.concat(_numbers(p, r"(?:pen|seg) ([0-9]{1,8}) [0-9]{1,8}"), _numbers(p, r"(?:pen|seg) [0-9]{1,8} ([0-9]{1,8})"), F.transform(_numbers(p, r"disc ([0-9]{1,8})"), lambda r: 2 * r)))
    bits = (
        p.rlike(r"disc [0-9]+"),
        p.rlike(rf"(seg [0-9]+ [0-9]+\n){{{o.ngon_min - 1},}}shut"),
        F.coalesce(10 * depth < o.thin_num * extent, F.lit(False)),
        F.coalesce(depth > o.tall * extent, F.lit(False)),
        F.regexp_count(p, F.lit(r"raise [0-9]+")) > 1,
    )
    return sum((F.when(b, 1 << i).otherwise(0) for i, b in enumerate(bits)), F.lit(0)).cast("int")


def intent_size(bits: Column) -> Column:
    return F.bit_count(bits.bitwiseAND(PRIMARY_MASK)).cast("int")


def profile(bits: Column) -> Column:
    """Primary features joined by '+', '' for none."""
    return F.concat_ws("+", *[F.when(bits.bitwiseAND(1 << i) != 0, n) for i, n in enumerate(PRIMARY)])


def with_intent(df: DataFrame, program: str = "program") -> DataFrame:
    return df.withColumn("intent5", phi(F.col(program))).withColumn("intent4", F.col("intent5").bitwiseAND(PRIMARY_MASK)).withColumn("profile", profile(F.col("intent4")))


def primary_only(df: DataFrame) -> DataFrame:
    """Rows with a requirement; an empty four-feature intent is excluded."""
    return df.filter(F.col("intent4") > 0)


def feature_map(bits: Column) -> Column:
    """Bits as a map from feature name to boolean."""
    return F.map_from_arrays(F.array(*[F.lit(f[0]) for f in FEATURES]), F.array(*[bits.bitwiseAND(1 << f[1]) != 0 for f in FEATURES]))
