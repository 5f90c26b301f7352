"""Types, the feature catalogue and the options with their defaults."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import types as T

#: name, bit, whether it counts for adherence, words used in the text header
FEATURES = (("CIRCLE", 0, True, "circle"), ("NGON", 1, True, "polygon"), ("THIN", 2, True, "thin"), ("TALL", 3, True, "tall"), ("MULTI_PART", 4, False, "several parts"))
NAMES = tuple(f[0] for f in FEATURES)
PRIMARY = tuple(f[0] for f in FEATURES if f[2])
PRIMARY_MASK = sum(1 << f[1] for f in FEATURES if f[2])

SEEDS = (0, 1, 2)
FORMS = ("text", "token")

@dataclass(frozen=True)
class Options:
    """Frozen parameters of an audit."""

    prefix_frac: float = 0.40
    floor: int = 15
    n: int = 400
    draw_seed: str = "20260805"
    plan_seed: str = "plan"
    alpha: float = 0.05
    min_seeds: int = 2
    nonzero_frac: float = 0.15
    gate_adherence: float = 0.30
    gate_exec_margin: float = 0.10
    profile_min_n: int = 15
    thin_num: int = 3  # depth/width < 3/10
    tall: int = 2  # depth/width > 2
    ngon_min: int = 5
    permutations: int = 2000
    bootstrap: int = 200
    cap_quantile: float = 0.95
    calibration_k: int = 20
    max_blocks: int = 3
    max_statements: int = 400


DEFAULTS = Options()

HISTORY = T.ArrayType(T.StructType([T.StructField("outline", T.StringType()), T.StructField("edges", T.IntegerType()), T.StructField("w", T.IntegerType()), T.StructField("d", T.IntegerType()), T.StructField("x", T.IntegerType()), T.StructField("closed", T.BooleanType())]))

GENERATION = T.StructType([
    T.StructField("sample_id", T.StringType()), T.StructField("model", T.StringType()), T.StructField("form", T.StringType()), T.StructField("arm", T.StringType()),
    T.StructField("prefix_frac", T.DoubleType()), T.StructField("seed", T.IntegerType()), T.StructField("injected_header", T.StringType()),
    T.StructField("completion", T.StringType()), T.StructField("hit_cap", T.BooleanType()), T.StructField("eos", T.BooleanType()),
])
