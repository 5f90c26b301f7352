"""Freezing, blinding and the fences around decisions."""

from __future__ import annotations

import ast
import hashlib
import inspect
import json
from dataclasses import asdict, fields
from datetime import datetime, timezone

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import DEFAULTS, Options

FORBIDDEN = {"avg", "mean", "signum", "sign", "wilcoxon", "rank", "percentile", "median"}
REPORTED = {"rec6", "gated6", "phi5"}
DECIDING = {"ok", "psi5", "adh6", "seed", "form", "model", "arm", "profile", "program_id", "prefix_sha", "d", "n", "drop_m", "drop_r", "h", "intent4", "intent5"}


def table_hash(df: DataFrame) -> str:
    """Order-free digest of a table: count, xor and sum of row hashes."""
    h = F.xxhash64(*[F.col(c) for c in sorted(df.columns)])
    r = df.agg(F.count("*"), F.bit_xor(h), F.sum(h.cast("decimal(38,0)"))).collect()[0]
    return hashlib.sha256(":".join(map(str, r)).encode()).hexdigest()


def freeze_entry(artifact: str, content: str, at: str, depends_on: str = "") -> tuple[str, str, str, str]:
    return artifact, hashlib.sha256(content.encode()).hexdigest(), at, depends_on


def options_hash(o: Options) -> str:
    return hashlib.sha256(json.dumps(asdict(o), sort_keys=True).encode()).hexdigest()


def asof_freeze(freezes: DataFrame, data: DataFrame) -> DataFrame:
    """For every data row (key, ts) the latest freeze (frozen_at) at or before it.

    Both sides meet in one sorted stream per partition key: an as-of join by a
    running last value rather than a range join.
    """
    from pyspark.sql import Window

    a = freezes.select("key", F.col("frozen_at").alias("ts"), F.lit(0).alias("side"), "artifact", F.lit(None).cast("long").alias("row"))
    b = data.select("key", "ts", F.lit(1).alias("side"), F.lit(None).cast("string").alias("artifact"), "row")
    w = Window.partitionBy("key").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.union(b)
    last = F.last(F.when(F.col("side") == 0, F.struct("artifact", F.col("ts").alias("frozen_at"))), True).over(w)
    return both.withColumn("f", last).filter("side = 1").select("key", "row", "ts", "f.artifact", "f.frozen_at")


def _instant(at: str) -> datetime:
    t = datetime.fromisoformat(at)
    return t if t.tzinfo else t.replace(tzinfo=timezone.utc)


def assert_frozen_first(frozen_at: str, data_at: str) -> None:
    """Compare as instants (ISO 8601; without a zone, UTC)."""
    if _instant(frozen_at) >= _instant(data_at):
        raise PermissionError("the protocol was not frozen before the data")


def assert_increment(base: Options, new: Options) -> list[str]:
    """Changed options; raises if anything but the sample size and its scaled thresholds changed."""
    changed = [f.name for f in fields(Options) if getattr(base, f.name) != getattr(new, f.name)]
    bad = set(changed) - {"n", "floor"}
    if bad:
        raise ValueError(f"an increment may not change {sorted(bad)}")
    return changed


def blinded_counts(d: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """Counts of non-zero differences by form and seed, whether they fall short, how many seeds of the form do, and the trigger (enough seeds in either form); nothing else."""
    c = d.groupBy("form", "seed").agg(F.count("*").alias("pairs"), F.count_if(F.col("d") != 0).alias("nonzero"))
    c = c.withColumn("below", F.col("nonzero") < o.nonzero_frac * F.col("pairs"))
    forms = c.groupBy("form").agg(F.count_if("below").alias("form_below"))
    every = forms.agg(F.max(F.col("form_below") >= o.min_seeds).alias("triggered"))
    return c.join(forms, "form").crossJoin(every)


def assert_blind(fn) -> None:
    """Raise if the function's source calls a mean, sign, rank or test."""
    tree = ast.parse(inspect.getsource(fn).lstrip())
    for node in ast.walk(tree):
        name = node.attr if isinstance(node, ast.Attribute) else node.id if isinstance(node, ast.Name) else ""
        if name in FORBIDDEN:
            raise PermissionError(f"{fn.__name__} uses {name}")


def assert_blind_plan(df: DataFrame) -> None:
    """Raise if the analyzed plan of a blinded frame holds a forbidden aggregate."""
    plan = df._jdf.queryExecution().analyzed().toString().lower()
    for name in FORBIDDEN:
        if f"{name}(" in plan:
            raise PermissionError(f"the plan uses {name}")


def assert_deciding_columns(columns) -> None:
    """Raise if a decision would read a report-only column."""
    extra = set(columns) - DECIDING
    if extra:
        raise PermissionError(f"report-only columns in a decision: {sorted(extra)}")


def columns_read(df: DataFrame) -> set[str]:
    """Names of the columns that the frame's plan reads from files."""
    leaves = df._jdf.queryExecution().sparkPlan().collectLeaves().mkString("\n").split("\n")
    return {c.split("#")[0].strip() for leaf in leaves if "FileScan" in leaf for c in leaf[leaf.find("[") + 1 : leaf.find("]")].split(",")}


def assert_decides(*frames: DataFrame) -> None:
    """Raise if the plan of a decision's frame reads a report-only column."""
    for df in frames:
        if extra := columns_read(df) & REPORTED:
            raise PermissionError(f"a decision reads {sorted(extra)}")


def assert_only_pairing_differs(train: DataFrame, own: str = "intent5", given: str = "g0", o: Options = DEFAULTS, other: Options = DEFAULTS) -> int:
    """Rows of the two training sets; raises unless programs, the multiset of headers and the options are equal, so that only the pairing differs."""
    if options_hash(o) != options_hash(other):
        raise AssertionError("the recipes differ")
    a, b = train.groupBy(F.col(own).alias("h")).agg(F.count("*").alias("x")), train.groupBy(F.col(given).alias("h")).agg(F.count("*").alias("y"))
    bad, n = a.join(b, "h", "full_outer").agg(F.count_if(~F.col("x").eqNullSafe(F.col("y"))), F.coalesce(F.sum("x"), F.lit(0))).collect()[0]
    if bad:
        raise AssertionError(f"{bad} headers have another frequency in the control's training set")
    return n


def arm_means(scores: DataFrame) -> DataFrame:
    return scores.groupBy("model", "form", "arm").agg((F.sum("adh6") / (6 * F.count("*"))).alias("m"))


def assert_means(scores: DataFrame, frozen: dict[tuple[str, str, str], float], tolerance: float = 1e-12) -> None:
    """Recomputed arm means against frozen ones."""
    now = {(r["model"], r["form"], r["arm"]): r["m"] for r in arm_means(scores).collect()}
    for k, v in frozen.items():
        if abs(now.get(k, float("nan")) - v) > tolerance or k not in now:
            raise AssertionError(f"arm mean of {k} moved")


def replay(scores: DataFrame, again: DataFrame) -> DataFrame:
    """Rows whose bits differ between two scorings of the same generations (empty if replayed)."""
    keys = ["program_id", "model", "form", "arm", "seed"]
    return scores.select(*keys, "ok", "phi5", "psi5").exceptAll(again.select(*keys, "ok", "phi5", "psi5"))


def verdict_json(primary: dict, secondary: dict | None) -> str:
    """The verdict with both runs, primary first; raises without the second."""
    if secondary is None:
        raise ValueError("both runs are reported together")
    return json.dumps([{"run": "primary", **primary}, {"run": "secondary", **secondary}])
