"""The SQL surface: functions, a table function, and views callable from SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import FEATURES, PRIMARY
from .geometry import solid_of


def register(spark: SparkSession) -> None:
    """Temporary SQL functions that the optimizer sees through, a table function and a grouped aggregate."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION adherence6(intent INT, bits INT) RETURNS INT RETURN CAST(6 * bit_count(intent & 15 & bits) / nullif(bit_count(intent & 15), 0) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION intent_size(intent INT) RETURNS INT RETURN bit_count(intent & 15)")
    words = " || ".join(f"CASE WHEN (intent & {1 << i}) <> 0 THEN '+{n}' ELSE '' END" for i, n in enumerate(PRIMARY))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION profile_of(intent INT) RETURNS STRING RETURN substr({words}, 2)")
    spoken = ", ".join(f"CASE WHEN (intent & {1 << b}) <> 0 THEN '{w}' END" for _, b, _, w in FEATURES)
    marked = ", ".join(f"CASE WHEN (intent & {1 << b}) <> 0 THEN '<{n}>' END" for n, b, _, _ in FEATURES)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION render_header(intent INT, form STRING) RETURNS STRING RETURN CASE WHEN coalesce(intent, 0) = 0 THEN '' WHEN form = 'token' THEN concat_ws(' ', '<WANT>', {marked}, '</WANT>') ELSE concat('# wants: ', concat_ws(', ', {spoken})) END")
    spark.udf.register("execute_program", solid_of)
    spark.udtf.register("explode_features", ExplodeFeatures)
    spark.udf.register("wilcoxon_z", wilcoxon_z)


@F.udtf(returnType=T.StructType([T.StructField("feature", T.StringType()), T.StructField("intended", T.BooleanType()), T.StructField("realized", T.BooleanType())]))
class ExplodeFeatures:
    """One row per primary feature of an intent and a realized set."""

    def eval(self, intent: int, realized: int):
        for i, n in enumerate(PRIMARY):
            yield n, bool((intent or 0) & (1 << i)), bool((realized or 0) & (1 << i))


@F.pandas_udf(T.DoubleType())
def wilcoxon_z(d: pd.Series) -> float:
    """Signed-rank z with zeros ranked then dropped; a grouped aggregate for small groups, the twin of the count-based test."""
    r = d.abs().round(12).rank()
    nz = d != 0
    var = float((r[nz] ** 2).sum()) / 4
    return (float(r[d > 0].sum()) - float(r[nz].sum()) / 2) / var**0.5 if var > 0 else None


def views(spark: SparkSession, tables: dict[str, DataFrame]) -> None:
    """Temporary views by name."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)
