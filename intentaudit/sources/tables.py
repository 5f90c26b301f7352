"""Given tables, and the sketch programs derived from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import DEFAULTS, Options

#: Fixed values of the sketch carrier: outline by the first word of the part type, depth factor by discount, offset by supplier.
OUTLINES = {"SMALL": 0, "ECONOMY": 3, "STANDARD": 4, "PROMO": 5, "MEDIUM": 6, "LARGE": 8}
DEPTHS = (1, 1, 1, 2, 2, 2, 5, 8, 12, 25, 30)
OFFSETS = (0, 0, 5, 200)
#: Loops on a 10x10 grid by number of vertices; the five-vertex one is a square with a redundant vertex.
LOOPS = {
    3: ((0, 0), (10, 0), (5, 10)),
    4: ((0, 0), (10, 0), (10, 10), (0, 10)),
    5: ((0, 0), (5, 0), (10, 0), (10, 10), (0, 10)),
    6: ((3, 0), (7, 0), (10, 5), (7, 10), (3, 10), (0, 5)),
    8: ((3, 0), (7, 0), (10, 3), (10, 7), (7, 10), (3, 10), (0, 7), (0, 3)),
}
BLOCK_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def assemble_histories(lineitem: DataFrame, part: DataFrame, o: Options = DEFAULTS) -> DataFrame:
    """One ordered step array per (l_orderkey, l_returnflag), at most ``max_blocks`` steps; one shuffle on that key."""
    kind = F.coalesce(*[F.when(F.split("p_type", " ")[0] == k, v) for k, v in OUTLINES.items()], F.lit(4))
    step = F.struct(
        *BLOCK_ORDER,
        kind.alias("edges"),
        ((F.floor((F.col("l_quantity") - 1) / 10) + 1) * 10).cast("int").alias("w"),
        F.element_at(F.array(*map(F.lit, DEPTHS)), (F.round(F.col("l_discount") * 100) + 1).cast("int")).alias("k"),
        F.element_at(F.array(*map(F.lit, OFFSETS)), (F.col("l_suppkey") % 4 + 1).cast("int")).alias("x"),
        (F.round(F.col("l_tax") * 100) != 8).alias("closed"),
    )
    rows = lineitem.join(part.select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    grouped = rows.groupBy("l_orderkey", "l_returnflag").agg(F.slice(F.array_sort(F.collect_list(step)), 1, o.max_blocks).alias("steps"))
    history = F.transform("steps", lambda s, i: F.struct(F.when(s["edges"] == 0, "disc").otherwise("loop").alias("outline"), s["edges"].alias("edges"), s["w"].alias("w"), (s["w"] / 10 * s["k"]).cast("int").alias("d"), F.when(i == 0, 0).otherwise(s["x"]).alias("x"), s["closed"].alias("closed")))
    return grouped.select("l_orderkey", "l_returnflag", history.alias("history"))


def _loop_text(s: Column, points) -> Column:
    parts = []
    for i, (x, y) in enumerate(points):
        parts += [F.lit(("\n" if i else "") + ("seg " if i else "pen ")), (s * x).cast("string"), F.lit(" "), (s * y).cast("string")]
    return F.concat(*parts)


def block_text(b: Column) -> Column:
    s = (b["w"] / 10).cast("int")
    body = F.when(b["edges"] == 0, F.concat(F.lit("disc "), (s * 5).cast("string")))
    for n, points in LOOPS.items():
        body = body.when(b["edges"] == n, F.concat(_loop_text(s, points), F.when(b["closed"], "\nshut").otherwise("")))
    return F.concat(F.lit("sheet "), b["x"].cast("string"), F.lit("\n"), body, F.lit("\nraise "), b["d"].cast("string"))


def transpile(histories: DataFrame) -> DataFrame:
    """Program text from a history, map-only and deterministic."""
    return histories.withColumn("program", F.array_join(F.transform("history", block_text), "\n"))


def flatten_arc(cx: Column, cy: Column, r: Column, segments: int) -> Column:
    """A full arc as vertices of straight segments (rounded to integers), in order."""
    import math

    return F.array(*[F.struct(F.round(cx + r * math.cos(2 * math.pi * i / segments)).cast("long").alias("x"), F.round(cy + r * math.sin(2 * math.pi * i / segments)).cast("long").alias("y")) for i in range(segments)])


def outer_profile(loops: Column) -> Column:
    """Of an array of loops, the one with the largest enclosed area."""
    from ..functions.geometry import twice_area

    return F.array_sort(F.transform(loops, lambda p: F.struct((-F.abs(twice_area(p))).alias("a"), p.alias("p"))))[0]["p"]


def hex_fraction(key: Column) -> Column:
    """The first 8 hex digits of an md5 as a number."""
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 8), 16, 10).cast("long")


def programs(spark: SparkSession, sf_dir: str, o: Options = DEFAULTS) -> DataFrame:
    """program_id, l_orderkey, program, program_sha, n_blocks, split, intent5, intent4, profile."""
    from ..functions.intent_text import with_intent

    df = transpile(assemble_histories(table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part"), o))
    df = df.select(
        F.concat_ws("-", F.col("l_orderkey").cast("string"), "l_returnflag").alias("program_id"), "l_orderkey", "program", F.sha2("program", 256).alias("program_sha"), F.size("history").alias("n_blocks"),
        F.when(hex_fraction(F.col("l_orderkey").cast("string")) % 10 < 8, "train").otherwise("held").alias("split"),
    )
    return with_intent(df)
