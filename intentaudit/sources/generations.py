"""Recorded generations: a Python data source, and JSON, Parquet and CSV readers and writers with fixed schemas."""

from __future__ import annotations

import io
import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition
from pyspark.sql.types import StringType, StructField, StructType

from ..schema import GENERATION

FIELDS = [f.name for f in GENERATION.fields]


PART_BYTES = 64 << 20


class _Range(InputPartition):
    """Bytes start to end of a file; a line belongs to the range in which it starts."""

    def __init__(self, path: str, start: int, end: int):
        self.path, self.start, self.end = path, start, end


def _store(path: str):
    """(file system, path in it): local, or any store that Arrow opens by URI (hdfs, s3, gs)."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


class GenerationReader(DataSourceReader):
    """Ranges of JSON-lines files; equality filters on arm, model, form and seed are applied while reading.

    Lines that do not parse are dropped, or, with the option ``corrupt`` set to true, kept as rows with the line in ``_corrupt``.
    """

    def __init__(self, options):
        self.path, self.equal, self.corrupt = options["path"], {}, str(options.get("corrupt", "false")).lower() == "true"

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and len(f.attribute) == 1 and f.attribute[0] in ("arm", "model", "form", "seed"):
                self.equal[f.attribute[0]] = f.value
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        store, path = _store(self.path)
        root = store.get_file_info(path)
        files = store.get_file_info(fs.FileSelector(path, recursive=True)) if root.type == fs.FileType.Directory else [root]
        found = sorted((f.path, f.size) for f in files if f.type == fs.FileType.File and (".json" in f.base_name or f.path == path))
        return [_Range(p, at, min(at + PART_BYTES, size)) for p, size in found for at in range(0, size, PART_BYTES)] or [_Range("", 0, 0)]

    def read(self, partition):
        if not partition.path:
            return
        store, _ = _store(self.path)
        with store.open_input_file(partition.path) as f:
            f.seek(max(0, partition.start - 1))
            lines = io.BufferedReader(f, 1 << 20)
            at = partition.start
            if partition.start:
                at += len(lines.readline()) - 1  # the rest of a line that started in the range before
            while at < partition.end:
                line = lines.readline()
                if not line:
                    return
                at += len(line)
                try:
                    row = json.loads(line)
                    row = row if isinstance(row, dict) else None
                except ValueError:
                    row = None
                if row is None:
                    if self.corrupt and line.strip() and not self.equal:
                        yield (*[None] * len(FIELDS), line.decode("utf-8", "replace").rstrip("\n"))
                elif all(row.get(k) == v for k, v in self.equal.items()):
                    yield tuple(row.get(k) for k in FIELDS) + ((None,) if self.corrupt else ())


class GenerationSource(DataSource):
    """``spark.read.format("intent_generations").load(folder)``; the folder is one that every executor reaches."""

    @classmethod
    def name(cls):
        return "intent_generations"

    def schema(self):
        if str(self.options.get("corrupt", "false")).lower() == "true":
            return StructType([*GENERATION.fields, StructField("_corrupt", StringType())])
        return GENERATION

    def reader(self, schema):
        return GenerationReader(self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(GenerationSource)


def read_generations(spark: SparkSession, path: str) -> DataFrame:
    """Generations as Parquet, any store that Spark reads."""
    return spark.read.schema(GENERATION).parquet(path)


def read_json(spark: SparkSession, path: str) -> DataFrame:
    """Generations as JSON lines by Spark's own reader; lines that do not parse are kept in ``_corrupt``."""
    return spark.read.schema(StructType([*GENERATION.fields, StructField("_corrupt", StringType())])).option("columnNameOfCorruptRecord", "_corrupt").json(path)


def read_quotas(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("profile string, pool long, quota long").option("header", True).csv(path)


def read_programs(spark: SparkSession, path: str) -> DataFrame:
    """One program per text file."""
    from pyspark.sql import functions as F

    return spark.read.option("wholetext", True).text(path).select(F.sha2("value", 256).alias("program_id"), F.rtrim("value").alias("program"))


def write_scores(scores: DataFrame, path: str) -> None:
    """Score rows partitioned so that a contrast reads only its arms."""
    scores.write.partitionBy("model", "form", "arm", "seed").parquet(path)


def save_scores(scores: DataFrame, name: str, buckets: int = 64) -> None:
    """Score rows as a table in the warehouse, partitioned by cell and bucketed by program and seed, so that pairing arms needs no shuffle."""
    scores.write.partitionBy("model", "form", "arm").bucketBy(buckets, "program_id", "seed").sortBy("program_id", "seed").mode("overwrite").saveAsTable(name)


def write_csv(table: DataFrame, path: str) -> None:
    """A result table as one CSV with a header."""
    table.coalesce(1).write.option("header", True).csv(path)


def to_markdown(table: DataFrame, rows: int = 1000) -> str:
    """A small result table as Markdown, ordered by its columns; raises past ``rows`` rows."""
    got = table.orderBy(*table.columns).limit(rows + 1).collect()
    if len(got) > rows:
        raise ValueError("too many rows for a report")
    cell = lambda v: "" if v is None else f"{v:.6g}" if isinstance(v, float) else str(v).replace("|", "\\|")
    lines = [table.columns, ["-"] * len(table.columns), *([cell(v) for v in r] for r in got)]
    return "\n".join("| " + " | ".join(x) + " |" for x in lines) + "\n"


def write_log(scores: DataFrame, path: str) -> None:
    scores.write.json(path)
