"""From raw documents to packed sequences: quality filter, line dedup, near dedup, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a frame that is written as
Parquet and read again for the next; all but the last return the columns of documents.

Every stage decides by row: rows with different texts under one identifier (or without one) are documents of
their own, whole copies of a row share their fate until near dedup keeps one. A null text is empty; an empty table gives an
empty result; texts of any length are read whole; columns of any other name pass through untouched.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from intentaudit.llm import line_dedup, mixing, near_dedup, packing, quality
from intentaudit.llm.common import free, keyed, materialize, sized, table, text_of, without
from intentaudit.llm.queries import tokenizer_path


def filter_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that importance resampling rejects go; an empty one weighs nothing and stays. Without labelled documents all stay."""
    rows, key = keyed(docs)
    good = table(spark, sf_dir, "labels").filter("quality = 1").select(F.col("doc_id").cast("long").alias("label_id"), "quality")
    ids = rows.select(F.col(key), F.col("doc_id").cast("long").alias("label_id"))
    labels = ids.join(good, "label_id").select(F.col(key).alias("doc_id"), "quality")
    decided = materialize(quality.resample(rows, labels, id_col=key))
    return without(rows, decided.filter("not kept").select("doc_id"), key).select(docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated lines go, text and length are updated; a document that loses all its words with them goes too. Of like lines the one in the document with the smallest key stays."""
    rows, key = keyed(docs)
    had = free(rows, "__had")
    word = r"[^\x20\x09-\x0D]"
    out = line_dedup.drop_repeated_lines(rows.withColumn(had, text_of("text").rlike(word)), id_col=key, counts=False)
    out = out.filter(~F.col(had) | text_of("text").rlike(word))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates stays, the one with the smallest key; of a repeated row one."""
    rows, key = keyed(docs)
    rows = materialize(rows)
    groups = materialize(near_dedup.near_groups(rows, id_col=key))
    left = without(rows, groups.filter("not kept").select("doc_id"), key)
    again = materialize(groups.filter("kept").groupBy("doc_id").count().filter("count > 1").select("doc_id"))
    if again.isEmpty():
        return left.select(docs.columns)
    name = free(rows, "__again")
    repeated = sized(again.toDF(name))
    one = left.join(repeated, F.col(key) == F.col(name), "left_semi").dropDuplicates([key])
    return left.join(repeated, F.col(key) == F.col(name), "left_anti").union(one).select(docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many whole copies of each document as the mix takes; a null source is a source of its own."""
    rows, key = keyed(docs)
    rows = materialize(rows)
    owner, copies, copy = (free(rows, n) for n in ("__owner", "__copies", "__copy"))
    taken = materialize(mixing.mix(rows, id_col=key)).filter("copies > 0").groupBy(F.col("doc_id").alias(owner)).agg(F.max("copies").alias(copies))
    out = rows.join(sized(taken), F.col(key) == F.col(owner))
    return out.withColumn(copy, F.explode(F.sequence(F.lit(1), copies))).select(docs.columns)


def pack_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces and their places in the sequences, a row per piece of every copy; an empty text is its end token alone."""
    return packing.pack(docs, tokenizer_path())


STAGES = [
    ("quality_filter", filter_quality),
    ("line_dedup", drop_lines),
    ("near_dedup", drop_near_duplicates),
    ("mix_sources", mix_sources),
    ("pack", pack_documents),
]

#: The quality filter's models have no SQL form; the tests hold every stage against a brute-force version on a small fixture.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table documents."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir))
    return docs
