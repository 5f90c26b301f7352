"""Corpus hygiene: content-keyed dedup, leak removal, audits of the key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.scratch import sized


def loose(text: Column) -> Column:
    """Text with case, blanks and placement of sheets removed."""
    return F.regexp_replace(F.regexp_replace(F.lower(text), "sheet [0-9]+", "sheet"), r"[ \t]+", " ")


def dedup_exact(df: DataFrame, content: str, id_col: str) -> DataFrame:
    """The row with the smallest identifier of each content. Only hashes and identifiers are shuffled; the rows come back by a semi-join."""
    stay = df.groupBy(F.sha2(F.col(content), 256).alias("__sha")).agg(F.min(id_col).alias(id_col)).select(id_col)
    return df.join(stay, id_col, "left_semi")


def dedup_loose(df: DataFrame, content: str, id_col: str, normalizer=loose) -> DataFrame:
    stay = df.groupBy(F.sha2(normalizer(F.col(content)), 256).alias("__sha")).agg(F.min(id_col).alias(id_col)).select(id_col)
    return df.join(stay, id_col, "left_semi")


def drop_leaked(held: DataFrame, train: DataFrame, content: str = "program", normalizer=loose) -> DataFrame:
    """Held-out rows whose exact or loose hash does not occur in train."""
    exact = train.select(F.sha2(F.col(content), 256).alias("__sha")).distinct()
    near = train.select(F.sha2(normalizer(F.col(content)), 256).alias("__loose")).distinct()
    keyed = held.withColumn("__sha", F.sha2(F.col(content), 256)).withColumn("__loose", F.sha2(normalizer(F.col(content)), 256))
    return keyed.join(exact, "__sha", "left_anti").join(near, "__loose", "left_anti").drop("__sha", "__loose")


def contaminated(docs: DataFrame, bench: DataFrame, n: int = 8) -> DataFrame:
    """(doc_id, item_id) of documents that hold a benchmark text verbatim.

    Every occurrence of a text holds its inner words between their blanks; the first inner n-gram of a long text, or the first inner
    word of a shorter one, is its key, and documents meet items by equal hashes. A text
    without an inner word is looked for at each of its document's words by that word's ends. The text itself decides. Items are broadcast if they are counted and found few.
    """
    w = F.split("text", r"[ \n]+")
    size = F.size(w)
    width = F.when(size >= n + 2, n).when(size >= 3, 1).otherwise(0)
    items = bench.filter("text <> ''").select("item_id", F.col("text").alias("passage"), width.alias("k"), F.when(size >= n + 2, F.xxhash64(F.slice(w, 2, n))).when(size >= 3, F.xxhash64(F.slice(w, 2, 1))).otherwise(F.lit(0).cast("long")).alias("g"))
    words = docs.select("doc_id", F.explode(F.array(w)).alias("w"))
    grams = lambda k: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - (k - 1), F.lit(1))), lambda i: F.xxhash64(F.slice("w", i, k))))
    found = None
    for k in (n, 1, 0):
        some = items.filter(F.col("k") == k)
        if some.isEmpty():
            continue
        keys = words.select("doc_id", F.explode(grams(k)).alias("g")) if k else docs.select("doc_id", F.lit(0).cast("long").alias("g"))
        pairs = keys.join(sized(some.select("g", "item_id")), "g").select("doc_id", "item_id").distinct()
        found = pairs if found is None else found.union(pairs)
    if found is None:
        return docs.select("doc_id", F.lit(0).alias("item_id")).limit(0)
    return found.join(docs.select("doc_id", "text"), "doc_id").join(sized(items.select("item_id", "passage")), "item_id").filter(F.col("text").contains(F.col("passage"))).select("doc_id", "item_id")


def dedup_key_report(df: DataFrame, keys: dict[str, Column]) -> DataFrame:
    """Per key: clusters of two or more, redundant rows, the largest; one scan."""
    stacked = df.select(F.explode(F.array(*[F.struct(F.lit(k).alias("key"), F.xxhash64(c).alias("h"), F.md5(c.cast("string").cast("binary")).alias("m")) for k, c in keys.items()])).alias("s")).select("s.*")
    sizes = stacked.groupBy("key", "h", "m").agg(F.count("*").alias("n"))
    return sizes.groupBy("key").agg(F.count_if(F.col("n") > 1).alias("clusters"), F.sum(F.col("n") - 1).alias("redundant"), F.max("n").alias("largest"))


def pools_agree(a: DataFrame, b: DataFrame, sha: str = "program_sha") -> DataFrame:
    """One row: hashes in both, only in a, only in b."""
    both = a.select(sha).distinct().withColumn("ina", F.lit(1)).join(b.select(sha).distinct().withColumn("inb", F.lit(1)), sha, "full_outer")
    return both.agg(F.count_if(F.col("ina").isNotNull() & F.col("inb").isNotNull()).alias("both"), F.count_if(F.col("inb").isNull()).alias("only_a"), F.count_if(F.col("ina").isNull()).alias("only_b"))


def length_profile(df: DataFrame, content: str, by: str, cap: int = 1024) -> DataFrame:
    """Token lengths (blank-separated): mean, max, 95th percentile, share within the cap."""
    n = F.size(F.split(F.col(content), r"[ \n]"))
    return df.groupBy(by).agg(F.count("*").alias("n"), F.avg(n).alias("mean_len"), F.max(n).alias("max_len"), F.percentile(n, 0.95).alias("p95_len"), F.avg((n <= cap).cast("int")).alias("within_cap"))


def held_out_pool(programs: DataFrame) -> DataFrame:
    """Held-out programs free of leaks, one per content, with a four-feature intent."""
    clean = drop_leaked(programs.filter("split = 'held'"), programs.filter("split = 'train'"))
    return dedup_exact(clean, "program", "program_id").filter("intent4 > 0")


def pool_steps(programs: DataFrame) -> DataFrame:
    """One row: how many held-out programs each step leaves (all, without exact leaks, without loose leaks, distinct, with a four-feature intent)."""
    train = programs.filter("split = 'train'")
    exact = train.select(F.sha2("program", 256).alias("__sha")).distinct()
    held = programs.filter("split = 'held'")
    far = held.join(exact, F.sha2("program", 256) == F.col("__sha"), "left_anti")
    clean = drop_leaked(held, train)
    pool = dedup_exact(clean, "program", "program_id")
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(held, "held").crossJoin(n(far, "no_exact_leak")).crossJoin(n(clean, "no_loose_leak")).crossJoin(n(pool, "distinct_programs")).crossJoin(n(pool.filter("intent4 > 0"), "pool"))
