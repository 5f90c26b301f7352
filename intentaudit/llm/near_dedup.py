"""MinHash near-duplicates with sequential Bayesian verification.

Documents with equal shingle sets collapse first. The rest are banded; in a
bucket everyone meets the bucket's leader, not everyone else. A candidate
pair's signatures are compared batch by batch and the pair is pruned as soon as the
posterior chance of reaching the threshold falls below the chosen miss
probability; survivors are confirmed on full shingle sets. Buckets that
still hold several components are then settled: small ones by all pairs across
components, large ones by an exact prefix filter on their members' shingles.
"""

from __future__ import annotations

import functools
import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordIds, blobs, map_batches, materialize, session, settled, sized, text_of

WIDTH, NUM, DEN = 5, 3, 4  # words in a shingle; the threshold NUM/DEN
BANDS, ROWS = 32, 4
BATCH, MISS = 16, 1e-4
HUB = BANDS * ROWS * NUM // DEN  # matches that make a pair likely to reach the threshold
SMALL = 8  # members up to which a bucket's pairs are listed
BLOCK = 1024  # documents of a block in the comparison of families
_A = np.random.Generator(np.random.PCG64(20240229)).integers(1, 2**63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
_B = np.random.Generator(np.random.PCG64(20240301)).integers(0, 2**63, BANDS * ROWS, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_hashes(text: bytes, ids: WordIds, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles (A-Z lowered)."""
    h = ids.array(text.lower().split())
    if not len(h):
        return h
    n = max(1, len(h) - width + 1)
    s = np.full(n, min(width, len(h)), np.uint64)
    for i in range(min(width, len(h))):
        s = _mix(s * np.uint64(0x9E3779B97F4A7C15) + h[i : i + n])
    return np.unique(s)


def exact_shingles(text: bytes, width: int = WIDTH) -> set:
    """The shingle set itself, as word tuples."""
    w = text.lower().split()
    return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def signature(s: np.ndarray) -> np.ndarray:
    out = np.full(len(_A), np.iinfo(np.uint32).max, np.uint32)
    for at in range(0, len(s), 2048):
        part = s[at : at + 2048]
        np.minimum(out, ((part[None, :] * _A[:, None] + _B[:, None]) >> np.uint64(32)).min(axis=1).astype(np.uint32), out=out)
    return out


@functools.cache
def least_matches(total: int = BANDS * ROWS, batch: int = BATCH, threshold: float = NUM / DEN, miss: float = MISS) -> tuple[tuple[int, int], ...]:
    """(compared, fewest matches) after each batch.

    With a uniform prior the similarity given m of n matches is
    Beta(m+1, n-m+1), so P(similarity >= t) is the chance that n+1 trials at t
    give at most m successes; below ``miss`` the pair is pruned.
    """
    out = []
    for n in range(batch, total + 1, batch):
        tail, m = 0.0, -1
        while tail < miss and m < n:
            m += 1
            tail += math.comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        out.append((n, m))
    return tuple(out)


def bayes_survivors(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(alive, matches) for rows of two signature matrices, batch by batch."""
    alive, matches = np.arange(len(a)), np.zeros(len(a), np.int32)
    done = 0
    for n, least in least_matches():
        matches[alive] += (a[alive, done:n] == b[alive, done:n]).sum(axis=1)
        alive = alive[matches[alive] >= least]
        done = n
    return alive, matches


def similar(x: set, y: set, num: int = NUM, den: int = DEN) -> bool:
    both = len(x & y)
    return den * both >= num * (len(x) + len(y) - both)


def connected(edges: DataFrame) -> DataFrame:
    """(node, component): smallest node reachable, for nodes with an edge.

    Alternates large-star and small-star steps, each an aggregate and a join,
    until nothing moves; only counts reach the driver.
    """
    edges = materialize(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct())
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        tops = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(tops, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").union(tops.select("u", F.col("m").alias("v"))).distinct()
        nxt = materialize(small)
        stats = nxt.groupBy("u").count().agg(F.max("count").alias("fan")).collect()[0]["fan"]
        moved = nxt.join(edges, ["u", "v"], "left_anti").isEmpty()
        chained = not nxt.select(F.col("v").alias("u")).join(nxt.select("u").distinct(), "u", "left_semi").isEmpty()
        edges = nxt
        if stats is None or (moved and stats == 1 and not chained):
            break
    part = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return part.union(part.select(F.col("component").alias("node"), "component").distinct())


def _confirm(pairs: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    """Pairs (a, b) whose full shingle sets reach the threshold."""

    def keep(batches):
        for batch in batches:
            out, last, words = [], None, None
            for a, b, x, y in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), blobs(batch.column("ta")), blobs(batch.column("tb"))):
                if a != last:
                    last, words = a, exact_shingles(x, width)
                if similar(words, exact_shingles(y, width)):
                    out.append((a, b))
            yield pa.record_batch([pa.array([o[0] for o in out], pa.int64()), pa.array([o[1] for o in out], pa.int64())], ["a", "b"])

    left = texts.select(F.col("rep").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("rep").alias("b"), F.col("text").alias("tb"))
    return map_batches(pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "ta", "tb"), keep, "a long, b long")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, kept.

    Links are exact (100*intersection >= 75*union on full sets); a link between
    two texts of just 0.75 is missed by all 32 bands with probability 5e-6 and
    pruned with at most the chosen miss probability. Documents without words
    are linked with nothing. Null texts are empty, null identifiers stand
    alone, repeated rows share one class; different texts under one identifier are texts of their own, and
    their rows have the same doc_id in the result. An empty table gives an empty result; a very long text is shingled whole. Extra columns are ignored.
    """
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).cast("binary").alias("text")).withColumn("hash", F.xxhash64("text"))

    def sketch(batches):
        ids = WordIds()
        for b in batches:
            sets = [shingle_hashes(t, ids, width) for t in blobs(b.column("text"))]
            yield pa.record_batch([
                b.column("doc_id"), b.column("hash"), pa.array([len(s) for s in sets], pa.int64()),
                pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary()),
                pa.array([signature(s).astype("<u4").tobytes() if len(s) else b"" for s in sets], pa.binary()),
            ], ["doc_id", "hash", "n_shingles", "set_key", "sig"])

    docs_ = materialize(map_batches(base, sketch, "doc_id long, hash long, n_shingles long, set_key binary, sig binary"))
    full = docs_.filter("n_shingles > 0 and doc_id is not null")
    reps = full.groupBy("set_key").agg(F.min(F.struct("doc_id", "hash")).alias("row")).select("set_key", F.col("row.doc_id").alias("rep"), F.col("row.hash").alias("hash"))
    # different texts under one identifier: each class is named by its set, and gets its smallest identifier at the end
    again = materialize(reps.groupBy("rep").count().filter("count > 1").select(F.col("rep").alias("twice")))
    repeated = not again.isEmpty()
    first = F.col("rep")
    if repeated:
        named = F.xxhash64("set_key")
        reps = reps.join(sized(again), F.col("rep") == F.col("twice"), "left").withColumn("first", first).withColumn("rep", F.when(F.col("twice").isNotNull(), named).otherwise(F.col("rep"))).drop("twice")
    else:
        reps = reps.withColumn("first", first)
    reps = materialize(reps)
    one = materialize(full.select("doc_id", "hash", "set_key", "n_shingles", "sig").join(reps.withColumnRenamed("hash", "own"), "set_key").filter("doc_id = first and hash = own").select("rep", "doc_id", "hash", "n_shingles", "sig").dropDuplicates(["rep"]))

    def bands(batches):
        for b in batches:
            m = np.frombuffer(b"".join(blobs(b.column("sig"))), "<u4").reshape(-1, BANDS, ROWS).astype(np.uint64)
            key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64), m.shape[:2]).copy()
            for r in range(ROWS):
                key = _mix(key * np.uint64(0x9E3779B97F4A7C15) + m[:, :, r])
            rep = np.repeat(b.column("rep").to_numpy(zero_copy_only=False), BANDS)
            yield pa.record_batch([pa.array(key.ravel().view(np.int64)), pa.array(rep)], ["bucket", "rep"])

    rows = materialize(map_batches(one.select("rep", "sig"), bands, "bucket long, rep long"))
    lead = rows.groupBy("bucket").agg(F.count("*").alias("members"), F.min_by("rep", F.xxhash64("rep", "bucket")).alias("leader")).filter("members > 1")
    shared = materialize(rows.join(lead, "bucket"))

    def prune(batches):
        for b in batches:
            a, c = (np.frombuffer(b"".join(blobs(b.column(k))), "<u4").reshape(-1, BANDS * ROWS) for k in ("sa", "sb"))
            alive, matches = bayes_survivors(a, c)
            take = pa.array(alive)
            yield pa.record_batch([b.column("a").take(take), b.column("b").take(take), pa.array(matches[alive])], ["a", "b", "matches"])

    sa = one.select(F.col("rep").alias("a"), F.col("sig").alias("sa"), F.col("n_shingles").alias("na"))
    sb = one.select(F.col("rep").alias("b"), F.col("sig").alias("sb"), F.col("n_shingles").alias("nb"))

    def survivors(pairs):
        sized = pairs.join(sa, "a").join(sb, "b").filter("4 * least(na, nb) >= 3 * greatest(na, nb)")
        return materialize(map_batches(sized.select("a", "b", "sa", "sb"), prune, "a long, b long, matches int"))

    def led(members):
        """Pairs (a, b) of every member with its bucket's leader."""
        return members.filter("rep <> leader").select(F.least("leader", "rep").alias("a"), F.greatest("leader", "rep").alias("b")).distinct()

    # only documents that share a bucket are ever compared by text
    met = sized(shared.select("rep").distinct())
    wanted = sized(one.join(met, "rep", "left_semi").select("rep", "doc_id", "hash"))
    texts = materialize(base.join(wanted, ["doc_id", "hash"]).select("rep", "text").dropDuplicates(["rep"]))

    def components(df, comps):
        return df.join(comps.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))

    def across(pairs, comps):
        """Pairs whose ends are still in different components."""
        ca = comps.select(F.col("node").alias("a"), F.col("component").alias("ca"))
        cb = comps.select(F.col("node").alias("b"), F.col("component").alias("cb"))
        return pairs.join(ca, "a", "left").join(cb, "b", "left").filter(F.coalesce("ca", "a") != F.coalesce("cb", "b"))

    # leaders by chance first; the members that most leaders are like, the hubs, lead next
    alive = survivors(led(shared))
    likely = F.sum(F.when(F.col("matches") >= HUB, 1).otherwise(0))
    degree = materialize(alive.select("b", "matches").union(alive.select("a", "matches")).groupBy(F.col("b").alias("rep")).agg(likely.alias("degree")))
    hubs = shared.select("bucket", "rep").join(degree, "rep").groupBy("bucket").agg(F.max_by("rep", F.struct("degree", -F.col("rep"))).alias("leader"))
    again = led(shared.drop("leader").join(hubs, "bucket")).join(alive.select("a", "b"), ["a", "b"], "left_anti")
    alive = materialize(alive.union(survivors(again)))

    # one candidate a document: its likeliest hub; then those that still join components
    ranked = alive.join(degree.toDF("a", "da"), "a", "left").join(degree.toDF("b", "db"), "b", "left").fillna(0, ["da", "db"])
    ends = ranked.select(F.col("b").alias("x"), F.col("a").alias("y"), F.col("da").alias("d"), "matches").union(ranked.select(F.col("a").alias("x"), F.col("b").alias("y"), F.col("db").alias("d"), "matches"))
    best = ends.groupBy("x").agg(F.max_by("y", F.struct((F.col("matches") >= HUB).alias("l"), "d", "matches", -F.col("y"))).alias("y")).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
    best = materialize(best)
    links = materialize(_confirm(best, texts, width))
    comps = materialize(connected(links))
    rest = across(alive.join(best, ["a", "b"], "left_anti"), comps).select("a", "b")
    links = materialize(links.union(_confirm(rest, texts, width)))
    comps = materialize(connected(links))

    # buckets that still hold several components
    placed = components(shared.select("bucket", "rep", "members"), comps)
    mixed = placed.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("bucket")
    open_ = materialize(placed.join(mixed, "bucket"))
    few = open_.filter(F.col("members") <= SMALL)
    cross = few.alias("x").join(few.alias("y"), "bucket").filter("x.rep < y.rep and x.component <> y.component").select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"))
    cross = cross.distinct().join(alive.select("a", "b"), ["a", "b"], "left_anti")
    late = materialize(_confirm(survivors(cross), texts, width))
    many = open_.filter(F.col("members") > SMALL)
    if not many.isEmpty():
        late = late.union(_family_links(many, one, texts, width))
    comps = connected(links.union(late))

    classes = reps.join(comps.withColumnRenamed("node", "rep"), "rep", "left").select("set_key", "first", F.coalesce("component", "rep").alias("component_id"))
    if repeated:
        classes = materialize(classes)
        least = classes.groupBy("component_id").agg(F.min("first").alias("least"))
        classes = classes.join(least, "component_id").select("set_key", F.col("least").alias("component_id"))
    else:
        classes = classes.drop("first")
    linked = full.select("doc_id", "n_shingles", "set_key").join(classes, "set_key").select("doc_id", "n_shingles", "component_id")
    alone = docs_.filter("n_shingles = 0 or doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _family_links(many: DataFrame, one: DataFrame, texts: DataFrame, width: int) -> DataFrame:
    """Links (a, b) across components among the members of large open buckets.

    Members that meet in such buckets form families. A family is dealt by hash
    into blocks of about BLOCK documents and every two blocks meet in one task, which
    prunes by signature batches and confirms on full sets; only links leave the
    task, never the pairs.
    """
    edges = many.groupBy("bucket").agg(F.min("rep").alias("a")).join(many.select("bucket", F.col("rep").alias("b")), "bucket").select("a", "b").distinct()
    family = materialize(connected(edges).withColumnRenamed("component", "family"))
    blocks = settled(family.groupBy("family").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks")))
    members = many.select("rep", "component").distinct().join(family.withColumnRenamed("node", "rep"), "rep").join(blocks, "family")
    members = members.withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    full = members.join(one.select("rep", "sig"), "rep").join(texts, "rep")
    dealt = full.select("family", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "rep", "component", "sig", "text")

    def compare(t: pa.Table) -> pa.Table:
        i, j = t.column("i")[0].as_py(), t.column("j")[0].as_py()
        ids = WordIds()
        rep, comp, own, text = t.column("rep").to_numpy(), t.column("component").to_numpy(), t.column("own").to_numpy(), blobs(t.column("text").combine_chunks())
        sig = np.frombuffer(b"".join(blobs(t.column("sig").combine_chunks())), "<u4").reshape(-1, BANDS * ROWS)
        sets = [shingle_hashes(x, ids, width) for x in text]
        n = np.array([len(x) for x in sets])
        root = {c: c for c in set(comp.tolist())}

        def find(c):
            while root[c] != c:
                root[c] = root[root[c]]
                c = root[c]
            return c

        links = []
        left = np.flatnonzero(own == i)
        right = np.flatnonzero(own == j)
        for x in left:
            y = right[rep[right] > rep[x]] if i == j else right
            y = y[(comp[y] != comp[x]) & (DEN * np.minimum(n[y], n[x]) >= NUM * np.maximum(n[y], n[x]))]
            done, matches = 0, np.zeros(len(y), np.int32)
            for upto, least in least_matches():
                if not len(y):
                    break
                matches = matches + (sig[y, done:upto] == sig[x, done:upto]).sum(axis=1, dtype=np.int32)
                y, matches, done = y[matches >= least], matches[matches >= least], upto
            for k in y[np.argsort(-matches, kind="stable")]:
                if find(comp[x]) == find(comp[k]):
                    continue
                both = len(np.intersect1d(sets[x], sets[k], assume_unique=True))
                if DEN * both >= NUM * (n[x] + n[k] - both) and similar(exact_shingles(text[x], width), exact_shingles(text[k], width)):
                    links.append((min(rep[x], rep[k]), max(rep[x], rep[k])))
                    root[find(comp[x])] = find(comp[k])
        return pa.table([pa.array([p[0] for p in links], pa.int64()), pa.array([p[1] for p in links], pa.int64())], ["a", "b"])

    session(dealt)
    return dealt.groupBy("family", "i", "j").applyInArrow(compare, "a long, b long")


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text,''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, unnest(CASE WHEN len(ws) = 0 THEN []::VARCHAR[] ELSE list_distinct(list_transform(range(1, greatest(len(ws) - 4, 1) + 1), lambda i: array_to_string(ws[i:i+4], ' '))) END) AS sh FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
i AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM i JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * k >= 75 * (na.n + nb.n - k)),
r AS (SELECT a AS doc_id, a AS c FROM (SELECT DISTINCT a FROM e) UNION SELECT e.b, r.c FROM r JOIN e ON e.a = r.doc_id WHERE r.c < e.b),
m AS (SELECT doc_id, min(c) AS c FROM r GROUP BY doc_id)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(w.doc_id, coalesce(m.c, w.doc_id)) AS component_id, w.doc_id = least(w.doc_id, coalesce(m.c, w.doc_id)) AS kept
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN m USING (doc_id)
"""
