"""Line dedup by an exact set-similarity join, in DataFrame functions only.

A line is the set of its word shingles. Lines with equal sets collapse
first. A line like another one has at least three quarters of its tokens in
common with it, so tokens are counted, not paired, to find the lines that can
have a partner: first those of each line's prefix (n - ceil(t*n) + 1 tokens by
hash), then half of the tokens of the lines left, then all tokens of the lines
left after that. Every count is over all lines that are left, and a line goes
only if no other line can be like it. A passage that many lines share keeps
none of them, unless they also have their other tokens from other lines.

The lines left get their tokens in the order of these counts, rarest first;
any order gives the same result, if it is the same for all lines. By the prefix
filter, two lines meet only through a token of both prefixes; length and
positional filters thin the pairs, and the rest is verified on all tokens that
more than one line has. A line goes if an earlier line, by (document, line
number), is as similar as the threshold; copies of a line go after its first
place.

Every line first meets the earliest line of each of its prefix tokens, so that a
large family of look-alikes costs one pair a line and token; only lines which
find no match there meet all earlier lines.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import free, materialize, release_shuffles, sized, text_of

WIDTH, NUM, DEN, MIN_WORDS = 5, 3, 4, 5
PAIRS, PER_ROW, ROUNDS = 4096, 32, 2  # pairs that make a token crowded; their number a row that makes another count of the lines left pay; how often they are counted again at most
BROADCAST_ROWS = 1_000_000  # 8 to 40 MB


def flat_text(text: Column) -> Column:
    """Lower case, ASCII white space other than line feeds as blanks."""
    low = flat = F.lower(text)
    for c in "\t\x0b\x0c\r":
        flat = F.replace(flat, F.lit(c), F.lit(" "))
    # looking costs far less than four copies of the text
    odd = text.contains("\t") | text.contains("\x0b") | text.contains("\x0c") | text.contains("\r")
    return F.when(odd, flat).otherwise(low)


def line_words(flat: Column) -> Column:
    """Words of a flat line (a column: it is read again and again)."""
    words = F.split(flat, " ")
    plain = ~(flat.contains("  ") | flat.startswith(" ") | flat.endswith(" "))
    return F.when(plain & (flat != ""), words).otherwise(F.filter(words, lambda w: w != ""))


def bound(expr: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of the expression's value, which is computed once and never copied into a row."""
    return F.get(F.transform(F.array(expr), use), F.lit(0))


def runs(words: Column, width: int) -> Column:
    """A hash of the ``width`` words from each place on, fewer at the end. Runs are put together from shorter ones: a lambda is interpreted, so its size is what counts."""

    def longer(left, right, by):
        return F.zip_with(left, F.slice(right, F.lit(by + 1), F.size(right)), lambda x, y: F.xxhash64(x, y))

    def grow(left, size):
        if size == width:
            return left
        if width - size == 1 and size > 1:
            return longer(left, words, size)
        by = min(size, width - size)
        return bound(left, lambda v: grow(longer(v, v, by), size + by))

    return F.transform(words, lambda w: F.xxhash64(w)) if width == 1 else grow(words, 1)


def fixed(expr: Column) -> Column:
    """The expression as a generated column, which the optimizer cannot write into later expressions."""
    return F.explode(F.array(expr))


def lines_of(docs: DataFrame, width: int, min_words: int) -> DataFrame:
    """(did, line_no, tokens) of the lines with at least ``min_words`` words; did is never null. A column ``wanted`` names the only lines to read.

    Tokens are the distinct hashed word shingles in order; a line of fewer words is one shingle.
    """
    if "wanted" in docs.columns:
        lines = docs.select("did", "wanted", F.posexplode(F.split("text", "\n")).alias("line_no", "line")).filter(F.array_contains("wanted", F.col("line_no")))
        lines = lines.select("did", "line_no", fixed(flat_text(F.col("line"))).alias("flat"))
    else:
        lines = docs.select("did", F.posexplode(F.split(flat_text(F.col("text")), "\n")).alias("line_no", "flat"))
    hashed = lines.select("did", "line_no", fixed(bound(line_words(F.col("flat")), lambda words: runs(words, width))).alias("h"))
    whole = F.slice("h", F.lit(1), F.greatest(F.size("h") - (width - 1), F.lit(1)))
    return hashed.filter(F.size("h") >= min_words).select("did", "line_no", fixed(F.sort_array(F.array_distinct(whole))).alias("tokens"))


def _near(nx: str, ny: str, i: str, j: str) -> Column:
    """Length filter and, by the places of a common token, the positional filter."""
    x, y = F.col(nx), F.col(ny)
    most = F.least(F.col(i), F.col(j)) + 1 + F.least(x - F.col(i) - 1, y - F.col(j) - 1)
    return (DEN * F.least(x, y) >= NUM * F.greatest(x, y)) & ((NUM + DEN) * most >= NUM * (x + y))


def _least(n: str) -> Column:
    """Tokens that a line of n tokens shares at least with any line like it."""
    return F.ceil(F.col(n) * (NUM / DEN)).cast("int")


def _half(n: str) -> Column:
    """Tokens of a line that are written down with it: one more than half, never fewer than its prefix."""
    return F.floor(F.col(n) / 2).cast("int") + 1


def met_again(rows: DataFrame) -> DataFrame:
    """The rows (tok, ...) whose token another line has too, with the number of its lines."""
    return rows.withColumn("held", F.count("*").over(Window.partitionBy("tok"))).filter("held > 1")


def repeated_lines(docs: DataFrame, width: int = WIDTH, min_words: int = MIN_WORDS, pairs_limit: int = PAIRS, per_row: int = PER_ROW) -> DataFrame:
    """(did, line_no) of every line to remove; docs is (did, text)."""
    line = ["did", "line_no"]
    tokens = lines_of(docs, width, min_words).withColumn("n", F.size("tokens"))
    lines = materialize(tokens.select(*line, "n", F.xxhash64("tokens").alias("k1"), F.xxhash64(F.lit(7), "tokens").alias("k2"), F.slice("tokens", F.lit(1), _half("n")).alias("low")))

    # equal sets: all but the first place go, and only the first meets others
    groups = materialize(lines.groupBy("k1", "k2").agg(F.min("did").alias("first"), F.count("*").alias("size")).filter("size > 1").select("k1", "k2", "first"))
    equal = materialize(lines.select(*line, "k1", "k2").join(sized(groups), ["k1", "k2"]))
    inside = equal.filter("did = first").withColumn("place", F.rank().over(Window.partitionBy("k1", "k2", "did").orderBy("line_no"))).filter("place > 1")
    copies = materialize(equal.filter("did <> first").select(*line).union(inside.select(*line)))

    # lines that share a token of their prefixes, then so many of the written tokens as any two lines alike do
    single = lines.join(sized(copies), line, "left_anti")
    each = single.select(*line, F.explode(F.slice("low", F.lit(1), F.col("n") - _least("n") + 1)).alias("tok"))
    met = materialize(met_again(each).select(*line).distinct())
    release_shuffles(docs.sparkSession)
    low = lines.join(sized(met), line, "left_semi").select(*line, "n", F.explode("low").alias("tok"))
    met = met_again(low).groupBy(*line, "n").agg(F.count("*").alias("common")).filter(F.col("common") >= F.least(_half("n"), F.col("n")) - F.col("n") + _least("n"))
    met = materialize(met.select(*line))
    release_shuffles(docs.sparkSession)

    # these are read again, with all their tokens
    places = materialize(met.groupBy("did").agg(F.collect_set("line_no").alias("wanted")))
    count = places.agg(F.count("*"), F.coalesce(F.sum(F.size("wanted")), F.lit(0))).collect()[0]
    small = 3 * count[0] + count[1] <= 4 * BROADCAST_ROWS
    again = lines_of(docs.join(F.broadcast(places) if small else places, "did"), width, min_words).withColumn("n", F.size("tokens"))

    def left(rows):
        """Lines with enough tokens that others have too; these tokens, rarest first, and the numbers of their lines. Plain rows are shuffled, as lists of one token each are twice as large."""
        sets = met_again(rows).repartition(*line).groupBy(*line, "n").agg(F.sort_array(F.collect_list(F.struct("held", "tok"))).alias("by")).filter(F.size("by") >= _least("n"))
        return materialize(sets.select(*line, "n", F.col("by.tok").alias("tokens"), F.col("by.held").alias("held")))

    sets = left(again.select(*line, "n", F.explode("tokens").alias("tok")))
    for _ in range(ROUNDS):
        pairs = F.aggregate(F.filter("held", lambda h: h * h > pairs_limit), F.lit(0).cast("long"), lambda s, h: s + h)
        crowded = sets.agg(F.sum(pairs), F.sum(F.size("held"))).collect()[0]
        # a few pairs a row cost less than another round
        if (crowded[0] or 0) <= per_row * (crowded[1] or 0):
            break
        sets = left(sets.select(*line, "n", F.explode("tokens").alias("tok")))
    release_shuffles(docs.sparkSession)

    def verified(pairs):
        """Later lines of the pairs (xd, xl, did, line_no) that are similar enough: tokens that no other line has are in no intersection."""
        x = sets.select(F.col("did").alias("xd"), F.col("line_no").alias("xl"), F.col("n").alias("xn"), F.col("tokens").alias("xt"))
        both = F.size(F.array_intersect("xt", "tokens"))
        return materialize(pairs.join(sets.drop("held"), line).join(x, ["xd", "xl"]).filter(DEN * both >= NUM * (F.col("xn") + F.col("n") - both)).select(*line).distinct())

    # in the order of their counts, tokens that a line has alone come first
    alone = F.col("n") - F.size("tokens")
    prefix = F.slice("tokens", F.lit(1), F.col("n") - _least("n") + 1 - alone)
    placed = sets.select(*line, "n", alone.alias("alone"), F.posexplode(prefix).alias("at", "tok")).select("tok", *line, "n", (F.col("alone") + F.col("at")).alias("pos"))
    first = F.min(F.struct(*line, "n", "pos")).over(Window.partitionBy("tok"))
    shared = materialize(met_again(placed.withColumn("lead", first)))
    led = shared.select(*line, "n", "pos", F.col("lead.did").alias("xd"), F.col("lead.line_no").alias("xl"), F.col("lead.n").alias("xn"), F.col("lead.pos").alias("xp"))
    led = materialize(led.filter("xd <> did or xl <> line_no").filter(_near("n", "xn", "pos", "xp")).select("xd", "xl", *line).distinct())
    found = verified(led)
    release_shuffles(docs.sparkSession)

    x = shared.select("tok", F.col("did").alias("xd"), F.col("line_no").alias("xl"), F.col("n").alias("xn"), F.col("pos").alias("xp"))
    # lines alike share so many prefix tokens that one of them is left without each line's most held ones
    ranked = shared.drop("lead").join(sized(found), line, "left_anti").withColumn("rank", F.row_number().over(Window.partitionBy(*line).orderBy(F.desc("held"), "tok"))).drop("held")
    needed = F.ceil((F.col("n") + F.col("xn")) * NUM / (NUM + DEN)) - F.greatest(_least("n"), _least("xn")) + 1
    more = ranked.join(x, "tok").filter("xd < did or (xd = did and xl < line_no)").filter(_near("n", "xn", "pos", "xp")).filter(F.col("rank") >= needed)
    more = materialize(more.select("xd", "xl", *line).distinct())
    late = verified(more.join(sized(led), ["xd", "xl", *line], "left_anti"))
    return copies.union(found).union(late).distinct()


def drop_repeated_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, min_words: int = MIN_WORDS, counts: bool = True) -> DataFrame:
    """The documents with repeated lines removed, plus n_lines and n_removed (without ``counts``, the input's columns alone).

    All rows and columns stay; with ``counts``, input columns of these two names are replaced. Lines of fewer than ``min_words`` words are left
    alone. A null text stays null with 0 lines removed; rows that share an
    identifier count as one document; a null identifier comes last. A document
    whose lines all go keeps an empty text. An empty table gives an empty result; very long texts and lines are read whole.
    """
    docs = docs.drop("n_lines", "n_removed") if counts else docs
    owner, gone_ = free(docs, "__did"), free(docs, "__gone")
    did = F.coalesce(F.col(id_col).cast("long"), F.lit(2**63 - 1))
    gone = repeated_lines(docs.select(did.alias("did"), text_of(text_col).alias("text")), width, min_words)
    by_doc = materialize(gone.groupBy(F.col("did").alias(owner)).agg(F.collect_set("line_no").alias(gone_)))
    total = by_doc.agg(F.count("*"), F.coalesce(F.sum(F.size(gone_)), F.lit(0))).collect()[0]
    small = total[0] * 3 + total[1] <= BROADCAST_ROWS
    out = docs.join(F.broadcast(by_doc) if small else by_doc, did == F.col(owner), "left")
    lines = F.split(F.col(text_col), "\n")
    kept = F.array_join(F.filter(lines, lambda x, i: ~F.array_contains(gone_, i)), "\n")
    if counts:
        out = out.withColumn("n_lines", F.when(F.col(text_col).isNull(), 0).otherwise(F.size(lines)).cast("long"))
        out = out.withColumn("n_removed", F.when(F.col(text_col).isNull() | F.col(gone_).isNull(), 0).otherwise(F.size(gone_)).cast("long"))
    return out.withColumn(text_col, F.when(F.col(gone_).isNull(), F.col(text_col)).otherwise(kept)).drop(owner, gone_)


ORACLE = r"""
WITH l AS (SELECT doc_id, unnest(range(len(string_split(coalesce(text,''), chr(10))))) AS no, unnest(string_split(coalesce(text,''), chr(10))) AS line FROM documents),
w AS (SELECT doc_id, no, regexp_extract_all(lower(line), '[^\x20\x09-\x0D]+') AS ws FROM l),
s AS (SELECT doc_id, no, list_sort(list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')))) AS sh FROM w WHERE len(ws) >= 5),
u AS (SELECT sh, min((doc_id, no)) AS loc, row_number() OVER () AS k, len(sh) AS n FROM s GROUP BY sh),
x AS (SELECT k, loc, n, unnest(sh) AS t FROM u),
p AS (SELECT a.k AS ka, b.k AS kb, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS c FROM x a JOIN x b ON a.t = b.t AND a.loc < b.loc GROUP BY 1, 2),
m AS (SELECT DISTINCT kb AS k FROM p WHERE 4 * c >= 3 * (na + nb - c)),
g AS (SELECT s.doc_id, s.no FROM s JOIN u ON s.sh = u.sh LEFT JOIN m ON u.k = m.k WHERE m.k IS NOT NULL OR (s.doc_id, s.no) <> u.loc),
k AS (SELECT l.doc_id, count(*) AS n_lines, count(g.no) AS n_removed, string_agg(line, chr(10) ORDER BY l.no) FILTER (g.no IS NULL) AS t FROM l LEFT JOIN g ON l.doc_id = g.doc_id AND l.no = g.no GROUP BY l.doc_id)
SELECT doc_id, n_lines::BIGINT AS n_lines, n_removed::BIGINT AS n_removed, sha256(coalesce(t, '')) AS text_sha256 FROM k
"""
