"""A closed-form surrogate for conditioned generation, and a count model.

The surrogate continues a prompt with the rest of a training program: one with
the prompt's header and prefix if the model has seen such, else one with the
prefix under any header, else (and always under an empty header, which a
header-trained model has never seen) the shortest one with the same
opening. M learns each program's own header, R the header of another
program, U none. It keeps the relations of the design; its levels are not those
of a language model.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import headers
from ..schema import FORMS, SEEDS
from ..sources.tables import hex_fraction
from .pairing import derange, wrong_headers

STEM = 2  # statements that open a program


def manifest(o_arms=("correct", "wrong", "masked"), forms=FORMS, seeds=SEEDS, baseline: bool = True, prefixes=(0.4,)) -> list[tuple]:
    """(model, form, arm, prefix_frac, seed) of every inference job of model M and the baseline."""
    cells = [("M", f, a) for f in forms for a in o_arms] + ([("U", "none", "uncond")] if baseline else [])
    return [(m, f, a, p, s) for p in prefixes for m, f, a in cells for s in seeds]


def training_rows(programs: DataFrame, plans: dict[int, DataFrame] | None = None) -> DataFrame:
    """Training programs with a header, beside the deranged header of each seed (g0, g1, ...), a number made of the identifier, and the cells (model, form, seed, h, key) that see the program.

    Each seed and form leaves out a fifth of the programs; the control shares the model's draw of programs (same form), so that pairing alone differs. ``key`` orders the programs of a cell: the first 60 bits of its md5.
    """
    train = programs.filter("split = 'train' and intent5 > 0").select("program_id", "program", "intent5")
    out = train.withColumn("pid", F.xxhash64("program_id"))
    for s in SEEDS:
        plan = (plans or {}).get(s)
        plan = plan if plan is not None else derange(train, "program_id", "intent5", f"R{s}")
        out = out.join(plan.select("program_id", F.col("given").alias(f"g{s}")), "program_id")
    cells = []
    for s in SEEDS:
        for m, f in (("U", "none"), ("M", "text"), ("M", "token"), ("R", "text")):
            salt = F.concat_ws(":", F.lit(str(s)), F.lit(f), "program_id")
            h = F.col("intent5") if m == "M" else F.col(f"g{s}") if m == "R" else F.lit(-1)
            key = F.conv(F.substring(F.md5(salt.cast("binary")), 1, 15), 16, 10).cast("long")
            cells.append(F.when(hex_fraction(salt) % 10 < 8, F.struct(F.lit(m).alias("model"), F.lit(f).alias("form"), F.lit(s).alias("seed"), h.cast("int").alias("h"), key.alias("key"))))
    return out.withColumn("cells", F.array_compact(F.array(*cells)))


def stem(text):
    return F.substring_index(text, "\n", STEM)


def prompts(sample: DataFrame, plan_seed: str = "plan") -> DataFrame:
    """(program_id, model, form, arm, seed, h, prefix) for every evaluated cell; one wrong-header plan for all models."""
    plan = wrong_headers(sample, seed=plan_seed).select("program_id", F.col("given").alias("wrong"))
    cells = [("U", "none", "uncond", F.lit(-1))] + [("M", f, a, h) for f in FORMS for a, h in (("correct", F.col("intent5")), ("wrong", F.col("wrong")), ("masked", F.lit(0)))] + [("R", "text", "correct", F.col("intent5")), ("R", "text", "wrong", F.col("wrong"))]
    arr = F.array(*[F.struct(F.lit(m).alias("model"), F.lit(f).alias("form"), F.lit(a).alias("arm"), h.cast("int").alias("h"), F.lit(s).alias("seed")) for m, f, a, h in cells for s in SEEDS])
    rows = sample.join(plan, "program_id").select("program_id", "prefix", F.explode(arr).alias("c"))
    return rows.select("program_id", "prefix", "c.*")


def complete(prompt: DataFrame, train: DataFrame) -> DataFrame:
    """Add ``program`` (prefix and completion) and ``level`` (1 header and prefix, 2 prefix, 3 opening).

    The prompts' prefixes, of a bounded sample, are broadcast to one scan of the
    training rows, which meet them by their first characters at each of the prefixes' lengths. From there on programs are numbers;
    one pick per key is kept before anything is shuffled, and only the picked programs' texts are fetched, by a join whose rows are checked by their key.
    """
    cell = ["model", "form", "seed"]
    wanted = prompt.select("prefix").distinct()
    lengths = [r[0] for r in wanted.select(F.length("prefix")).distinct().collect()]
    cut = train.withColumn("n", F.explode(F.array(*[F.lit(n) for n in sorted(lengths)]))).filter("n <= length(program)")
    hits = cut.withColumn("prefix", F.substring("program", F.lit(1), F.col("n"))).join(F.broadcast(wanted), "prefix").select("pid", "prefix", F.explode("cells").alias("c")).select("pid", "prefix", "c.*")
    one = hits.groupBy(*cell, "h", "prefix").agg(F.min_by("pid", "key").alias("p1"), F.min("key").alias("k1"))
    two = one.groupBy(*cell, "prefix").agg(F.min_by("p1", "k1").alias("p2"), F.min("k1").alias("k2"))
    opens = prompt.select(stem(F.col("prefix")).alias("stem")).distinct()
    seen = train.withColumn("stem", stem(F.col("program"))).join(F.broadcast(opens), "stem").select("pid", "stem", F.length("program").alias("size"), F.explode("cells").alias("c")).select("pid", "stem", "size", "c.*")
    # shortest first, then by key: both in one number
    place = F.shiftleft(F.least("size", F.lit(8191)).cast("long"), 50).bitwiseOR(F.shiftright("key", 10))
    three = seen.withColumn("place", place).groupBy(*cell, "stem").agg(F.min_by("pid", "place").alias("p3"), F.min_by("key", "place").alias("k3"))
    joined = prompt.withColumn("stem", stem(F.col("prefix"))).join(one, [*cell, "h", "prefix"], "left").join(two, [*cell, "prefix"], "left").join(three, [*cell, "stem"], "left")
    known = F.col("h") != 0
    level = F.when(known & F.col("p1").isNotNull(), 1).when(known & F.col("p2").isNotNull(), 2).otherwise(3)
    pick = lambda a: F.when(level == 1, F.col(f"{a}1")).when(level == 2, F.col(f"{a}2")).otherwise(F.col(f"{a}3"))
    picked = joined.select("program_id", *cell, "arm", "h", "prefix", level.alias("level"), pick("p").alias("pid"), pick("k").alias("key"))
    texts = train.join(F.broadcast(picked.select("pid").distinct()), "pid").select("pid", F.col("program").alias("source"), F.explode("cells").alias("c"))
    texts = texts.select("pid", "source", F.col("c.model").alias("model"), F.col("c.form").alias("form"), F.col("c.seed").alias("seed"), F.col("c.key").alias("key"))
    out = picked.join(texts, [*cell, "pid", "key"], "left").withColumn("source", F.coalesce("source", F.lit("")))
    rest = F.substring("source", F.length("prefix") + 1, F.length("source"))
    return out.select("program_id", "model", "form", "arm", "seed", "h", "prefix", "level", F.concat("prefix", rest).alias("program"))


def _statements(program: str = "program"):
    return F.concat(F.array(F.lit("^"), F.lit("^")), F.split(program, "\n"), F.array(F.lit("")))


def transition_counts(train: DataFrame, header: str = "intent5") -> DataFrame:
    """Count model: (h, prev2, prev1, next, n) over statements; the end is ''."""
    s = F.col("s")
    grams = F.transform(F.sequence(F.lit(1), F.size(s) - 2), lambda i: F.struct(F.element_at(s, i).alias("prev2"), F.element_at(s, i + 1).alias("prev1"), F.element_at(s, i + 2).alias("next")))
    return train.select(F.col(header).alias("h"), F.explode(F.array(_statements())).alias("s")).select("h", F.explode(grams).alias("g")).groupBy("h", "g.prev2", "g.prev1", "g.next").agg(F.count("*").alias("n"))


def dropped_counts(train: DataFrame, p: float = 0.5) -> DataFrame:
    """The count model of the header-dropout variant: each program under its own header or, with probability p by its identifier, under none (header 0)."""
    none = headers.dropout(F.lit("x"), F.col("program_id"), p) == ""
    return transition_counts(train.withColumn("seen", F.when(none, 0).otherwise(F.col("intent5"))), "seen")


def header_counts(train: DataFrame, header: str = "intent5") -> DataFrame:
    """(h, n): how often a header opens a training sequence; the header takes part in the loss."""
    return train.groupBy(F.col(header).alias("h")).agg(F.count("*").alias("n"))


def smoothed(counts: DataFrame, asked: DataFrame, add: float = 0.5) -> DataFrame:
    """Add ``p`` to rows (h, prev2, prev1, next, ...): the next statement's probability, backing off from (h, prev2, prev1) over (h, prev1) and (prev1) to all statements.

    Each level is its own counts plus ``add`` parts of the next shorter one; the last is smoothed over the vocabulary and one unseen statement.
    """
    levels = (["h", "prev2", "prev1"], ["h", "prev1"], ["prev1"])
    every = counts.groupBy("next").agg(F.sum("n").alias("c"))
    size = every.agg(F.sum("c").alias("all_n"), F.count("*").alias("all_v"))
    out = asked.join(every, "next", "left").crossJoin(F.broadcast(size)).withColumn("p", (F.coalesce("c", F.lit(0)) + add) / (F.col("all_n") + add * (F.col("all_v") + 1))).drop("c", "all_n", "all_v")
    for keys in reversed(levels):
        own = counts.groupBy(*keys, "next").agg(F.sum("n").alias("c"))
        total = counts.groupBy(*keys).agg(F.sum("n").alias("t"))
        out = out.join(own, [*keys, "next"], "left").join(total, keys, "left").withColumn("p", (F.coalesce("c", F.lit(0)) + add * F.col("p")) / (F.coalesce("t", F.lit(0)) + add)).drop("c", "t")
    return out


def nll(counts: DataFrame, heads: DataFrame, corpus: DataFrame, header: str = "intent5", add: float = 0.5) -> DataFrame:
    """Mean negative log likelihood per unit by header; the header counts as the first unit of each sequence, before its statements."""
    rows = transition_counts(corpus, header).withColumnRenamed("n", "m")
    each = smoothed(counts, rows, add).groupBy("h").agg(F.sum("m").alias("statements"), F.sum(-F.col("m") * F.ln("p")).alias("loss"))
    size = heads.agg(F.sum("n").alias("all_n"), F.count("*").alias("all_v"))
    first = header_counts(corpus, header).withColumnRenamed("n", "programs").join(heads, "h", "left").crossJoin(F.broadcast(size))
    first = first.select("h", "programs", (-F.ln((F.coalesce("n", F.lit(0)) + add) / (F.col("all_n") + add * (F.col("all_v") + 1)))).alias("head_loss"))
    both = each.join(first, "h")
    return both.select("h", "programs", "statements", "head_loss", ((F.col("loss") + F.col("programs") * F.col("head_loss")) / (F.col("statements") + F.col("programs"))).alias("nll"))


def greedy_steps(counts: DataFrame, heads: DataFrame) -> DataFrame:
    """(h, prev2, prev1, next): the most frequent next statement (ties by text) under a header, or under any where the header has not seen the state, for the headers asked for."""
    pick = F.max_by("next", F.struct("n", "next")).alias("next")
    own = counts.groupBy("h", "prev2", "prev1").agg(pick)
    anyone = counts.groupBy("prev2", "prev1", "next").agg(F.sum("n").alias("n")).groupBy("prev2", "prev1").agg(F.max_by("next", F.struct("n", "next")).alias("other"))
    states = anyone.crossJoin(F.broadcast(heads.select("h").distinct()))  # at most 32 headers
    return states.join(own, ["h", "prev2", "prev1"], "left").select("h", "prev2", "prev1", F.coalesce("next", "other").alias("next"))


def guided_steps(counts: DataFrame, heads: DataFrame, strength: float = 2.0, add: float = 0.5) -> DataFrame:
    """The same by guided scores of a dropout model: (1 + strength) times the log probability under the header less strength times that under none."""
    seen = counts.select("prev2", "prev1", "next").distinct().crossJoin(F.broadcast(heads.select("h").distinct()))
    given = smoothed(counts, seen, add).withColumnRenamed("p", "with")
    none = smoothed(counts, seen.select("prev2", "prev1", "next", F.lit(0).alias("h")).distinct(), add).select("prev2", "prev1", "next", F.col("p").alias("without"))
    score = F.round((1 + strength) * F.ln("with") - strength * F.ln("without"), 9)
    both = given.join(none, ["prev2", "prev1", "next"]).withColumn("score", score)
    return both.groupBy("h", "prev2", "prev1").agg(F.max_by("next", F.struct("score", "next")).alias("next"))


def begin(prompt: DataFrame, steps_from: DataFrame) -> DataFrame:
    """Add ``head`` (the prompt's whole statements with its last, cut one completed), ``prev2`` and ``prev1``.

    A prefix of characters may stop inside a statement. The most frequent statement that starts so completes
    it: after the same two statements under the header, else after them under any, else anywhere; a cut that no statement
    starts with stays as it is.
    """
    lines = F.split("prefix", "\n")
    cut = prompt.withColumn("__l", lines).withColumn("cut", F.element_at("__l", -1))
    cut = cut.withColumn("__w", F.slice("__l", 1, F.size("__l") - 1)).drop("__l")
    at = lambda k: F.coalesce(F.try_element_at("__w", F.lit(-k)), F.lit("^"))
    cut = cut.withColumn("prev2", at(2)).withColumn("prev1", at(1))
    best = F.max_by("next", F.struct("n", "next"))
    out = cut
    for k, keys in enumerate((["h", "prev2", "prev1"], ["prev2", "prev1"], [])):
        asked = cut.select(*keys, "cut").distinct()
        rows = steps_from.filter("next <> ''").groupBy(*keys, "next").agg(F.sum("n").alias("n"))
        fits = rows.join(F.broadcast(asked), keys) if keys else rows.crossJoin(F.broadcast(asked))  # the distinct cuts of a bounded sample
        found = fits.filter(F.startswith("next", "cut")).groupBy(*keys, "cut").agg(best.alias(f"__f{k}"))
        out = out.join(found, [*keys, "cut"], "left")
    first = F.coalesce("__f0", "__f1", "__f2", "cut")
    out = out.withColumn("__first", first)
    head = F.array_join(F.concat("__w", F.array("__first")), "\n")
    return out.withColumn("head", head).withColumn("prev2", F.col("prev1")).withColumn("prev1", F.col("__first")).drop("__w", "__f0", "__f1", "__f2", "__first", "cut")


def greedy_decode(steps: DataFrame, starts: DataFrame, cap: int = 24, cut=lambda df: df) -> DataFrame:
    """Greedy statement decoding by pointer doubling: ``starts`` plus ``completion`` and ``hit_cap`` (no end within ``cap`` statements).

    State = (h, prev2, prev1). Doubling the successor table log2(cap) times composes up
    to ``cap`` steps with as many self-joins; ``cut`` writes the table between
    doublings. ``starts`` has h, prev2, prev1 and any other columns. A state that the table does not hold ends there, as truncated.
    """
    nothing = F.array().cast("array<string>")
    step = steps.select("h", "prev2", "prev1", F.when(F.col("next") == "", nothing).otherwise(F.array("next")).alias("out"), F.col("prev1").alias("to2"), F.col("next").alias("to1"))
    n = 1
    while n < cap + 1:  # the end itself takes a step
        step = cut(step)
        a, b = step.alias("a"), step.alias("b")
        go = (F.col("a.h") == F.col("b.h")) & (F.col("a.to2") == F.col("b.prev2")) & (F.col("a.to1") == F.col("b.prev1")) & (F.col("a.to1") != "")
        step = a.join(b, go, "left").select(F.col("a.h").alias("h"), F.col("a.prev2").alias("prev2"), F.col("a.prev1").alias("prev1"), F.concat("a.out", F.coalesce("b.out", nothing)).alias("out"), F.coalesce("b.to2", "a.to2").alias("to2"), F.coalesce("b.to1", "a.to1").alias("to1"))
        n *= 2
    ended = (F.coalesce("to1", F.lit("^")) == "") & (F.size(F.coalesce("out", nothing)) <= cap)
    done = starts.join(step, ["h", "prev2", "prev1"], "left")
    return done.select(*starts.columns, F.array_join(F.slice(F.coalesce("out", nothing), 1, cap), "\n").alias("completion"), (~ended).alias("hit_cap"))


def decode(steps: DataFrame, counts: DataFrame, prompt: DataFrame, cap: int = 24, cut=lambda df: df) -> DataFrame:
    """Programs decoded from prefixes: the columns of ``prompt`` with h, plus ``program`` and ``hit_cap``."""
    out = greedy_decode(steps, begin(prompt, counts), cap, cut)
    whole = F.when(F.col("completion") == "", F.col("head")).otherwise(F.concat_ws("\n", "head", "completion"))
    return out.select(*prompt.columns, whole.alias("program"), "hit_cap")


def truncation_report(generated: DataFrame, *by: str) -> DataFrame:
    """Generations and the share that reached the completion cap, by cell (a column ``hit_cap``)."""
    return generated.groupBy(*by).agg(F.count("*").alias("n"), F.avg(F.col("hit_cap").cast("int")).alias("truncated"))


def over_cap(sample: DataFrame, cap: int) -> DataFrame:
    """The share of the references' own completions that the cap would cut."""
    n = F.size(F.split(F.substring("program", F.length("prefix") + 1, F.length("program")), "\n"))
    return sample.agg(F.count("*").alias("n"), F.avg((n > cap).cast("int")).alias("over_cap"))


def header_prompt(prompt: DataFrame) -> DataFrame:
    """Add ``prompt``: the rendered header on its own line and the prefix, as a generator reads them."""
    head = headers.render_header(F.greatest("h", F.lit(0)), F.col("form"))
    return prompt.withColumn("prompt", F.when(head == "", F.col("prefix")).otherwise(F.concat_ws("\n", head, "prefix")))


def compare_runs(a: DataFrame, b: DataFrame) -> DataFrame:
    """Byte-equal share, score moves and arm-mean shift between two runs of the same jobs (program, adh6)."""
    keys = ["program_id", "model", "form", "arm", "seed"]
    j = a.select(*keys, F.col("program").alias("pa"), F.col("adh6").alias("sa")).join(b.select(*keys, F.col("program").alias("pb"), F.col("adh6").alias("sb")), keys)
    return j.groupBy("model", "form", "arm").agg(F.count("*").alias("n"), F.avg((F.col("pa") == F.col("pb")).cast("int")).alias("byte_equal"), F.count_if(F.col("sa") != F.col("sb")).alias("score_moves"), F.avg((F.col("sb") - F.col("sa")) / 6).alias("mean_shift"))
