"""Golden values, invariants, planted effects and protocol fences."""

import ast
import math
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from intentaudit.functions import geometry, headers, tails
from intentaudit.functions.intent_text import phi, with_intent
from intentaudit.operators import contrasts, decisions, generator, pairing, protocol, ranktests, resampling, routing, sampling
from intentaudit.schema import Options

POOL = {"THIN": 1174, "NGON+THIN": 736, "CIRCLE+THIN": 609, "CIRCLE": 412, "NGON": 411, "TALL": 142, "CIRCLE+TALL": 112, "CIRCLE+NGON+THIN": 87, "CIRCLE+NGON": 75, "NGON+TALL": 70, "CIRCLE+NGON+TALL": 6}
DRAWN = {"THIN": 112, "NGON+THIN": 70, "CIRCLE+THIN": 58, "CIRCLE": 40, "NGON": 39, "TALL": 15, "CIRCLE+TALL": 15, "CIRCLE+NGON+THIN": 15, "CIRCLE+NGON": 15, "NGON+TALL": 15, "CIRCLE+NGON+TALL": 6}


def test_allocation_golden():
    assert sampling.allocate(POOL, 400, 15) == DRAWN
    assert sum(sampling.proportional_quotas(POOL, 400).values()) == 400
    assert sum(sampling.equal_quotas(POOL, 400).values()) == 400
    with pytest.raises(ValueError):
        sampling.allocate({"a": 100, "b": 100}, 20, 15)


def test_manifest_totals():
    assert len(generator.manifest()) == 21
    assert len(generator.manifest(prefixes=(0.0, 0.4))) == 42


def block(body, d, x=0):
    return f"sheet {x}\n{body}\nraise {d}"


SQUARE = "pen 0 0\nseg 10 0\nseg 10 10\nseg 0 10\nshut"
CASES = {
    "disc": (block("disc 5", 10), True, 1, 1),
    "square": (block(SQUARE, 10), True, 0, 0),
    "pentagon": (block("pen 3 0\nseg 7 0\nseg 10 5\nseg 5 10\nseg 0 5\nshut", 10), True, 2, 2),
    "redundant": (block("pen 0 0\nseg 5 0\nseg 10 0\nseg 10 10\nseg 0 10\nshut", 10), True, 2, 0),
    "bow_tie": (block("pen 0 0\nseg 10 10\nseg 10 0\nseg 0 5\nshut", 10), False, 0, 0),
    "open": (block(SQUARE[:-5], 10), False, 0, 0),
    "zero_depth": (block(SQUARE, 0), False, 4, 0),
    "unknown": ("turn 3\n" + block(SQUARE, 10), False, 0, 0),
    "truncated": (block(SQUARE, 10)[:-3], False, 0, 0),
    "ratio_low_edge": (block(SQUARE, 3), True, 0, 0),
    "ratio_high_edge": (block(SQUARE, 20), True, 0, 0),
    "thin": (block(SQUARE, 2), True, 4, 4),
    "tall": (block(SQUARE, 21), True, 8, 8),
    "fused": (block(SQUARE, 5) + "\n" + block(SQUARE, 5, 5), True, 16, 0),
    "apart": (block(SQUARE, 100) + "\n" + block(SQUARE, 100, 200), True, 24, 16),
    "apart_in_y": (block(SQUARE, 100) + "\n" + block("pen 0 500\nseg 10 500\nseg 10 510\nseg 0 510\nshut", 100), True, 20, 20),
    "discs_in_one_box": (block("disc 50", 300) + "\n" + block("disc 10", 300, 90), True, 25, 25),
    "discs_that_touch_an_area": (block("disc 50", 500) + "\n" + block("disc 50", 500, 90), True, 25, 9),
    "disc_beside_slope": (block("pen 0 0\nseg 100 0\nseg 0 100\nshut", 300) + "\n" + block("disc 10", 300, 85), True, 25, 9),
    "disc_off_slope": (block("pen 0 100\nseg 100 0\nseg 100 100\nshut", 300) + "\n" + block("disc 20", 300), True, 25, 25),
    "three_in_a_row": ("\n".join(block(SQUARE, 100, x) for x in (0, 16, 8)), True, 24, 8),
    "empty": ("", False, 0, 0),
    "odd_number": (block(SQUARE, "9" * 12), False, 4, 0),
}


def test_detectors_golden(spark):
    df = spark.createDataFrame([(k, v[0]) for k, v in CASES.items()] + [("null", None)], "k string, program string")
    got = {r["k"]: r for r in geometry.execute(df).select("k", F.col("solid.ok").alias("ok"), geometry.psi(F.col("solid")).alias("psi"), phi(F.col("program")).alias("phi")).collect()}
    assert not got["null"]["ok"] and got["null"]["psi"] == 0 and got["null"]["phi"] == 0
    for k, (_, ok, text, solid) in CASES.items():
        if k in ("odd_number", "zero_depth"):
            assert not got[k]["ok"]
            continue
        assert (got[k]["ok"], got[k]["psi"]) == (ok, solid), k
        assert got[k]["phi"] == text, k


def test_work_is_bounded(spark):
    loop = "\n".join(["pen 0 0", *(f"seg {i} {i * i}" for i in range(1, 160)), "shut"])
    many = "\n".join(["sheet 0", *["seg 1 1"] * 400, "raise 5"])
    got = spark.createDataFrame([(block(loop, 5),), (many,)], "program string")
    assert [r["r"] for r in geometry.execute(got).select(F.col("solid.fail_reason").alias("r")).collect()] == ["budget", "budget"]


def test_detectors_share_no_code():
    root = Path(__file__).resolve().parents[1] / "intentaudit/functions"
    own = lambda f: {n.module for n in ast.walk(ast.parse((root / f).read_text())) if isinstance(n, ast.ImportFrom) and n.level}
    assert not own("geometry.py") and "geometry" not in (root / "intent_text.py").read_text()


def test_derangements(spark):
    rows = [(f"p{i:03d}", i % 7) for i in range(101)]
    df = spark.createDataFrame(rows, "program_id string, intent5 int")
    for plan in (pairing.derange(df, "program_id", "intent5", "s"), pairing.derange_shuffled(df, "program_id", "intent5", "s")):
        assert plan.count() == 101 and plan.select("program_id").distinct().count() == 101
        pairing.assert_same_marginal(plan)
    ids = df.select("program_id", F.col("program_id").alias("h"))
    for fn in (pairing.derange, pairing.derange_shuffled):
        assert fn(ids, "program_id", "h", "s").filter("own = given").count() == 0
    strict = pairing.wrong_headers(df)
    assert strict.filter("own = given").count() == 0 and strict.count() == 101
    with pytest.raises(ValueError):
        pairing.wrong_headers(spark.createDataFrame([("a", 1), ("b", 1), ("c", 2)], "program_id string, intent5 int"))
    with pytest.raises(AssertionError):
        pairing.assert_same_marginal(spark.createDataFrame([(1, 2), (2, 2)], "own int, given int"))


def test_headers(spark):
    r = spark.createDataFrame([(5, "a"), (0, "b"), (10, "c")], "b int, k string").select("b", headers.render_header(F.col("b"), "text").alias("t"), headers.render_header(F.col("b"), "token").alias("o"), headers.corrupt(F.col("b"), F.col("k"), 2).alias("c"), headers.random_header(F.col("b"), F.col("k")).alias("r")).collect()
    assert r[0]["t"] == "# wants: circle, thin" and r[0]["o"] == "<WANT> <CIRCLE> <THIN> </WANT>" and r[1]["t"] == ""
    for x in r:
        assert x["c"] & 12 != 12 and x["r"] & 12 != 12 and x["c"] != x["b"]
    assert bin(r[0]["r"]).count("1") == 2


def test_normal_tail(spark):
    z = [i / 4 for i in range(-48, 49)]
    for r in spark.createDataFrame([(x,) for x in z], "z double").select("z", tails.normal_sf(F.col("z")).alias("p")).collect():
        want = 0.5 * math.erfc(r["z"] / math.sqrt(2))
        assert abs(r["p"] - want) <= 2e-7 * want


def test_fisher(spark):
    tables = [(8, 2, 1, 5), (3, 7, 3, 7), (0, 5, 4, 1), (10, 0, 0, 10), (0, 0, 3, 4)]
    df = spark.createDataFrame(tables, "a long, b long, c long, d long").select("*", tails.fisher_greater(F.col("a"), F.col("b"), F.col("c"), F.col("d")).alias("p"))
    for r in df.collect():
        a, b, c, d = r["a"], r["b"], r["c"], r["d"]
        n, k = a + b, a + c
        want = sum(math.comb(n, i) * math.comb(c + d, k - i) for i in range(a, min(n, k) + 1)) / math.comb(a + b + c + d, k)
        assert abs(r["p"] - want) < 1e-9


def brute_pratt(d):
    order = sorted(abs(x) for x in d)
    rank = {v: (order.index(v) + 1 + order.index(v) + order.count(v)) / 2 for v in set(order)}
    nz = [x for x in d if x]
    t = sum(rank[abs(x)] for x in nz if x > 0)
    s, s2 = sum(rank[abs(x)] for x in nz), sum(rank[abs(x)] ** 2 for x in nz)
    return t, (t - s / 2) / math.sqrt(s2 / 4)


def test_wilcoxon(spark):
    cells = {"mix": [0.5, -0.5, 0, 1, 1 / 3, 0, -1, 0.5], "ties": [1, 1, 1, -1], "one": [0.5], "zero": [0, 0, 0]}
    df = spark.createDataFrame([(k, float(x)) for k, v in cells.items() for x in v], "cell string, d double")
    got = {r["cell"]: r for r in ranktests.wilcoxon(df, ["cell"], alternative="greater").collect()}
    less = {r["cell"]: r for r in ranktests.wilcoxon(df.withColumn("d", -F.col("d")), ["cell"], alternative="less").collect()}
    for k in ("mix", "ties", "one"):
        t, z = brute_pratt(cells[k])
        assert abs(got[k]["t_plus"] - t) < 1e-9 and abs(got[k]["z"] - z) < 1e-9
        assert abs(got[k]["p"] - 0.5 * math.erfc(z / math.sqrt(2))) < 1e-6
        assert abs(less[k]["p"] - got[k]["p"]) < 1e-9
    assert got["zero"]["p"] is None and not got["zero"]["significant"]


def planted(spark, drop_m, drop_r, level_r=0.5, n=200):
    """Score rows with given correct-to-wrong drops, in sixths, for half of the programs."""
    rows = []
    for s in (0, 1, 2):
        for i in range(n):
            hit = i % 2 == 0
            base = 3
            cells = {("U", "none", "uncond"): base, ("M", "text", "correct"): base, ("M", "token", "correct"): base, ("M", "text", "wrong"): base - drop_m * hit, ("M", "token", "wrong"): base - drop_m * hit, ("R", "text", "correct"): int(6 * level_r), ("R", "text", "wrong"): int(6 * level_r) - drop_r * hit}
            rows += [(f"p{i}", f"x{i}", "THIN" if i % 4 < 2 else "NGON", m, f, a, s, v, True, 1) for (m, f, a), v in cells.items()]
    return spark.createDataFrame(rows, "program_id string, prefix_sha string, profile string, model string, form string, arm string, seed int, adh6 int, ok boolean, h int")


def test_planted_outcomes(spark):
    for (dm, dr, lv), want in {(2, 0, 0.5): "dissociation confirmed", (0, 0, 0.5): "underpowered", (0, 2, 0.5): "clean negative", (2, 0, 0.0): "control invalid"}.items():
        s = planted(spark, dm, dr, lv)
        assert decisions.outcome(s, contrasts.dissociation_rows(s)).collect()[0]["outcome"] == want
    v = decisions.decide_wrong_vs_none(contrasts.paired(planted(spark, 2, 0), "wrong")).collect()[0]
    assert v["verdict"] == "REPLICATED" and not v["veto"]
    v = decisions.decide_wrong_vs_none(contrasts.paired(planted(spark, -2, 0), "wrong")).collect()[0]
    assert v["veto"] and v["verdict"] == "clean negative"
    v = decisions.decide_wrong_vs_none(contrasts.paired(planted(spark, 0, 0), "wrong")).collect()[0]
    assert v["verdict"] == "underpowered"


def differences(text, token, n=400):
    """Rows of n programs; each seed of a form is (number of non-zero differences, their sign or 0 for either in turn)."""
    out = []
    for form, seeds in (("text", text), ("token", token)):
        for seed, (k, sign) in enumerate(seeds):
            out += [(form, seed, f"p{i}", f"x{i}", "THIN" if i % 2 else "NGON", (0.0 if i >= k else (sign or (1 if i % 4 < 2 else -1)) / 6), True) for i in range(n)]
    return out


DOWN, FLAT, UP, FEW = (100, -1), (100, 0), (100, 1), (59, -1)
VERDICTS = {
    "replicated": ([DOWN] * 3, [DOWN] * 3, "REPLICATED"),
    "just enough pairs": ([(60, -1)] * 3, [(60, -1)] * 3, "REPLICATED"),
    "one pair short": ([FEW] * 3, [DOWN] * 3, "underpowered"),
    "one pair short in the other form": ([DOWN] * 3, [DOWN, FEW, FEW], "underpowered"),
    "powered null": ([FLAT] * 3, [FLAT] * 3, "clean negative"),
    "one flagged seed, majority without it": ([DOWN, DOWN, FEW], [DOWN] * 3, "REPLICATED"),
    "majority only with the flagged seed": ([DOWN, FLAT, FEW], [DOWN] * 3, "clean negative"),
    "token majority only with the flagged seed": ([DOWN] * 3, [DOWN, FLAT, FEW], "clean negative"),
    "veto on one seed of the other form": ([DOWN] * 3, [DOWN, DOWN, UP], "clean negative"),
}


def test_verdicts_one_label_each(spark):
    rows = [(k, *r) for k, (a, b, _) in VERDICTS.items() for r in differences(a, b)]
    df = spark.createDataFrame(rows, "case string, form string, seed int, program_id string, prefix_sha string, profile string, d double, ok boolean").cache()
    for k, (_, _, want) in VERDICTS.items():
        d = df.filter(F.col("case") == k).drop("case")
        assert decisions.decide_wrong_vs_none(d).first()["verdict"] == want, k
    short = protocol.blinded_counts(df.filter("case = 'one pair short in the other form'")).orderBy("form", "seed").collect()
    assert [r["below"] for r in short] == [False] * 3 + [False, True, True] and all(r["triggered"] for r in short)
    assert not protocol.blinded_counts(df.filter("case = 'just enough pairs'")).first()["triggered"]


def test_gates(spark, tmp_path):
    train = spark.createDataFrame([("a", 1, 2), ("b", 2, 1)], "program_id string, intent5 int, g0 int")
    assert protocol.assert_only_pairing_differs(train) == 2
    with pytest.raises(AssertionError):
        protocol.assert_only_pairing_differs(train.withColumn("g0", F.lit(1)))
    with pytest.raises(AssertionError):
        protocol.assert_only_pairing_differs(train, other=Options(alpha=0.1))
    cells = spark.createDataFrame([("p", 0, "x"), ("q", 0, "y")], "sample_id string, seed int, injected_header string")
    assert pairing.assert_same_injection(cells, cells) == 2
    with pytest.raises(AssertionError):
        pairing.assert_same_injection(cells, cells.filter("sample_id = 'p'"))
    s = spark.createDataFrame([("M", "text", "wrong", 3), ("M", "text", "wrong", 6)], "model string, form string, arm string, adh6 int")
    protocol.assert_means(s, {("M", "text", "wrong"): 0.75})
    with pytest.raises(AssertionError):
        protocol.assert_means(s, {("M", "text", "wrong"): 0.7})
    s.withColumn("rec6", F.lit(1)).write.parquet(str(tmp_path / "s"))
    kept = spark.read.parquet(str(tmp_path / "s"))
    protocol.assert_decides(kept.groupBy("arm").agg(F.avg("adh6")))
    with pytest.raises(PermissionError):
        protocol.assert_decides(kept.groupBy("arm").agg(F.avg("rec6")))
    r = spark.createDataFrame([("p", "M", "text", "wrong", 0, True, 1, 1)], "program_id string, model string, form string, arm string, seed int, ok boolean, phi5 int, psi5 int")
    assert protocol.replay(r, r).isEmpty() and protocol.replay(r, r.withColumn("psi5", F.lit(2))).count() == 1


def test_decoding(spark):
    """A cut statement is completed, an unseen state backs off, an endless loop stops at the cap."""
    train = spark.createDataFrame([(1, "a x\nb\nc"), (1, "a x\nb\nc"), (1, "a y\nb\nd"), (2, "l\nl\nl\nl\nl")], "intent5 int, program string")
    c = generator.transition_counts(train)
    asked = spark.createDataFrame([("cut", 1, "a"), ("rare", 1, "a y\n"), ("other", 2, "a x\nb"), ("odd", 1, "zz")], "id string, h int, prefix string")
    got = {r["id"]: r for r in generator.decode(generator.greedy_steps(c, asked), c, asked, 24).collect()}
    assert got["cut"]["program"] == "a x\nb\nc" and not got["cut"]["hit_cap"]
    assert got["rare"]["program"] == "a y\nb\nd"
    assert got["other"]["program"] == "a x\nb\nc"
    assert got["odd"]["program"] == "zz" and got["odd"]["hit_cap"]
    loop = spark.createDataFrame([("l", 2, "^", "^")], "id string, h int, prev2 string, prev1 string")
    steps = spark.createDataFrame([(2, "^", "^", "l"), (2, "^", "l", "l"), (2, "l", "l", "l")], "h int, prev2 string, prev1 string, next string")
    r = generator.greedy_decode(steps, loop, 24).first()
    assert r["completion"].count("l") == 24 and r["hit_cap"]
    whole = generator.smoothed(c, c.select("h", "prev2", "prev1").distinct().crossJoin(c.select("next").distinct())).groupBy("h", "prev2", "prev1").agg(F.sum("p").alias("p"))
    assert all(0.9 < x["p"] < 1 for x in whole.collect())  # the rest is the unseen statement's


def test_permutation_nulls_agree(spark):
    """The scale-free null draws the same distribution as whole re-assignments of rows; a planted uptake stands out."""
    rows = []
    for s in (0, 1):
        for i in range(120):
            h, intent = (1, 2, 4, 8)[i % 4], (2, 4, 8, 1)[i % 4]
            rows.append(("M", "text", "wrong", s, f"p{i}", h, intent, h if i % 3 else 0, True))
    df = spark.createDataFrame(rows, "model string, form string, arm string, seed int, program_id string, h int, intent4 int, psi5 int, ok boolean")
    a = {r["unit"]: r for r in routing.uptake_permutation(df, replicates=400).collect()}
    b = {r["unit"]: r for r in routing.uptake_reassigned(df, replicates=400).collect()}
    assert set(a) == set(b) == {"0", "1", "pooled"}
    for k in a:
        assert abs(a[k]["observed"] - b[k]["observed"]) < 1e-9 and a[k]["p_perm"] == b[k]["p_perm"] == 1 / 401
        assert abs(a[k]["null_mean"] - b[k]["null_mean"]) < 0.02 and 0.6 < a[k]["null_sd"] / b[k]["null_sd"] < 1.6


def test_bootstrap_levels(spark):
    rows = [("text", s, f"x{i}", 0.1 * s + (i % 5 - 2) / 10) for s in (0, 1, 2) for i in range(50)]
    df = spark.createDataFrame(rows, "form string, seed int, prefix_sha string, d double")
    for fn in (resampling.bootstrap_exact, resampling.bootstrap_poisson):
        got = {r["unit"]: r for r in fn(df).collect()}
        assert set(got) == {"0", "1", "2", "pooled"} and abs(got["pooled"]["estimate"] - 0.1) < 1e-9
        # the seeds differ, so the pooled interval is wider than one seed's
        assert got["pooled"]["hi"] - got["pooled"]["lo"] > 1.3 * (got["1"]["hi"] - got["1"]["lo"])
        assert all(got[k]["lo"] < got[k]["estimate"] < got[k]["hi"] for k in got)


def test_protocol(spark):
    protocol.assert_blind(protocol.blinded_counts)
    with pytest.raises(PermissionError):
        protocol.assert_blind(decisions.guardrail)
    df = spark.createDataFrame([("text", 0, 1.0)], "form string, seed int, d double")
    protocol.assert_blind_plan(protocol.blinded_counts(df))
    with pytest.raises(PermissionError):
        protocol.assert_blind_plan(df.groupBy("form").agg(F.avg("d")))
    with pytest.raises(PermissionError):
        protocol.assert_frozen_first("2026-01-02", "2026-01-01")
    with pytest.raises(ValueError):
        protocol.assert_increment(Options(), Options(alpha=0.1))
    assert protocol.assert_increment(Options(), Options(n=800)) == ["n"]
    with pytest.raises(ValueError):
        protocol.verdict_json({"a": 1}, None)
    with pytest.raises(PermissionError):
        protocol.assert_deciding_columns(["adh6", "rec6"])
    assert protocol.table_hash(df) == protocol.table_hash(df.repartition(3))


def test_no_single_task_window_in_derangement(spark):
    """Rows are ranked inside buckets; only the bucket counts meet in one task."""
    df = spark.range(1000).select(F.col("id").cast("string").alias("program_id"), (F.col("id") % 9).cast("int").alias("intent5"))
    plan = pairing.derange(df, "program_id", "intent5", "s")._jdf.queryExecution().executedPlan().toString().split("\n")
    ranked = [i for i, line in enumerate(plan) if "Window [row_number()" in line]
    assert ranked
    for i in ranked:
        exchange = next(line for line in plan[i:] if "Exchange" in line)
        assert "hashpartitioning(__b" in exchange and "SinglePartition" not in exchange


def test_report_and_protocol_instants(spark):
    from intentaudit.sources import generations

    assert generations.to_markdown(spark.createDataFrame([("b", 1.0), ("a|x", None)], "k string, v double")) == "| k | v |\n| - | - |\n| a\\|x |  |\n| b | 1 |\n"
    protocol.assert_frozen_first("2026-08-06T02:25:00Z", "2026-08-06T04:37:00+02:00")
    with pytest.raises(PermissionError):
        protocol.assert_frozen_first("2026-08-06T02:25:00Z", "2026-08-06T04:00:00+02:00")


def test_intent_properties(spark):
    df = with_intent(spark.createDataFrame([(v[0],) for v in CASES.values()], "program string"))
    assert df.filter("intent4 & 12 = 12").count() == 0
