"""The registered queries: each method and experiment on the given tables.

Programs, sample and scores of a directory are shared by the queries of an
application; they are written once to the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import headers as H
from ..functions.geometry import execute, psi, twice_area, validity
from ..operators import contrasts as C
from ..operators import corpus, decisions, generator, pairing, prompts, ranktests, resampling, routing, sampling, scoring
from ..operators import protocol as P

from ..schema import SEEDS
from ..shipping import ship
from ..sources.tables import flatten_arc, outer_profile, programs, table
from .scratch import written

_KEPT: dict[tuple, DataFrame] = {}


def _keep(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        _KEPT[key] = written(make())
    return _KEPT[key]


def progs(spark, d) -> DataFrame:
    return _keep(spark, d, "programs", lambda: programs(spark, d))


def pool(spark, d) -> DataFrame:
    return _keep(spark, d, "pool", lambda: corpus.held_out_pool(progs(spark, d)))


def sample(spark, d) -> DataFrame:
    return _keep(spark, d, "sample", lambda: prompts.with_prefix(sampling.draw(pool(spark, d), sampling.quotas(pool(spark, d)))))


def training(spark, d) -> DataFrame:
    return _keep(spark, d, "training", lambda: generator.training_rows(progs(spark, d)))


def prompts_of(spark, d) -> DataFrame:
    return _keep(spark, d, "prompts", lambda: generator.prompts(sample(spark, d)))


def _gates(spark, d) -> list[tuple[str, int]]:
    """What must hold before any statistic: the control's training set differs in pairing only, and both models get identical wrong headers. Raises otherwise."""
    key = (spark.sparkContext.applicationId, d, "gates")
    if key not in _KEPT:
        wrong = lambda m: prompts_of(spark, d).filter((F.col("model") == m) & (F.col("form") == "text") & (F.col("arm") == "wrong")).select(F.col("program_id").alias("sample_id"), "seed", F.col("h").alias("injected_header"))
        passed = [(f"only_pairing_{s}", P.assert_only_pairing_differs(training(spark, d), given=f"g{s}")) for s in SEEDS]
        _KEPT[key] = [*passed, ("same_injection", pairing.assert_same_injection(wrong("M"), wrong("R")))]
    return _KEPT[key]


def scores(spark, d) -> DataFrame:
    def make():
        _gates(spark, d)
        return scoring.score(generator.complete(prompts_of(spark, d), training(spark, d)), sample(spark, d))

    return _keep(spark, d, "scores", make)


def earlier(spark, d) -> DataFrame:
    """The earlier design's sample: an unstratified draw of 100 held-out entries, duplicates and leaks kept."""
    held = lambda: progs(spark, d).filter("split = 'held' and intent4 > 0")
    return _keep(spark, d, "earlier", lambda: prompts.with_prefix(sampling.draw_simple(held(), 100, "initial")))


def earlier_scores(spark, d) -> DataFrame:
    return _keep(spark, d, "earlier_scores", lambda: scoring.score(generator.complete(generator.prompts(earlier(spark, d)), training(spark, d)), earlier(spark, d)))


CAP = 24


def decoded(spark, d) -> DataFrame:
    """Programs decoded greedily from the 40 % prefixes by the count models of M, R and U, seed 0, text header."""

    def make():
        out = None
        asked = prompts_of(spark, d).filter("seed = 0 and form in ('text', 'none')").withColumn("h", F.greatest("h", F.lit(0)))
        for model, header in (("M", F.col("intent5")), ("R", F.col("g0")), ("U", F.lit(0))):
            c = written(generator.transition_counts(training(spark, d).withColumn("seen", header), "seen"))
            mine = asked.filter(F.col("model") == model)
            part = generator.decode(generator.greedy_steps(c, mine), c, mine, CAP, written)
            out = part if out is None else out.union(part)
        return out

    return _keep(spark, d, "decoded", make)


def refs(spark, d) -> DataFrame:
    return _keep(spark, d, "refs", lambda: scoring.reference_scores(sample(spark, d)))


def wrong_d(spark, d) -> DataFrame:
    return C.paired(scores(spark, d), "wrong")


def r9(df: DataFrame) -> DataFrame:
    """Doubles rounded to nine places."""
    return df.select(*[F.round(c, 9).alias(c) if t == "double" else c for c, t in df.dtypes])


def logp(df: DataFrame, col: str = "p") -> DataFrame:
    """p as log10, rounded to six places, so that tails count."""
    return df.withColumn(col, F.round(F.log10(col), 6))


# corpus


def corpus_programs(spark, d):
    return progs(spark, d).select("program_id", "n_blocks", "program_sha", "split")


def phi_bits(spark, d):
    return progs(spark, d).select("program_id", "intent5", "intent4", "profile")


def psi_bits(spark, d):
    ship(spark)
    e = execute(progs(spark, d).select("program").distinct())
    return e.select(F.sha2("program", 256).alias("sha"), F.col("solid.ok").alias("ok"), psi(F.col("solid")).alias("psi5"), validity(F.col("program")).alias("valid"))


def dedup_exact(spark, d):
    return corpus.dedup_exact(progs(spark, d), "program", "program_id").select("program_id", "program_sha")


def dedup_loose(spark, d):
    return corpus.dedup_loose(progs(spark, d), "program", "program_id").select("program_id")


def dedup_key_report(spark, d):
    p = prompts.with_prefix(progs(spark, d))
    return corpus.dedup_key_report(p, {"source": F.col("l_orderkey").cast("string"), "program": F.col("program"), "prefix": F.col("prefix"), "completion": F.expr("substring(program, length(prefix) + 1)")})


def pool_steps(spark, d):
    return corpus.pool_steps(progs(spark, d))


def leak_filter(spark, d):
    p = progs(spark, d)
    return corpus.drop_leaked(p.filter("split = 'held'"), p.filter("split = 'train'")).select("program_id")


def contamination(spark, d):
    return corpus.contaminated(table(spark, d, "documents"), table(spark, d, "benchmark"))


def pool_agree(spark, d):
    again = corpus.held_out_pool(programs(spark, d))
    return corpus.pools_agree(pool(spark, d), again)


def length_profile(spark, d):
    return r9(corpus.length_profile(progs(spark, d), "program", "split"))


# sampling and headers


def profile_counts(spark, d):
    return sampling.profile_counts(pool(spark, d))


def quota_draw(spark, d):
    return sample(spark, d).select("program_id", "profile", "prefix_sha")


def natural_weights(spark, d):
    return r9(sampling.natural_weights(sampling.profile_counts(pool(spark, d))))


def quota_comparators(spark, d):
    return sampling.comparators(sampling.profile_counts(pool(spark, d)))


def document_draw(spark, d):
    """The same stratified draw over documents, by language and whether a notice opens a line."""
    notice = F.coalesce("text", F.lit("")).rlike(r"(^|\n)Licensed under")
    docs = table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("program_id"), F.concat_ws(":", F.coalesce("lang", F.lit("")), F.when(notice, "notice").otherwise("plain")).alias("profile"))
    return sampling.draw(docs, sampling.quotas(docs)).select(F.col("program_id").alias("doc_id"), "profile")


def sample_overlap(spark, d):
    return sampling.sample_overlap(sample(spark, d), earlier(spark, d))


def effective_size(spark, d):
    return sampling.effective_size(scores(spark, d))


def arc_vertices(spark, d):
    """Full arcs flattened to twelve segments, one per supplier, and twice their enclosed area."""
    s = table(spark, d, "supplier").select("s_suppkey", (F.col("s_suppkey") % 1000).alias("c"), (2 * (10 + F.col("s_suppkey") % 50)).alias("r"))
    loop = s.select("s_suppkey", F.explode(F.array(flatten_arc(F.col("c"), F.col("c"), F.col("r"), 12))).alias("p"))
    return loop.select("s_suppkey", twice_area(F.col("p")).alias("area2"), F.array_max(F.transform("p", lambda v: v["x"])).alias("right"))


def outer_loops(spark, d):
    """Of three nested squares per supplier, in an order that varies, twice the area of the outer profile."""
    s = table(spark, d, "supplier").select("s_suppkey", *[(5 + (F.col("s_suppkey") * k) % 97).cast("long").alias(f"w{k}") for k in (1, 7, 13)])
    square = lambda w: F.array(*[F.struct((w * x).cast("long").alias("x"), (w * y).cast("long").alias("y")) for x, y in ((0, 0), (1, 0), (1, 1), (0, 1))])
    loops = s.select("s_suppkey", F.explode(F.array(F.array(*[square(F.col(f"w{k}")) for k in (1, 7, 13)]))).alias("l"))
    outer = loops.select("s_suppkey", F.explode(F.array(outer_profile(F.col("l")))).alias("p"))
    return outer.select("s_suppkey", twice_area(F.col("p")).alias("area2"))


def sample_facts(spark, d):
    return r9(sampling.sample_facts(sample(spark, d), pool(spark, d)))


def headers_rendered(spark, d):
    s, key = sample(spark, d), F.col("program_id")
    bits = {"own": F.col("intent5"), "corrupt1": H.corrupt(F.col("intent5"), key, 1), "corrupt2": H.corrupt(F.col("intent5"), key, 2), "random": H.random_header(F.col("intent5"), key)}
    return s.select("program_id", *[H.render_header(b, f).alias(f"{k}_{f}") for k, b in bits.items() for f in ("text", "token")], H.dropout(H.render_header(F.col("intent5"), "text"), key).alias("dropped"))


def header_vocab(spark, d):
    return progs(spark, d).select(F.explode(F.split(H.render_header(F.col("intent5"), "token"), " ")).alias("token")).filter("token <> ''").groupBy("token").agg(F.count("*").alias("n"))


def derangement_plan(spark, d):
    return pairing.derange(progs(spark, d).filter("split = 'train' and intent5 > 0"), "program_id", "intent5", "R0")


def wrong_headers(spark, d):
    return pairing.wrong_headers(sample(spark, d))


def chance_match(spark, d):
    return r9(pairing.chance_match(derangement_plan(spark, d)))


def marginal_identity(spark, d):
    return pairing.assert_same_marginal(derangement_plan(spark, d)).groupBy("h").agg(F.count("*").alias("n"))


def shuffled_plan(spark, d):
    """Invariants of the other derangement plan: rows, programs that kept their own header, headers whose frequency changed."""
    train = progs(spark, d).filter("split = 'train' and intent5 > 0").select("program_id", F.col("program_id").alias("head"))
    plan = pairing.derange_shuffled(train, "program_id", "head", "R0")
    twice = plan.groupBy("given").agg(F.count("*").alias("c")).agg(F.count_if(F.col("c") != 1).alias("changed"))
    return plan.agg(F.count("*").alias("n"), F.count_if(F.col("own") == F.col("given")).alias("kept")).crossJoin(twice)


def retrieved_header(spark, d):
    out = pairing.retrieved_header(table(spark, d, "embeddings"))
    return out.withColumn("cosine", F.round("cosine", 6))


# prompts


def prefix_clusters(spark, d):
    return prompts.prefix_clusters(sample(spark, d))


def prefix_leakage(spark, d):
    return r9(prompts.prefix_leakage(sample(spark, d)))


def prompts_rendered(spark, d):
    return generator.header_prompt(prompts_of(spark, d)).select("program_id", "model", "form", "arm", "seed", F.sha2("prompt", 256).alias("prompt_sha"))


def first_occurrence(spark, d):
    return r9(prompts.first_occurrence(sample(spark, d)))


def cap_calibration(spark, d):
    return prompts.calibrate_cap(prompts.with_prefix(progs(spark, d).filter("split = 'train'")))


# models


def fit_counts_m(spark, d):
    return generator.transition_counts(training(spark, d))


def fit_counts_r(spark, d):
    return generator.transition_counts(training(spark, d), "g0")


def fit_counts_u(spark, d):
    return generator.transition_counts(training(spark, d).withColumn("h", F.lit(0)), "h")


def nll(spark, d):
    """The loss of M on held-out programs, header and statements."""
    held = progs(spark, d).filter("split = 'held' and intent5 > 0")
    return r9(generator.nll(generator.transition_counts(training(spark, d)), generator.header_counts(training(spark, d)), held))


def decode_greedy(spark, d):
    """Completions of M from nothing, one per header."""
    c = written(generator.transition_counts(training(spark, d)))
    starts = sample(spark, d).select(F.col("program_id").alias("id"), F.col("intent5").alias("h"), F.lit("^").alias("prev2"), F.lit("^").alias("prev1"))
    return generator.greedy_decode(generator.greedy_steps(c, starts), starts, CAP, written).select("id", "completion", "hit_cap")


def decode_prefix(spark, d):
    return decoded(spark, d).select("program_id", "model", "arm", F.sha2("program", 256).alias("sha"), "hit_cap")


def decode_guided(spark, d):
    """The header-dropout variant, decoded with guidance from the 40 % prefixes under the true header."""
    c = written(generator.dropped_counts(training(spark, d)))
    asked = prompts_of(spark, d).filter("model = 'M' and arm = 'correct' and seed = 0 and form = 'text'")
    out = generator.decode(written(generator.guided_steps(c, asked)), c, asked, CAP, written)
    return out.select("program_id", F.sha2("program", 256).alias("sha"), "hit_cap")


def truncation(spark, d):
    """Share of decoded programs at the completion cap, by model and arm; the references' share over it as arm 'reference'."""
    own = generator.over_cap(sample(spark, d), CAP).select(F.lit("none").alias("model"), F.lit("reference").alias("arm"), "n", F.col("over_cap").alias("truncated"))
    return r9(generator.truncation_report(decoded(spark, d), "model", "arm").union(own))


def decoded_levels(spark, d):
    """Adherence and executability of the decoded programs, a truncated one scored as it stands."""
    s = scoring.score(decoded(spark, d), sample(spark, d))
    return r9(s.groupBy("model", "arm").agg(F.count("*").alias("n"), (F.sum("adh6") / (6 * F.count("*"))).alias("adherence"), F.avg(F.col("ok").cast("int")).alias("executability"), F.avg(F.col("hit_cap").cast("int")).alias("truncated")))


def integrity(spark, d):
    """The gates that run before any statistic, with the number of rows each compared, and the arm means read again from the written scores."""
    scores(spark, d)
    again = {(r["model"], r["form"], r["arm"]): r["m"] for r in P.arm_means(scores(spark, d)).collect()}  # nine rows
    P.assert_means(scores(spark, d), again)
    return spark.createDataFrame([*_gates(spark, d), ("arm_means", len(again))], "gate string, n long")


def generations(spark, d):
    return scores(spark, d).select("program_id", "model", "form", "arm", "seed", "h", "level", F.sha2("program", 256).alias("sha"))


def score_rows(spark, d):
    return scores(spark, d).select("program_id", "model", "form", "arm", "seed", "ok", "phi5", "psi5", "adh6", "rec6", "gated6")


# measures


def arm_levels(spark, d):
    return scoring.arm_levels(scores(spark, d))


def detector_agreement(spark, d):
    return r9(scoring.detector_agreement(refs(spark, d)))


def reference_self_score(spark, d):
    return r9(scoring.reference_self_score(refs(spark, d)))


def multi_part(spark, d):
    return scoring.multi_part(scores(spark, d))


def recovery(spark, d):
    return r9(scoring.recovery(scores(spark, d), refs(spark, d)))


def output_identity(spark, d):
    return scoring.output_identity(scores(spark, d))


# contrasts and tests


def paired_wilcoxon(spark, d):
    return r9(logp(ranktests.wilcoxon(wrong_d(spark, d), ["form", "seed"])))


def cluster_wilcoxon(spark, d):
    return r9(logp(ranktests.wilcoxon(C.clustered(wrong_d(spark, d)), ["form", "seed"])))


def zero_handling(spark, d):
    x = wrong_d(spark, d)
    parts = [ranktests.wilcoxon(x, ["form", "seed"], zeros=z).select(F.lit(z).alias("zeros"), "form", "seed", "t_plus", "z", "p") for z in ("pratt", "drop", "split", "sign")]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return r9(logp(out))


def sign_flip(spark, d):
    return r9(ranktests.sign_flip(wrong_d(spark, d), ["form", "seed"], "program_id"))


def largest_class(spark, d):
    return r9(logp(C.largest_class(wrong_d(spark, d)), "p_without"))


def _clusters(spark, d, what):
    """Cluster means of a contrast with the baseline, or of the interaction."""
    return C.clustered(C.dissociation_rows(scores(spark, d)) if what == "interaction" else C.paired(scores(spark, d), what))


def bootstrap_exact(spark, d):
    return r9(resampling.bootstrap_exact(_clusters(spark, d, "wrong")))


def bootstrap_poisson(spark, d):
    return r9(resampling.bootstrap_poisson(_clusters(spark, d, "wrong")))


def bootstrap_interaction(spark, d):
    return r9(resampling.bootstrap_exact(_clusters(spark, d, "interaction")))


def bootstrap_interaction_poisson(spark, d):
    return r9(resampling.bootstrap_poisson(_clusters(spark, d, "interaction")))


def bootstrap_masked(spark, d):
    return r9(resampling.bootstrap_exact(_clusters(spark, d, "masked")))


def bootstrap_benefit(spark, d):
    return r9(resampling.bootstrap_exact(_clusters(spark, d, "correct")))


def retrospective_power(spark, d):
    return r9(resampling.power_by_resampling(wrong_d(spark, d)))


def retrospective_power_clusters(spark, d):
    return r9(resampling.power_by_resampling(_clusters(spark, d, "wrong"), unit="prefix_sha"))


def wrong_vs_none_decision(spark, d):
    x = wrong_d(spark, d)
    P.assert_deciding_columns(set(x.columns) - {"ref_ok"})
    P.assert_decides(x)
    return r9(decisions.decide_wrong_vs_none(x))


def blinded_check(spark, d):
    P.assert_blind(P.blinded_counts)
    return P.blinded_counts(wrong_d(spark, d))


def profile_reweighting(spark, d):
    return r9(C.reweight(wrong_d(spark, d), sampling.natural_weights(sampling.profile_counts(pool(spark, d)))))


def masked_contrast(spark, d):
    return r9(logp(ranktests.wilcoxon(C.paired(scores(spark, d), "masked"), ["form", "seed"])))


def cluster_masked(spark, d):
    return r9(logp(ranktests.wilcoxon(_clusters(spark, d, "masked"), ["form", "seed"])))


def benefit(spark, d):
    return r9(logp(ranktests.wilcoxon(C.paired(scores(spark, d), "correct"), ["form", "seed"], alternative="two-sided")))


def cluster_benefit(spark, d):
    return r9(logp(ranktests.wilcoxon(_clusters(spark, d, "correct"), ["form", "seed"], alternative="two-sided")))


def joint_benefit(spark, d):
    """The benefit where both arms run."""
    return r9(logp(ranktests.wilcoxon(C.paired(scores(spark, d), "correct").filter("ok"), ["form", "seed"], alternative="two-sided")))


def joint_executable(spark, d):
    return r9(logp(ranktests.wilcoxon(wrong_d(spark, d).filter("ok"), ["form", "seed"])))


def reference_strata(spark, d):
    return r9(C.by_reference_stratum(wrong_d(spark, d), refs(spark, d)))


def dissociation(spark, d):
    return r9(logp(decisions.dissociation_cells(C.dissociation_rows(scores(spark, d)))))


def cluster_dissociation(spark, d):
    return r9(logp(ranktests.wilcoxon(_clusters(spark, d, "interaction"), ["seed"], alternative="greater")))


def dissociation_joint(spark, d):
    return r9(C.joint_pooled(C.dissociation_rows(scores(spark, d))))


def earlier_dissociation(spark, d):
    """Test D on the earlier, unstratified sample, one value per distinct program; reported beside the main one, never pooled with it."""
    s = earlier(spark, d)
    x = C.dissociation_rows(earlier_scores(spark, d)).join(s.select("program_id", "program_sha"), "program_id")
    return r9(logp(ranktests.wilcoxon(C.clustered(x, "program_sha"), ["seed"], alternative="greater")))


def competence_gate(spark, d):
    return r9(decisions.competence_gate(scores(spark, d)))


def outcome(spark, d):
    s = scores(spark, d)
    x = C.dissociation_rows(s)
    P.assert_decides(x)
    return r9(decisions.outcome(s, x))


def uptake(spark, d):
    return r9(logp(routing.uptake(scores(spark, d))))


def uptake_by_seed(spark, d):
    return r9(logp(routing.uptake(scores(spark, d), by_seed=True)))


def uptake_reassigned(spark, d):
    return r9(routing.uptake_reassigned(scores(spark, d)))


def uptake_permutation(spark, d):
    return r9(routing.uptake_permutation(scores(spark, d)))


def neither_named(spark, d):
    return r9(routing.neither_named(scores(spark, d)))


def mann_whitney(spark, d):
    s = scores(spark, d).filter("ok and ((model = 'R' and arm = 'correct') or model = 'U')").withColumn("g", F.when(F.col("model") == "R", 1).otherwise(0))
    return r9(logp(ranktests.mann_whitney(s, ["seed"], "adh6", "g")))


def mann_whitney_pooled(spark, d):
    """Runnable outputs, seeds pooled: R (both arms, and the correct one alone) against the baseline, and M's correct arm against R's."""
    s = scores(spark, d).filter("ok and form in ('text', 'none')")
    r, u, m, right = F.col("model") == "R", F.col("model") == "U", F.col("model") == "M", F.col("arm") == "correct"
    pairs = {"R_vs_baseline": (r, u), "R_correct_vs_baseline": (r & right, u), "M_correct_vs_R_correct": (m & right, r & right)}
    rows = F.array_compact(F.array(*[F.when(x | y, F.struct(F.lit(k).alias("pair"), F.when(x, 1).otherwise(0).alias("g"))) for k, (x, y) in pairs.items()]))
    return r9(logp(ranktests.mann_whitney(s.select("adh6", F.explode(rows).alias("e")).select("adh6", "e.*"), ["pair"], "adh6", "g")))


def leave_one_profile(spark, d):
    return r9(logp(ranktests.wilcoxon(routing.leave_one_out(C.dissociation_rows(scores(spark, d))), ["left_out", "seed"], alternative="greater")))


def leave_one_feature(spark, d):
    return r9(logp(ranktests.wilcoxon(routing.leave_one_out(C.dissociation_rows(scores(spark, d)), "feature"), ["left_out", "seed"], alternative="greater")))


def diff_mass_cube(spark, d):
    return routing.diff_mass(wrong_d(spark, d))


def per_profile(spark, d):
    return r9(C.per_profile(scores(spark, d)))


def single_feature_order(spark, d):
    return C.single_feature_order(r9(C.per_profile(scores(spark, d))))


def metric_shift(spark, d):
    return r9(C.metric_shift(scores(spark, d)))


def control_offset(spark, d):
    return r9(C.control_offset(scores(spark, d)))


def control_offset_share(spark, d):
    return r9(C.offset_share(scores(spark, d)))


def _retrieved(spark, d):
    """Sample programs, each with the next query vector in turn, and whether the retrieved neighbour has the query's label."""
    got = retrieved_header(spark, d).select("vec_id", (F.col("own") == F.col("given")).alias("hit"))
    q = got.count()
    at = pairing.global_rank(got, F.floor(F.col("vec_id") / 1_000_000), F.col("vec_id")).select(F.col("rank").alias("v"), "hit")
    order = F.md5(F.concat(F.lit("W:"), "program_id").cast("binary"))
    s = pairing.global_rank(sample(spark, d).select("program_id"), F.substring(order, 1, 1), order, F.col("program_id"))
    return s.select("program_id", (F.col("rank") % max(q, 1)).alias("v")).join(at, "v").select("program_id", "hit")


def retrieval_contrast(spark, d):
    """Wrong-vs-none where a retrieval step supplies the header: all programs, and those with a right and with a wrong header."""
    x = C.retrieval_arm(scores(spark, d), _retrieved(spark, d))
    x = x.withColumn("rows", F.explode(F.array(F.lit("all"), F.when(F.col("hit"), "right").otherwise("error"))))
    return r9(logp(ranktests.wilcoxon(x, ["rows", "seed"])))


def regime_defined(spark, d):
    return r9(C.regime(scores(spark, d)))


def zero_prefix_regime(spark, d):
    """The 0 % prefix: every program starts from nothing, so headers alone tell prompts apart."""
    s = prompts.with_prefix(sample(spark, d).drop("prefix", "prefix_sha"), 0.0)
    return r9(C.regime(scoring.score(generator.complete(generator.prompts(s), training(spark, d)), s)))


def dose_response(spark, d):
    """M, text, all seeds under correct, corrupted, random and wrong headers."""
    s = sample(spark, d)
    base = generator.prompts(s).filter("model = 'M' and form = 'text' and arm in ('correct', 'wrong')")
    own = base.filter("arm = 'correct'").join(s.select("program_id", "intent5"), "program_id")
    more = [own.withColumn("arm", F.lit(a)).withColumn("h", h.cast("int")).drop("intent5") for a, h in (("corrupted", H.corrupt(F.col("intent5"), F.col("program_id"), 1)), ("random", H.random_header(F.col("intent5"), F.col("program_id"))))]
    allp = base.unionByName(more[0]).unionByName(more[1])
    lv = scoring.score(generator.complete(allp, training(spark, d)), s).groupBy("arm").agg((F.sum("adh6") / (6 * F.count("*"))).alias("adherence"))
    return r9(decisions.dose_response(lv))


def initial_evaluation(spark, d):
    """The earlier design: an unstratified draw of 100 entries with duplicates kept, averaged within equal programs, then tested."""
    x = C.paired(earlier_scores(spark, d), "wrong").join(earlier(spark, d).select("program_id", "program_sha"), "program_id")
    return r9(logp(ranktests.wilcoxon(C.clustered(x, "program_sha"), ["form", "seed"])))


def job_manifest(spark, d):
    """The inference jobs of model M and the baseline, each with the number of prompts that the sample gives it."""
    jobs = spark.createDataFrame(generator.manifest(), "model string, form string, arm string, prefix_frac double, seed int")
    n = prompts_of(spark, d).groupBy("model", "form", "arm", "seed").agg(F.count("*").alias("n"))
    return n.join(F.broadcast(jobs), ["model", "form", "arm", "seed"]).select("model", "form", "arm", "prefix_frac", "seed", "n")


# other carriers

DOC_FEATURES = ("TABLE", "NOTICE", "LONG_LINE", "SECTIONS", "SENTENCES")


def doc_audit(spark, d):
    """Documents: features read off the text by patterns against features of its parsed lines, as a confusion table per feature and quality label.

    The parser splits lines and cells and looks at their number, place and length; it uses no pattern.
    """
    doc = table(spark, d, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    t = F.col("text")
    seen = (t.rlike(r"\|"), t.rlike(r"(^|\n)Licensed under"), t.rlike(r"[^\n]{200}"), t.rlike(r"[^\n]\n+[^\n]"), t.rlike(r"[.!?]"))
    doc = doc.select("doc_id", F.array(*seen).alias("seen"), F.explode(F.array(F.split(t, "\n"))).alias("lines"))
    lines = F.col("lines")
    parsed = (
        F.exists(lines, lambda x: F.size(F.split(x, "[|]")) > 1),
        F.exists(lines, lambda x: (F.get(F.split(x, " "), F.lit(0)) == "Licensed") & F.startswith(F.coalesce(F.get(F.split(x, " "), F.lit(1)), F.lit("")), F.lit("under"))),
        F.exists(lines, lambda x: F.length(x) >= 200),
        F.size(F.filter(lines, lambda x: x != "")) > 1,
        F.exists(lines, lambda x: F.translate(x, ".!?", "") != x),
    )
    rows = F.array(*[F.struct(F.lit(n).alias("feature"), F.get("seen", F.lit(i)).alias("t"), F.coalesce(p, F.lit(False)).alias("s")) for i, (n, p) in enumerate(zip(DOC_FEATURES, parsed))])
    j = doc.select("doc_id", F.explode(rows).alias("r")).join(table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    return j.groupBy(F.coalesce("quality", F.lit(-1)).alias("quality"), "r.feature").agg(F.count("*").alias("n"), F.count_if(F.col("r.t") & F.col("r.s")).alias("both"), F.count_if(F.col("r.t") & ~F.col("r.s")).alias("text_only"), F.count_if(~F.col("r.t") & F.col("r.s")).alias("parsed_only"))


PAGE_FEATURES = (("LIST", "li"), ("LINKS", "a"), ("HEADINGS", "h1"), ("PARAGRAPHS", "p"))


def page_audit(spark, d):
    """Pages: features read off the raw text by patterns against tags of a parsed page outside scripts, with nesting that closes as executability.

    The parser splits at the opening brackets, names each tag by its first word and keeps the depth as
    a running sum; a page runs if the depth of non-void tags never falls below zero and ends there.
    """
    p = table(spark, d, "pages").select("page_id", F.coalesce("html", F.lit("")).alias("html"))
    seen = F.array(*[F.regexp_count("html", F.lit(f"<{tag}[ >]")).alias(n) for n, tag in PAGE_FEATURES])
    clean = F.regexp_replace("html", r"(?s)<script.*?</script>", "")
    parts = p.select("page_id", seen.alias("seen"), F.posexplode(F.split(clean, "<")).alias("pos", "part"))
    name = F.lower(F.substring_index(F.substring_index(F.substring_index(F.substring_index("part", ">", 1), " ", 1), "\n", 1), "/", -1))
    closing = F.startswith("part", F.lit("/"))
    void = name.isin("br", "img", "hr", "meta", "link", "input", "") | F.startswith("part", F.lit("!")) | F.startswith("part", F.lit("?")) | (F.col("pos") == 0)
    tags = parts.select("page_id", "seen", "pos", F.when(void, "").otherwise(name).alias("name"), F.when(void, 0).when(closing, -1).otherwise(1).alias("step"))
    w = Window.partitionBy("page_id").orderBy("pos")
    deep = tags.withColumn("depth", F.sum("step").over(w))
    counts = [F.count_if((F.col("name") == tag) & (F.col("step") == 1)).alias(n) for n, tag in PAGE_FEATURES]
    page = deep.groupBy("page_id").agg(F.first("seen").alias("seen"), *counts, ((F.min("depth") >= 0) & (F.sum("step") == 0)).alias("runs"))
    rows = F.array(*[F.struct(F.lit(n).alias("feature"), F.get("seen", F.lit(i)).alias("t"), F.col(n).alias("s")) for i, (n, _) in enumerate(PAGE_FEATURES)])
    r = page.select("runs", F.explode(rows).alias("r"))
    return r.groupBy("runs", "r.feature").agg(F.count("*").alias("n"), F.count_if((F.col("r.t") > 0) & (F.col("r.s") > 0)).alias("both"), F.count_if((F.col("r.t") > 0) & (F.col("r.s") == 0)).alias("text_only"), F.count_if((F.col("r.t") == 0) & (F.col("r.s") > 0)).alias("parsed_only"), F.sum("r.t").alias("found"), F.sum("r.s").alias("parsed"))


def conversation_pairs(spark, d):
    """Assistant turns with the previous turn as conditioning, and a deranged one; shared-word share of each."""
    c = table(spark, d, "conversations")
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = c.withColumn("given", F.lag("text").over(w)).withColumn("prev_role", F.lag("role").over(w)).filter("role = 'assistant' and prev_role = 'user'")
    t = t.select(F.concat_ws("-", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("id"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce("given", F.lit("")).alias("given"))
    n = t.count()
    order = F.md5(F.col("id").cast("binary"))
    ranked = pairing.global_rank(t, pairing.bucket_of(order, n), order, F.col("id"))
    donor = ranked.select(((F.col("rank") - 1 + n) % max(n, 1)).alias("rank"), F.col("given").alias("wrong"))
    words = lambda x: F.array_distinct(F.split(F.lower(x), r"[^a-z]+"))
    share = lambda a: F.size(F.array_intersect(words(F.col(a)), words(F.col("text")))) / F.size(words(F.col("text")))
    return ranked.join(donor, "rank").select("id", F.round(share("given"), 9).alias("own_overlap"), F.round(share("wrong"), 9).alias("wrong_overlap"))


def asof_orders(spark, d):
    """Latest order of a customer at or before each of their events."""
    o = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("key"), F.col("o_orderdate").cast("timestamp").alias("frozen_at")).agg(F.max(F.col("o_orderkey")).cast("string").alias("artifact"))
    e = table(spark, d, "events").select(F.col("user_id").alias("key"), F.expr("timestampadd(YEAR, -27, ts)").alias("ts"), F.col("event_id").alias("row"))
    return P.asof_freeze(o, e).select("key", "row", "artifact")


def interval_pairs(spark, d):
    """Purchases within an hour after a click of the same user, by hour buckets and an equi-join."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("u"))
    hour = 3_600_000_000
    c = e.filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("u").alias("cu"), F.explode(F.array(F.floor(F.col("u") / hour), F.floor(F.col("u") / hour) + 1)).alias("b"))
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "u", F.floor(F.col("u") / hour).alias("b"))
    return p.join(c, ["user_id", "b"]).filter((F.col("u") >= F.col("cu")) & (F.col("u") <= F.col("cu") + hour)).select("purchase_id", "click_id")


def rollup_arms(spark, d):
    t = scores(spark, d).withColumn("seed", F.col("seed").cast("string")).rollup("form", "arm", "seed").agg(F.count("*").alias("n"), (F.sum("adh6") / (6 * F.count("*"))).alias("adherence"))
    return r9(t.fillna("all", ["form", "arm", "seed"]))


def grouping_sets_profiles(spark, d):
    s = scores(spark, d)
    s.createOrReplaceTempView("intentaudit_scores")
    return r9(spark.sql("SELECT arm, profile, count(*) AS n, sum(adh6) / (6 * count(*)) AS adherence FROM intentaudit_scores GROUP BY GROUPING SETS ((arm), (profile), (arm, profile), ())"))


def population_strata(spark, d):
    """Adherence-free carrier of reweighting: orders per region and market segment with natural shares."""
    c = table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


def run_agreement(spark, d):
    """Two decodings of the same jobs under different partition counts.

    The training rows are dealt anew without a shuffle of their texts: two read splits become one, so that the second run is as parallel as the first.
    """
    s, train = sample(spark, d), training(spark, d)
    splits = train.rdd.getNumPartitions()
    train = train.coalesce(splits - 1) if splits > 1 else train.repartition(2)
    again = scoring.score(generator.complete(generator.prompts(s.repartition(7)), train), s)
    return r9(generator.compare_runs(scores(spark, d), again))


def stream_windows(spark, d):
    from ..streaming.monitor import window_counts

    return window_counts(table(spark, d, "events"))


def stream_sliding(spark, d):
    from ..streaming.monitor import sliding_counts

    return sliding_counts(table(spark, d, "events"))


def stream_sessions(spark, d):
    from ..streaming.monitor import sessions

    return sessions(table(spark, d, "events"))


NAMES = (
    "corpus_programs arc_vertices outer_loops phi_bits psi_bits dedup_exact dedup_loose dedup_key_report pool_steps leak_filter contamination pool_agree length_profile profile_counts quota_draw quota_comparators document_draw "
    "natural_weights sample_facts sample_overlap headers_rendered header_vocab derangement_plan shuffled_plan wrong_headers chance_match marginal_identity retrieved_header prefix_clusters prefix_leakage "
    "prompts_rendered first_occurrence cap_calibration fit_counts_m fit_counts_r fit_counts_u nll decode_greedy decode_prefix decode_guided truncation decoded_levels integrity generations score_rows "
    "effective_size arm_levels detector_agreement reference_self_score multi_part recovery output_identity paired_wilcoxon cluster_wilcoxon zero_handling sign_flip largest_class "
    "bootstrap_exact bootstrap_poisson bootstrap_interaction bootstrap_interaction_poisson bootstrap_masked bootstrap_benefit retrospective_power retrospective_power_clusters wrong_vs_none_decision blinded_check "
    "profile_reweighting masked_contrast cluster_masked benefit cluster_benefit joint_benefit joint_executable reference_strata dissociation cluster_dissociation dissociation_joint earlier_dissociation "
    "competence_gate outcome uptake uptake_by_seed uptake_reassigned uptake_permutation neither_named mann_whitney mann_whitney_pooled leave_one_profile leave_one_feature diff_mass_cube per_profile "
    "single_feature_order metric_shift control_offset control_offset_share retrieval_contrast regime_defined zero_prefix_regime dose_response initial_evaluation job_manifest doc_audit page_audit "
    "conversation_pairs asof_orders interval_pairs rollup_arms grouping_sets_profiles population_strata run_agreement stream_windows stream_sliding stream_sessions"
).split()
QUERIES = {n: globals()[n] for n in NAMES}
