"""Sources, sinks and the SQL surface."""

import json

from intentaudit.functions import sql
from intentaudit.operators import ranktests
from intentaudit.sources import generations


def row(i, arm):
    return {"sample_id": f"s{i}", "model": "M", "form": "text", "arm": arm, "prefix_frac": 0.4, "seed": i % 3, "injected_header": "", "completion": "raise 5", "hit_cap": False, "eos": True}


def test_generation_source(spark, tmp_path):
    for k in range(3):
        (tmp_path / f"part{k}.jsonl").write_text("".join(json.dumps(row(i, "wrong" if i % 2 else "correct")) + "\n" for i in range(10)) + "not json\n")
    generations.register(spark)
    df = spark.read.format("intent_generations").load(str(tmp_path))
    assert df.count() == 30 and df.filter("arm = 'wrong'").count() == 15
    assert generations.read_json(spark, str(tmp_path)).cache().filter("_corrupt is not null").count() == 3


def test_generation_source_ranges_and_bad_lines(spark, tmp_path, monkeypatch):
    """Ranges of a file give every line once; bad lines are counted where they are kept."""
    from intentaudit.sources.generations import GenerationReader

    lines = [json.dumps(row(i, "wrong")) for i in range(50)] + ["not json", "[1]"]
    (tmp_path / "a.jsonl").write_text("\n".join(lines))
    for step in (7, 100, 333, 1 << 20):
        monkeypatch.setattr(generations, "PART_BYTES", step)
        reader = GenerationReader({"path": str(tmp_path)})
        got = [r for p in reader.partitions() for r in reader.read(p)]
        assert sorted(r[0] for r in got) == sorted(f"s{i}" for i in range(50))
    generations.register(spark)
    kept = spark.read.format("intent_generations").option("corrupt", "true").load(f"file://{tmp_path}")
    assert kept.filter("_corrupt is not null").count() == 2 and kept.filter("sample_id is not null").count() == 50


def test_bucketed_scores_pair_without_shuffle(spark):
    df = spark.createDataFrame([(f"p{i}", "M", "text", a, s, 3) for i in range(20) for a in ("correct", "wrong") for s in (0, 1)], "program_id string, model string, form string, arm string, seed int, adh6 int")
    generations.save_scores(df, "kept_scores", 4)
    plan = spark.table("kept_scores").groupBy("program_id", "seed").count()._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and spark.table("kept_scores").count() == 80
    spark.sql("drop table kept_scores")


def test_score_layout(spark, tmp_path):
    df = spark.createDataFrame([("p", "M", "text", a, s, 3) for a in ("correct", "wrong") for s in (0, 1)], "program_id string, model string, form string, arm string, seed int, adh6 int")
    generations.write_scores(df, str(tmp_path / "s"))
    back = spark.read.parquet(str(tmp_path / "s")).filter("arm = 'wrong' and seed = 1")
    assert back.count() == 1 and "PartitionFilters: [" in back._jdf.queryExecution().toString()
    generations.write_log(df, str(tmp_path / "j"))
    assert spark.read.json(str(tmp_path / "j")).count() == 4


def test_sql_surface(spark):
    sql.register(spark)
    r = spark.sql("SELECT adherence6(5, 1) AS a, adherence6(16, 1) AS e, intent_size(21) AS n, profile_of(6) AS p").first()
    assert (r["a"], r["e"], r["n"], r["p"]) == (3, None, 2, "NGON+THIN")
    h = spark.sql("SELECT render_header(5, 'text') AS t, render_header(5, 'token') AS o, render_header(0, 'text') AS e, execute_program('sheet 0\\ndisc 5\\nraise 10').n_solids AS n, execute_program('x').ok AS bad").first()
    assert (h["t"], h["o"], h["e"], h["n"], h["bad"]) == ("# wants: circle, thin", "<WANT> <CIRCLE> <THIN> </WANT>", "", 1, False)
    assert spark.sql("SELECT * FROM explode_features(5, 4)").filter("intended and realized").first()["feature"] == "THIN"


def test_aggregate_twin(spark):
    df = spark.createDataFrame([("a", float(x)) for x in (0.5, -0.5, 0, 1, 1 / 3, 0, -1, 0.5)], "cell string, d double")
    z = ranktests.wilcoxon(df, ["cell"]).first()["z"]
    assert abs(df.groupBy("cell").agg(sql.wilcoxon_z("d").alias("z")).first()["z"] - z) < 1e-9
