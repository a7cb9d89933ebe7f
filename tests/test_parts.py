"""Experiments ask for the parts that their results depend on; plans and drift look at rows."""

import pytest
from pyspark.sql import functions as F

from sqltutor import registry, workloads
from sqltutor.operators import grouprl, judging, linking, mutate, replay, reward


@pytest.fixture
def alone(monkeypatch):
    """No part is kept yet, and nothing may be timed, trained or compared row by row."""
    def never(*a, **k):
        raise AssertionError("not needed")

    monkeypatch.setattr(workloads, "_TABLES", {})
    monkeypatch.setattr(workloads, "_RUNS", {})
    for where, name in ((replay, "overlaps"), (replay, "outcomes"), (replay, "clocked"), (grouprl, "train")):
        monkeypatch.setattr(where, name, never, raising=False)


def _few(spark, monkeypatch):
    """One question of two families, and made-up runs: gold's texts agree, all others differ."""
    qs = spark.createDataFrame([(1, "A", "A01", "simple"), (2, "B", "B01", "easy")], "question_id long, suite string, family string, tier string")
    monkeypatch.setattr(workloads, "asked", lambda *a: qs)
    kinds = spark.createDataFrame([(k, "slow") for k in mutate.KINDS], "kind string, mode string")
    verdicts = {"em": "true", "jac": "1.0D", "n_tok_in": "1", "n_tok_out": "1", "error": "'table'", "pattern_ok": "true"}
    rows = qs.crossJoin(kinds).withColumns({c: F.expr(x) for c, x in verdicts.items()})
    monkeypatch.setattr(workloads, "scored", lambda *a, **k: rows, raising=False)

    def checked(spark, sf_dir, wanted, profile, first=None, users=8):
        assert profile.name == "adaptive"
        one = wanted.select("db_id", "sql").union(wanted.select("db_id", "gold_sql")).distinct()
        right = wanted.select(F.col("gold_sql").alias("sql"), F.lit(True).alias("right")).distinct()
        made = {"engine": "'adaptive'", "status": "'ok'", "times": "CAST(NULL AS ARRAY<DOUBLE>)", "t_mean": "CAST(NULL AS DOUBLE)", "n": "1L", "sum_h": "IF(right, '0', sql)", "xor_h": "0L", "ncols": "1",
                "error": "CAST(NULL AS STRING)", "cpu_ms": "0L", "shuffled": "0L", "spilled": "0L", "peak": "0L", "t_first": "1.0D"}
        return one.join(right, "sql", "left").withColumn("right", F.coalesce("right", F.lit(False))).withColumns({c: F.expr(x) for c, x in made.items()})

    monkeypatch.setattr(replay, "checked", checked, raising=False)


def test_error_shares_of_the_untrained_policy_need_no_times_and_no_training(spark, sf, alone, monkeypatch):
    _few(spark, monkeypatch)
    assert {r["arm"] for r in workloads.run("w11", spark, sf).collect()} <= {"base"}
    assert workloads._first(spark, sf, ("base",)).count() == 2


def test_equality_alone_needs_no_times(spark, sf, alone, monkeypatch):
    _few(spark, monkeypatch)
    got = registry.QUERIES["executed_pairs"](spark, sf).collect()
    assert len(got) == len(registry._PAIRED) * len(registry._SAME) and {r["equal"] for r in got} == {False}


@pytest.fixture
def asked_for(monkeypatch, spark):
    """What is run, timed and scored as text, as far as the answer depends on it; runs are made up."""
    seen = {"runs": set(), "kinds": set(), "timed": set(), "steps": set(), "texts": 0}
    monkeypatch.setattr(workloads, "_TABLES", {})
    monkeypatch.setattr(workloads, "_RUNS", {})

    def checked(spark, sf_dir, wanted, profile, first=None, users=8):
        families = {(r["family"], r["kind"]) for r in wanted.select("family", "kind").collect()}
        seen["runs"] |= {f[0] for f, _ in families}
        seen["kinds"] |= {k for _, k in families}
        right = wanted.select("db_id", F.col("gold_sql").alias("sql"), F.lit(True).alias("right")).distinct()
        one = wanted.select("db_id", "sql").distinct().join(right, ["db_id", "sql"], "left").withColumn("right", F.coalesce("right", F.lit(False)))
        made = {"engine": f"'{profile.name}'", "status": "'ok'", "times": "array(1.0D, 1.0D)", "t_mean": "1.0D", "n": "1L", "sum_h": "IF(right, '0', sql)", "xor_h": "0L", "ncols": "1",
                "error": "CAST(NULL AS STRING)", "cpu_ms": "1L", "shuffled": "0L", "spilled": "0L", "peak": "0L", "t_first": "1.0D"}
        return one.withColumns({c: F.expr(x) for c, x in made.items()})

    def clocked(spark, sf_dir, rows, profile, warmup=0, repeats=2):
        seen["timed"] |= {r["sql"] for r in rows.where("right").select("sql").collect()}
        return rows

    def noted(where, name):
        whole = getattr(where, name)

        def step(df, *a, **k):
            seen["steps"].add(name)
            seen["texts"] = max(seen["texts"], df.count())
            return whole(df, *a, **k)

        monkeypatch.setattr(where, name, step)

    monkeypatch.setattr(replay, "checked", checked)
    monkeypatch.setattr(replay, "clocked", clocked)
    for where, name in ((reward, "assembled"), (linking, "with_elements"), (judging, "judged")):
        noted(where, name)
    return seen


def test_error_shares_of_one_suite_run_and_score_no_more_than_its_answers(spark, sf, asked_for):
    got = workloads.run("w11", spark, sf).collect()
    assert got and asked_for["runs"] == {"A"} and not asked_for["timed"]
    assert asked_for["texts"] <= workloads.asked(spark, sf, "A").count()


def test_supervised_fits_score_no_text_and_run_what_is_learnt_from(spark, sf, asked_for):
    assert {r["arm"] for r in registry.QUERIES["supervised_fits"](spark, sf).collect()} == set(workloads.SUPERVISED)
    assert asked_for["runs"] == {"A", "B"} and not asked_for["steps"] and not asked_for["timed"]


def test_the_critic_times_golds_only(spark, sf, asked_for):
    assert len(registry.QUERIES["plan_critic"](spark, sf).collect()) == 5
    assert asked_for["kinds"] == {"exact"} and len(asked_for["timed"]) == 36


def test_the_gate_grid_links_and_judges_nothing(spark, sf, asked_for):
    assert len(workloads.run("w17", spark, sf).collect()) == 25
    assert asked_for["steps"] == {"assembled"} and not asked_for["timed"]


@pytest.mark.parametrize("name", ["reward_cube", "reward_candidates", "several_objectives", "training_overhead_arms", "tree_search", "workload_w20"])
def test_staged_rewards_judge_no_clauses(spark, sf, asked_for, name):
    assert registry.QUERIES[name](spark, sf).limit(1).count() == 1
    assert asked_for["steps"] == {"assembled", "with_elements"} and asked_for["runs"] == {"A", "B", "C"}


@pytest.mark.parametrize("wid", ["w12", "w15"])
def test_training_runs_and_scores_its_own_questions(spark, sf, asked_for, wid):
    assert workloads.run(wid, spark, sf).count() > 0
    assert asked_for["runs"] == {"A", "B"} and asked_for["steps"] == {"assembled", "with_elements"}
    assert asked_for["texts"] == len(mutate.KINDS) * workloads.training_questions(spark, sf).count()


@pytest.mark.parametrize("name", ["plan_cost", "cost_limit"])
def test_plan_level_queries_run_their_texts(spark, sf, monkeypatch, name):
    from sqltutor.plans import execution

    ran, whole = [], execution.run
    monkeypatch.setattr(execution, "run", lambda spark, texts, *a, **k: ran.append(texts.count()) or whole(spark, texts, *a, **k))
    got = registry.QUERIES[name](spark, sf).collect()
    assert len(got) == 36 and sum(ran) >= 36
    assert name == "cost_limit" or all(0 < r["ratio"] <= 1 for r in got)


def test_drift_looks_at_values_before_names(spark):
    cells = "db_id string, tab string, col string, dtype string"
    old, new = spark.createDataFrame([("d", "t", "price", "int")], cells), spark.createDataFrame([("d", "t", "prices", "int"), ("d", "t", "cost", "int")], cells)
    df = spark.createDataFrame([(1, 7), (2, 8)], "price int, prices int")
    was, now = linking.contents(old, new, {"t": df.select("price")}), linking.contents(new, old, {"t": df.select(F.col("price").alias("cost"), "prices")})
    assert {tuple(r)[2:] for r in linking.drift(old, new, was, now).collect()} == {("price", "cost", "renamed"), (None, "prices", "gained")}
    assert {tuple(r)[2:] for r in linking.drift(old, new).collect()} == {("price", "prices", "renamed"), (None, "cost", "gained")}


def test_drift_reads_the_tables(spark, sf):
    files = registry.QUERIES["schema_drift"](spark, sf).inputFiles()
    assert any(f.endswith("customer.parquet") for f in files)


def test_suites_and_databases_run_together_and_runaways_by_themselves(spark, sf, monkeypatch):
    from sqltutor.plans import execution

    calls = []

    def run(spark, texts, tables, profile, repeats=0, concurrency=1, limit_s=30.0):
        rows = texts.select("db_id", "sql").collect()
        calls.append((limit_s, {r["db_id"] for r in rows}, any("CROSS JOIN" in r["sql"] for r in rows), all("CROSS JOIN" in r["sql"] for r in rows)))
        return spark.createDataFrame([], f"{execution.SCHEMA}, db_id string")

    monkeypatch.setattr(workloads, "_TABLES", {})
    monkeypatch.setattr(execution, "run", run)
    workloads._checked(spark, sf, "ABC", execution.ADAPTIVE)
    every = {"retail", "web", "activity"}
    assert calls == [(30.0, every, False, False), (replay.RUNAWAY_S, every, True, True)]
    workloads._checked(spark, sf, "B", execution.ADAPTIVE)
    assert len(calls) == 2


def test_each_text_runs_over_the_tables_of_its_database(spark, sf):
    from sqltutor.plans import execution
    from sqltutor.sources.load import DATABASES, views

    views(spark, sf)
    texts = spark.createDataFrame([("retail", "SELECT COUNT(*) AS n FROM nation"), ("web", "SELECT COUNT(*) AS n FROM nation")], "db_id string, sql string")
    got = {r["db_id"]: r["status"] for r in execution.run(spark, texts, DATABASES, repeats=0, concurrency=2).collect()}
    assert got == {"retail": "ok", "web": "blocked"}


@pytest.mark.parametrize("wid", ["w2", "w16"])
def test_ranks_by_rows_and_times_judge_no_answer(spark, sf, asked_for, monkeypatch, wid):
    monkeypatch.setattr(workloads, "trained", lambda spark, sf_dir, arms=workloads.ARMS: {a: grouprl.Run(workloads.start_policy()) for a in arms})
    assert workloads.run(wid, spark, sf).count() > 0
    assert "judged" not in asked_for["steps"] and bool(asked_for["timed"])


def test_shared_rows_of_the_suite_are_not_timed(spark, sf, asked_for, monkeypatch):
    monkeypatch.setattr(replay, "overlaps", lambda spark, *a: spark.createDataFrame([], "family string, kind string, overlap double"))
    got = registry.QUERIES["execute_suite"](spark, sf).collect()
    assert {r["engine"] for r in got} == {"adaptive", "static"} and len(got) == 2 * 36 * len(mutate.KINDS)
    assert asked_for["runs"] == {"A", "B", "C"} and not asked_for["timed"]
