"""Every question's texts run with the question's own parameters; those that run together do what each does by itself."""

import pytest
from pyspark.sql import functions as F

from sqltutor import workloads
from sqltutor.operators import replay
from sqltutor.operators.suites import BY_ID
from sqltutor.plans import execution
from sqltutor.sources import load

ASKED = [(1, "C06", "en", "src0"), (2, "C06", "en", "nowhere"), (3, "A07", "1998", "5-LOW"), (4, "A10", "3", ""), (5, "B12", "BUILDING", ""), (6, "B12", "it's", ""), (7, "A12", "1996", "1-URGENT")]
KINDS = ("exact", "equivalent", "value", "operator", "condition", "attribute", "syntax_error", "bad_cast")


@pytest.fixture(scope="module")
def wanted(spark):
    qs = spark.createDataFrame(ASKED, "question_id long, family string, p1 string, p2 string")
    return replay.asked_texts(qs, KINDS).localCheckpoint()


@pytest.fixture(scope="module")
def alone(spark, sf, wanted):
    load.views(spark, sf)
    texts = {(r.db_id, r.sql) for r in wanted.collect()}
    return {(db, s): execution.run_one(spark, s, load.DATABASES[db], repeats=0) for db, s in texts}


def test_texts_are_those_of_the_questions(wanted):
    got = {(r.question_id, r.kind): r for r in wanted.collect()}
    assert len(got) == len(ASKED) * len(KINDS)
    for q, family, p1, p2 in ASKED:
        assert got[q, "exact"].sql == got[q, "exact"].gold_sql == BY_ID[family].text(p1, p2)


@pytest.mark.parametrize("profile", [execution.ADAPTIVE, execution.STATIC], ids=lambda p: p.name)
def test_together_is_what_each_text_does_by_itself(spark, sf, wanted, alone, profile):
    rows = replay.together(spark, wanted, profile).collect()
    known = {r.sql for r in rows}
    assert len(known) == len(rows) and {"C06", "B12", "A12"} <= {r.family for r in wanted.collect() if r.sql in known}
    for r in rows:
        one = alone[r.db_id, r.sql]
        assert (r.status, r.n, r.sum_h, r.xor_h, r.ncols) == (one[0], *one[3:7]), r.sql
    assert {r.status for r in rows} == {"ok", "parse_error"}


def test_a_question_has_the_outcome_of_its_own_text(spark, sf, wanted, alone):
    seen = replay.checked(spark, sf, wanted, execution.ADAPTIVE)
    got = {(r.question_id, r.kind): r for r in replay.compared(wanted, seen).collect()}
    assert len(got) == wanted.count()
    for r in wanted.collect():
        pred, gold = alone[r.db_id, r.sql], alone[r.db_id, r.gold_sql]
        x = got[r.question_id, r.kind]
        assert (x.status, x.equal) == (pred[0], pred[0] == "ok" and pred[3:7] == gold[3:7]), (r.sql, r.kind)
    assert not got[1, "value"].equal and got[2, "value"].equal  # one family, one kind


def test_shared_rows_are_those_of_single_texts(spark, sf, wanted):
    load.views(spark, sf)
    some = wanted.where("kind NOT IN ('syntax_error', 'bad_cast')")
    rows = replay.compared(some, replay.checked(spark, sf, some, execution.ADAPTIVE))
    key = F.col("question_id").cast("string")
    single = replay.overlaps(spark, sf, some.drop("template").withColumn("family", key), rows.withColumn("family", key))
    got, want = ({(str(r[0]), r[1]): round(r[2], 9) for r in df.collect()} for df in (replay.overlaps(spark, sf, some, rows), single))
    assert got == want and len(got) > 5 and any(0 < x < 1 for x in got.values())


def test_what_takes_too_long_together_is_split(spark, sf, monkeypatch):
    load.views(spark, sf)
    qs = spark.createDataFrame([(k, "B09", str(k), "") for k in range(6)], "question_id long, family string, p1 string, p2 string")
    some, calls, whole = replay.asked_texts(qs, ("exact",)), [], execution.limited

    def limited(spark, limit_s, work):
        calls.append(limit_s)
        if len(calls) == 1:
            raise execution.TimeLimit
        return whole(spark, limit_s, work)

    monkeypatch.setattr(execution, "limited", limited)
    assert {r.sql for r in replay.together(spark, some, execution.ADAPTIVE).collect()} == {r.sql for r in some.collect()} and len(calls) == 3


def test_only_what_counts_is_timed_and_once(spark, sf, monkeypatch):
    monkeypatch.setattr(workloads, "_TABLES", {})
    qs = spark.createDataFrame([(1, "B", "B01", "easy", "1", ""), (2, "B", "B01", "easy", "2", "")], "question_id long, suite string, family string, tier string, p1 string, p2 string")
    monkeypatch.setattr(workloads, "asked", lambda *a: qs)
    timed, whole = [], replay.clocked

    def clocked(spark, sf_dir, rows, profile, warmup=0, repeats=2):
        timed.append({r["sql"] for r in rows.collect()})
        return whole(spark, sf_dir, rows, profile, warmup, repeats)

    monkeypatch.setattr(replay, "clocked", clocked)
    one = workloads.answered(spark, sf, "B", need="times", only=("first", qs.where("question_id = 1").withColumn("kind", F.lit("slow"))))
    assert [(r.question_id, r.kind) for r in one.collect()] == [(1, "slow")] and len(timed[0]) == 2 and one.first()["t_pred"] > 0
    every = workloads.answered(spark, sf, "B", need="times").where("equal").collect()
    assert not timed[0] & timed[1] and all(r.t_pred > 0 and r.t_gold > 0 for r in every) and {r.question_id for r in every} == {1, 2}
