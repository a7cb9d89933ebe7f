"""Rewards, policy optimisation, execution, data preparation, streams: exact leaves, invariants, brute force."""

import math
import uuid

import numpy as np
import pytest
from pyspark.sql import functions as F

from sqltutor.operators import baselines, dataset, distill, grouprl, linking, metrics, reward
from sqltutor.plans import execution, planlevel
from sqltutor.sources import load
from sqltutor.store import shared_dir
from sqltutor.streaming import jobs

LEAF = "pattern_ok boolean, shape_ok boolean, sim double, status string, equal boolean, t_gold double, t_pred double, link_set_ok boolean, link_equal boolean, n_elements int, clause_share double, want double"


def test_reward_leaves(spark):
    rows = [(False, True, 1.0, "ok", True, 1.0, 1.0, True, True, 1, 1.0, -2.0), (True, True, 0.59, "ok", True, 1.0, 1.0, True, True, 1, 1.0, -2.0),
            (True, True, 0.6, "ok", True, 1.0, 2.0, True, True, 1, 1.0, 3.5), (True, True, 0.9, "ok", True, 2.0, 1.0, True, True, 1, 1.0, 4.0), (True, True, 0.9, "ok", True, 2.0, 0.0, True, True, 1, 1.0, 4.0),
            (True, True, 0.9, "ok", False, 1.0, 1.0, True, False, 0, 0.5, 0.0), (True, True, 0.9, "runtime_error", None, 1.0, None, False, False, 1, 0.0, -1.5), (True, True, 0.9, "ok", True, 1.0, 31.0, True, True, 1, 1.0, 0.0),
            (None, None, None, None, None, None, None, None, None, None, None, -2.0)]
    df = spark.createDataFrame(rows, LEAF)
    assert all(r.total == r.want for r in reward.score(df).collect())
    assert {r.total for r in reward.score(df, reward.preset("skeleton")).collect()} == {-2.0, 3.0, 0.0, -1.5}
    assert {r.total for r in reward.score(df, reward.RewardSpec.sparse()).collect()} == {0.0, 1.0}
    assert [r.total for r in reward.score(df, reward.RewardSpec(require_nonempty=True)).collect()][5] == -1.5
    assert [r.total for r in reward.score(df, reward.RewardSpec(success_rule="ran")).collect()][5] == 4.0


def test_advantages(spark):
    df = spark.createDataFrame([(1, 0, 4.0), (1, 1, -2.0), (2, 0, 1.0), (2, 1, 1.0)], "question_id long, slot int, total double")
    a = grouprl.advantages(df)
    assert all(abs(r.s) < 1e-9 for r in a.groupBy("question_id").agg(F.sum("adv").alias("s")).collect())
    shifted = grouprl.advantages(df.withColumn("total", F.col("total") + 5))
    assert sorted(r.adv for r in a.collect()) == sorted(r.adv for r in shifted.collect())
    assert grouprl.dead_groups(df).first().dead == 1
    same = a.withColumn("logp", F.lit(-1.0)).withColumn("logp_old", F.lit(-1.0))
    assert abs(grouprl.surrogate(same).first().surrogate) < 1e-12


def test_gradient_by_differences(spark):
    rng = np.random.default_rng(0)
    kinds, classes = ["a", "b", "c"], ["x", "y"]
    old = grouprl.Policy(classes, kinds, rng.normal(size=(2, 3)))
    now = grouprl.Policy(classes, kinds, old.theta + 0.25 * rng.normal(size=(2, 3)))
    rows = [(q, classes[q % 2], kinds[rng.integers(3)], float(rng.normal())) for q in range(6) for _ in range(4)]
    df = spark.createDataFrame(rows, "question_id long, family string, kind string, total double")
    df = grouprl.advantages(df).withColumn("group", F.lit(4.0)).withColumn("logp_old", old.logp()).cache()

    def value(theta):
        p = grouprl.Policy(classes, kinds, theta)
        return grouprl.surrogate(df.withColumn("logp", p.logp())).first().surrogate

    grad, here = grouprl.gradient(df.withColumn("logp", now.logp()), now)
    assert here == pytest.approx(value(now.theta), abs=1e-9)
    for i, j in ((0, 0), (1, 2)):
        step = np.zeros((2, 3))
        step[i, j] = 1e-5
        assert grad[i, j] == pytest.approx((value(now.theta + step) - value(now.theta - step)) / 2e-5, abs=1e-6)
    w = np.array([0.4, 0.6])
    kl = lambda t: float((w * grouprl.kl_exact(grouprl.Policy(classes, kinds, t).probs(), old.probs())).sum())
    g = grouprl.kl_gradient(now, old, w)
    for i, j in ((0, 1), (1, 0)):
        step = np.zeros((2, 3))
        step[i, j] = 1e-5
        assert g[i, j] == pytest.approx((kl(now.theta + step) - kl(now.theta - step)) / 2e-5, abs=1e-6)
    assert kl(now.theta) >= 0 and abs(kl(old.theta)) < 1e-12


def test_training_improves(spark):
    qs = spark.createDataFrame([(q, f"L{q % 2}") for q in range(40)], "question_id long, family string")
    kinds = {"exact": 4.0, "slow": 3.4, "value": 0.0, "no_fence": -2.0}
    cube = spark.createDataFrame([(q, k, v, v > 3, 5, 9) for q in range(40) for k, v in kinds.items()], "question_id long, kind string, total double, ex boolean, n_tok_in int, n_tok_out int")
    start = grouprl.Policy.initial(["L0", "L1"], list(kinds))
    a, b, c = (grouprl.train(qs.repartition(n), cube.repartition(2 * n), start, steps=5, group=4, every=5) for n in (1, 4, 8))
    assert a.trace == b.trace == c.trace and (a.policy.theta == c.policy.theta).all() and a.trace[-1][1] > a.trace[0][1] and set(a.snapshots) == {5}
    fitted = grouprl.fit_mle(qs.withColumn("kind", F.lit("exact")), start)
    assert fitted.probs()[:, 0].min() > 0.7


def test_distillation(spark):
    rows = [(1, 0, a, c) for a, c in enumerate([1, 1, 0, 1, 1, 1, 1])] + [(2, 0, a, c) for a, c in enumerate([1, 1, 0, 1])]
    df = spark.createDataFrame([(q, s, a, bool(c)) for q, s, a, c in rows], "question_id long, snapshot int, attempt int, correct boolean")
    assert [(r.question_id, r.attempt) for r in distill.keep_run(df).collect()] == [(1, 5)]
    assert [r.attempt for r in distill.keep_run(df, take="first").collect()] == [3]
    assert {(r.question_id, r.first, r.length) for r in distill.runs(df).collect()} == {(1, 0, 2), (1, 3, 4), (2, 0, 2), (2, 3, 1)}


def test_measures(spark):
    df = spark.createDataFrame([("b", "q", True, 1.0, 1.0, 10, 10), ("b", "r", False, 1.0, 1.0, 10, 10), ("s", "q", True, 4.0, 1.0, 10, 30), ("s", "r", True, 1.0, 1.0, 10, 30)],
                               "arm string, question_id string, ex boolean, t_gold double, t_pred double, n_tok_in int, n_tok_out int")
    by = lambda d, v: {r.arm: r[v] for r in d.collect()}
    assert by(metrics.ves(df, ["arm"]), "ves") == {"b": 0.5, "s": 1.5} and by(metrics.ves(df, ["arm"], "capped"), "ves") == {"b": 0.5, "s": 1.0}
    assert by(metrics.pgr(metrics.ex(df, ["arm"]), "b", "s", []), "pgr") == {"b": 0.0, "s": 1.0}
    assert by(metrics.pgr(metrics.ex(df, ["arm"]), "b", "b", []), "pgr") == {"b": None, "s": None}
    assert by(metrics.tep(df, "b", []), "tep") == {"b": None, "s": 1.0}


@pytest.fixture(scope="module")
def tables(spark, sf):
    load.views(spark, sf)
    return load.DATABASES["retail"]


@pytest.mark.parametrize(("sql", "status"), [
    ("SELECT COUNT(*) FROM orders", "ok"), ("SELECT o_custkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer) UNION SELECT 1", "ok"), ("WITH a AS (SELECT * FROM orders) SELECT * FROM a", "ok"),
    ("DROP TABLE orders", "blocked"), ("INSERT INTO orders SELECT * FROM orders", "blocked"), ("CREATE VIEW v AS SELECT 1", "blocked"), ("SELECT * FROM parquet.`/etc/x`", "blocked"),
    ("SELECT * FROM documents", "blocked"), ("SELECT (SELECT COUNT(*) FROM pages) FROM orders", "blocked"), ("SELECT * FROM range(10)", "blocked"), ("SELECT n FORM orders WHERE", "parse_error"), ("SELECT 1; SELECT 2", "parse_error"), ("", "parse_error"), (None, "parse_error")])
def test_guard(spark, tables, sql, status):
    assert execution.guard(spark, sql, tables) == status


def test_execution(spark, tables):
    run = lambda q, **k: execution.run_one(spark, q, tables, repeats=0, **k)[0]
    assert run("SELECT nothing FROM orders") == "analysis_error" and run("SELECT CAST(o_orderstatus AS INT) FROM orders") == "runtime_error"
    assert run("SELECT SUM(a.l_tax * b.l_tax * c.l_tax) FROM lineitem a CROSS JOIN lineitem b CROSS JOIN lineitem c", limit_s=2.0) == "timeout"
    status, times, mean, n, *_ = execution.run_one(spark, "SELECT o_orderkey FROM orders", tables, execution.STATIC, 0, 2)
    assert status == "ok" and len(times) == 2 and mean > 0 and n == 1500 and spark.conf.get("spark.sql.adaptive.enabled") == "true"


def test_execution_runs_past_a_page(spark, tables):
    texts = spark.createDataFrame([(f"SELECT {i} AS a FROM region",) for i in range(5)] + [(None,)], "sql string")
    rows = execution.run(spark, texts, tables, warmup=0, repeats=0, page=2).collect()
    assert {r.status for r in rows} == {"ok"} and len(rows) == 5
    assert execution.run(spark, texts.limit(0), tables).count() == 0


def test_costs_and_load(spark, tables):
    texts = spark.createDataFrame([(f"SELECT o_custkey + {i}, COUNT(*) FROM orders GROUP BY o_custkey",) for i in range(4)] + [("SELECT nothing FROM orders",)], "sql string")
    rows = {r.sql: r for r in execution.run(spark, texts, tables, execution.SORTING, repeats=1, concurrency=3).collect()}
    assert [rows[t].status for t in sorted(rows)].count("ok") == 4 and len(rows) == 5
    one = execution.run_one(spark, "SELECT o_custkey, COUNT(*) FROM orders GROUP BY o_custkey", tables, execution.ADAPTIVE, 0, 1, costs=True)
    assert len(one) == 9 + len(execution.COSTS) and one[-1] > 0 and one[8 + execution.COSTS.index("shuffled")] > 0
    assert execution.run_one(spark, "SELECT 1 FROM nowhere", tables, costs=True)[-1] is None


def test_guard_by_function(spark, tables):
    assert execution.guard(spark, "SELECT SUM(o_totalprice) FROM orders", tables, ("sum",)) == "ok"
    assert execution.guard(spark, "SELECT SUM(ABS(o_totalprice)) FROM orders", tables, ("sum",)) == "blocked"


def test_fingerprints(spark, tables):
    same = [("SELECT COUNT(*) AS a FROM orders", "SELECT SUM(1) FROM orders"), ("SELECT o_custkey, o_orderkey FROM orders", "SELECT o_custkey x, o_orderkey FROM orders ORDER BY 2 DESC")]
    for a, b in same:
        assert execution.equal(spark, a, b) and execution.equal_exactly(spark.sql(a), spark.sql(b))
    for a, b in [("SELECT o_custkey FROM orders", "SELECT DISTINCT o_custkey FROM orders"), ("SELECT 1", "SELECT 1, 1"), ("SELECT NULL", "SELECT ''")]:
        assert not execution.equal(spark, a, b)
    assert execution.equal(spark, "SELECT o_custkey FROM orders", "SELECT DISTINCT o_custkey FROM orders", "set")


def test_plan_cost_sees_redundant_joins(spark, tables):
    gold = "SELECT COUNT(*) FROM orders WHERE o_totalprice > 5"
    assert planlevel.ratio(spark, gold, gold) == 1.0
    assert planlevel.ratio(spark, gold, gold + " AND o_orderkey IN (SELECT o_orderkey FROM orders)") < 1.0


def test_linking(spark):
    df = spark.createDataFrame([(1, ["a", "a.x"], ["a", "a.x", "a.y"]), (2, [], ["a"]), (3, ["a", "b"], ["a"]), (4, None, None)], "id int, p array<string>, g array<string>")
    got = {r.id: (r.link_set_ok, r.link_equal) for r in linking.score(df, "p", "g").collect()}
    assert got == {1: (True, False), 2: (True, False), 3: (False, False), 4: (True, True)}


def test_dedup_keeps_null_texts(spark):
    df = spark.createDataFrame([(1, None), (2, None), (3, "a"), (4, " A"), (5, "b"), (5, "b"), (None, "c"), (None, "c")], "doc_id long, text string")
    ids = lambda how: sorted((r.doc_id is None, r.doc_id or 0) for r in dataset.dedup(df, how).collect())
    assert ids("exact") == [(False, 1), (False, 3), (False, 4), (False, 5), (True, 0)] and ids("normalised") == [(False, 1), (False, 3), (False, 5), (True, 0)]


def test_grams_are_those_of_the_words(spark):
    rng = np.random.default_rng(3)
    texts = [" ".join(rng.choice(list("ab"), n)) for n in (0, 1, 3, 7, 8, 9, 40, 60)] + ["A  b\ta"]
    df = spark.createDataFrame(list(enumerate(texts)), "i int, t string")
    for n in (1, 3, 5, 8):
        for r in df.select("t", F.size(dataset.grams(F.col("t"), n)).alias("k")).collect():
            w = r.t.lower().split()
            assert r.k == len({tuple(w[i : i + n]) for i in range(len(w) - n + 1)})


def test_value_hints(spark):
    df = spark.createDataFrame([(str(i % (7 + i % 3)),) for i in range(400)], "v string")
    counts = sorted(((-n, v) for v, n in __import__("collections").Counter(r.v for r in df.collect()).items()))[:3]
    assert [(r.value, r.n) for r in dataset.value_hints(df, ["v"]).orderBy("place").collect()] == [(v, -n) for n, v in counts]


def test_several_objectives(spark):
    base = (True, True, 1.0, "ok", True, 1.0, 2.0, True, True, 1, 1.0, 0.0)
    df = spark.createDataFrame([(*base, 4, 8), (*base, 0, 0), (*base, 9, 3), (*base[:4], False, *base[5:], 1, 1)], LEAF + ", gold_shuffled long, shuffled long")
    assert [r.eff for r in reward.several(df, {"t": 1.0, "shuffled": 3.0}).collect()] == [0.125 + 0.375, 0.125 + 0.75, 0.125 + 0.75, 0.0]


def test_preferences(spark):
    rows = lambda ks: spark.createDataFrame([(q, "L1", s, k) for q, s, k in ks], "question_id long, family string, slot int, kind string")
    right = spark.createDataFrame([(q, k, k == "a") for q in (1, 2) for k in "abc"], "question_id long, kind string, correct boolean")
    got = baselines.preferred(rows([(1, 0, "b"), (1, 1, "a"), (2, 0, "b")]), rows([(1, 0, "a"), (1, 1, "c"), (1, 2, "b"), (2, 0, "c")]), right).collect()
    assert [(r.question_id, r.chosen, r.rejected) for r in got] == [(1, "a", "c")]


def test_dataset(spark, sf):
    docs = load.table(spark, sf, "documents")
    assert dataset.dedup(docs).count() == docs.select("text").distinct().count()
    a, b = (r.doc_id for r in [dataset.shuffle(docs, 1).first(), dataset.shuffle(docs.repartition(5), 1).first()])
    assert a == b
    left = dataset.decontaminate(docs, load.table(spark, sf, "benchmark"))
    assert left.count() + dataset.contaminated(docs, load.table(spark, sf, "benchmark")).select("doc_id").distinct().join(docs, "doc_id").count() == docs.count()


def _vectors(spark, n):
    v = np.random.default_rng(4).normal(size=(n, 64)).astype(np.float32)
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    return v, spark.createDataFrame([(i, x) for i, x in enumerate(v.tolist())], "vec_id long, embedding array<float>")


def _best(v, k):
    s = np.round(v.astype(float) @ v.T.astype(float), 6)
    np.fill_diagonal(s, -2.0)
    return {(i, r + 1, int(j)) for i, x in enumerate(s) for r, j in enumerate(np.lexsort((np.arange(len(v)), -x))[:k])}


def test_nearest_is_exact_beyond_a_block(spark, monkeypatch):
    monkeypatch.setattr(baselines, "POOL_MOST", 100, raising=False)
    monkeypatch.setattr(baselines, "BLOCK", 64, raising=False)
    v, df = _vectors(spark, 600)
    assert {(r.vec_id, r.place, r.neighbour) for r in baselines.nearest_examples(df, df, 3).collect()} == _best(v, 3)
    assert baselines.nearest_examples(df.limit(0), df, 3).count() == 0 and baselines.nearest_examples(df, df.limit(3), 3).where("vec_id = neighbour").count() == 0


def test_planes_find_nine_of_ten(spark):
    v, df = _vectors(spark, 2_000)
    got = {(r.vec_id, r.neighbour) for r in baselines.nearest_by_planes(df, df, 3, 6, 9).collect()}
    want = {(q, j) for q, _, j in _best(v, 3)}
    assert len(got) == 6_000 and len(got & want) >= 0.9 * len(want)


def test_neighbours_are_alike_in_text(spark):
    asked = ["how many orders are there in year", "list the names of suppliers from nation", "average price of parts of brand"]
    df = spark.createDataFrame([(i, f"{asked[i % 3]} {i}", f"S{i % 3}", f"q{i}") for i in range(30)], "question_id long, question string, skeleton string, gold_sql string")
    near = baselines.nearest_by_text(df, "question", 3)
    rows = near.collect()
    assert len(rows) == 90 and all(r.question_id != r.neighbour and r.question_id % 3 == r.neighbour % 3 for r in rows)
    assert all(r.skeleton == f"S{r.question_id % 3}" and r.sql != f"q{r.question_id}" for r in baselines.skeleton_then_fill(near, df).collect())


def test_tree_search_goes_clause_by_clause(spark):
    kinds, paths = list("abcde"), [["t", "x", "p"], ["t", "x", "q"], ["t", "y", "p"], ["u", "y", "p"], ["u", "z", "q"]]
    for c in (0.0, 1.0):
        assert baselines.searched(kinds, paths, [0.0, 1.0, -2.0, 3.0, 4.0], 40, c)[2] >= 2
    assert baselines.searched(kinds, paths, [0.0, 1.0, -2.0, 3.0, 4.0], 40, 1.0)[:2] == ("e", 4.0) and baselines.searched(kinds, paths, [0.0, 1.0, -2.0, 3.0, 4.0], 200, 9.0)[2] == 5
    assert baselines.searched(["a"], [["t"]], [1.5], 3, 1.0) == ("a", 1.5, 1)
    few = baselines.searched([f"k{i}" for i in range(20)], [[f"t{i // 5}", f"w{i}"] for i in range(20)], [4.0 if i // 5 == 2 else -2.0 for i in range(20)], 8, 0.5)
    assert few[1] == 4.0 and few[2] < 20
    cube = spark.createDataFrame([(q, "A01", k, t) for q in range(5) for k, t in (("exact", 3.5), ("value", 0.0), ("syntax_error", -2.0), ("slow", None))], "question_id long, family string, kind string, total double")
    got = baselines.tree_search(cube, baselines.clause_paths(spark)).collect()
    assert {(r.kind, r.total) for r in got} == {("exact", 3.5)} and len(got) == 5


def test_streams_equal_batches(spark, sf):
    events, path = load.table(spark, sf, "events"), f"{sf}/events.parque[t]"
    close = lambda df: sorted(tuple(round(x, 6) if isinstance(x, float) and not math.isnan(x) else x for x in r) for r in df.fillna(-1).collect())
    hour = lambda df: jobs.closed(events, df, F.col("start") + F.expr("INTERVAL 1 HOUR"))
    for job, want in ((jobs.tumbling, hour), (jobs.sliding, hour), (jobs.sessions, lambda df: jobs.closed(events, df, F.col("end"))), (jobs.runs_of_three, None), (jobs.deduplicated, lambda df: df), (jobs.bought_after_signup, lambda df: df)):
        folder = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
        got = jobs.drained(spark, job(jobs.source(spark, path)), folder)
        rows = close(got)
        assert rows == close(jobs.runs_of_three_batch(events) if want is None else want(job(events))) and rows
        assert close(jobs.drained(spark, job(jobs.source(spark, path)), folder)) == rows  # nothing new, nothing twice


def test_late_rows(spark):
    from datetime import datetime, timedelta

    hours = [0, 50, 10, 51, 26, 90, 65, 67, 200, 100]
    df = spark.createDataFrame([(i, datetime(2024, 1, 1) + timedelta(hours=h)) for i, h in enumerate(hours)], "event_id long, ts timestamp")
    want = sum(any(x > h + 24 for x in hours[:i]) for i, h in enumerate(hours))
    assert {jobs.late_rows(df, span=s).first().late for s in (2, 3, 100)} == {want} and jobs.late_rows(df.limit(0)).first().n == 0


def test_sql_surface(spark):
    from sqltutor import surface

    surface.register(spark)
    r = spark.sql("SELECT reward_of(true, 0.9D, true, false, 0.5D) AS a, reward_of(true, 0.5D, true, true, 1D) AS b, hybrid_similarity('A B', 'A B') AS c").first()
    assert (r.a, r.b, r.c) == (3.5, -2.0, 1.0)
    assert spark.sql("SELECT count(*) AS n FROM sql_tokens('SELECT a FROM t')").first().n == 4
    assert {x.clause for x in spark.sql("SELECT * FROM clause_items('SELECT a FROM t WHERE b = 1')").collect()} == {"select", "from", "where"}
