"""Experiments against plain loops over their rows, and outcomes against runs of their own."""

import math
import random
from collections import Counter, defaultdict

import pytest

from sqltutor import workloads
from sqltutor.operators import grouprl, mutate, replay, reward
from sqltutor.plans import execution
from sqltutor.sources import load

mean = lambda xs: sum(xs) / len(xs)
near = lambda a, b: a is None and b is None or a is not None and b is not None and math.isclose(a, b, rel_tol=1e-9, abs_tol=1e-9)
EVERY = (*workloads.ARMS, *workloads.BASELINES)


@pytest.fixture(scope="module")
def rows(spark, sf):
    return [r.asDict() for r in workloads.evaluated(spark, sf, EVERY).collect()]


@pytest.fixture(scope="module")
def cands(spark, sf):
    return [r.asDict() for r in workloads.prepared(spark, sf).collect()]


def grouped(rows, *keys):
    out = defaultdict(list)
    for r in rows:
        out[tuple(r[k] for k in keys)].append(r)
    return out


def one_engine(rows, **equal):
    return [r for r in rows if r["engine"] == "adaptive" and all(r[k] in v for k, v in equal.items())]


def run(spark, sf, wid, *keys):
    got = workloads.run(wid, spark, sf).collect()
    out = {tuple(r[k] for k in keys): r for r in got}
    assert len(out) == len(got) > 0
    return out


def factor(r):
    return math.sqrt(r["t_gold"] / r["t_pred"]) if r["ex"] else 0.0


def test_each_arm_answers_each_question_on_each_engine(spark, sf, rows):
    asked = workloads.asked(spark, sf).count()
    assert Counter(r["arm"] for r in rows) == dict.fromkeys(EVERY, 2 * asked)
    assert len({(r["arm"], r["question_id"], r["engine"]) for r in rows}) == len(rows)
    assert all(r["t_pred"] > 0 and r["t_gold"] > 0 for r in rows if r["ex"])


def test_accuracy_and_elasticity(spark, sf, rows):
    by = grouped(one_engine(rows), "arm", "suite")
    ex = {k: mean([bool(r["ex"]) for r in v]) for k, v in by.items()}
    tokens = {k: mean([r["n_tok_in"] + r["n_tok_out"] for r in v]) for k, v in by.items()}
    w3, w4 = run(spark, sf, "w3", "arm", "suite"), run(spark, sf, "w4", "arm", "suite")
    assert set(w3) == set(w4) == set(by)
    for (arm, suite), r in w3.items():
        base, full = ex["base", suite], ex["full", suite]
        assert near(r["em"], mean([bool(x["em"]) for x in by[arm, suite]]))
        assert near(r["pgr"], (ex[arm, suite] - base) / (full - base) if full != base else None)
        gain, spent = (ex[arm, suite] - base) / base if base else None, tokens[arm, suite] / tokens["base", suite] - 1
        assert near(r["gain"], gain) and near(r["spent"], spent) and near(r["tep"], gain / spent if gain is not None and spent else None)
        assert near(w4[arm, suite]["ex"], ex[arm, suite])
        for other in ("base", "sft"):
            assert near(w4[arm, suite][f"over_{other}"], 100 * (ex[arm, suite] / ex[other, suite] - 1) if ex[other, suite] else None)


def test_efficiency_on_two_engines(spark, sf, rows):
    per = {k: mean(list(map(factor, v))) for k, v in grouped(rows, "arm", "suite", "engine").items()}
    both = {(a, s): mean([per[a, s, e] for e in ("adaptive", "static")]) for a, s, _ in per}
    for k, r in run(spark, sf, "w6", "arm", "suite").items():
        assert near(r["ves"], both[k]) and near(r["over_base"], 100 * (both[k] / both["base", k[1]] - 1) if both["base", k[1]] else None)
    place = lambda s, e: {a: 1 + sum(per[b, s, e] > per[a, s, e] for b in workloads.ARMS) for a in workloads.ARMS}
    for (suite,), r in run(spark, sf, "w16", "suite").items():
        x, y = ([place(suite, e)[a] for a in workloads.ARMS] for e in ("adaptive", "static"))
        dx, dy = [v - mean(x) for v in x], [v - mean(y) for v in y]
        assert near(r["spearman"], sum(p * q for p, q in zip(dx, dy, strict=True)) / math.sqrt(sum(p * p for p in dx) * sum(q * q for q in dy)))


def test_similarity_and_tiers(spark, sf, rows):
    some = one_engine(rows, suite=("A", "B"), arm=workloads.ARMS)
    by = grouped(some, "arm", "suite")
    for (arm, suite, x), r in run(spark, sf, "w5", "arm", "suite", "x").items():
        known = [v["jac"] for v in by[arm, suite] if v["jac"] is not None]
        assert near(r["share"], mean([j <= x for j in known]))
    for wid, value in (("w7", lambda r: float(bool(r["ex"]))), ("w8", lambda r: r["jac"]), ("w9", factor)):
        cells = grouped(some, "arm", "tier")
        for (arm,), r in run(spark, sf, wid, "arm").items():
            for tier in workloads.TIERS["A"] + workloads.TIERS["B"]:
                assert near(r[tier], mean([value(x) for x in cells[arm, tier] if value(x) is not None]) if (arm, tier) in cells else None)


def test_errors(spark, sf, rows):
    counts = Counter((r["arm"], r["suite"], r["error"]) for r in one_engine(rows, arm=workloads.ARMS) if r["error"])
    for (arm, suite, error), r in run(spark, sf, "w10", "arm", "suite", "error").items():
        base = counts["base", suite, error]
        assert (r["n"], r["n_base"]) == (counts[arm, suite, error], base) and near(r["reduction"], 100 * (base - r["n"]) / base)
    coarse = Counter(("schema linking" if e in ("table", "attribute") else "condition" if e in ("condition", "value") else "structural") for (a, s, e), n in counts.items() if (a, s) == ("base", "A") for _ in range(n))
    got = run(spark, sf, "w11", "class")
    assert {k: r["n"] for (k,), r in got.items()} == coarse and math.isclose(sum(r["share"] for r in got.values()), 1.0)


def test_generalisation(spark, sf, rows):
    by = grouped(one_engine(rows, suite=("C",), arm=workloads.ARMS), "arm")
    for (arm,), r in run(spark, sf, "w19", "arm").items():
        assert near(r["ex"], mean([bool(x["ex"]) for x in by[arm,]])) and near(r["em"], mean([bool(x["em"]) for x in by[arm,]]))
    assert not workloads.training_questions(spark, sf).where("suite = 'C'").count()


def test_rewards_of_all_arms(cands, spark, sf):
    """The staged reward, leaf by leaf, for every candidate and arm."""
    got = {(r.arm, r.question_id, r.kind): r.total for r in reward.score_arms(workloads.prepared(spark, sf)).collect()}
    for arm, spec in reward.ARMS.items():
        for c in cands:
            form = c["pattern_ok"] and (not spec.skeleton or (c["sim"] or 0) >= 0.6)
            if not form:
                want = -2.0
            elif c["status"] == "ok" and c["equal"] and c["t_pred"] <= 30:
                want = 3.0 + (min(1.0, c["t_gold"] / c["t_pred"]) if spec.efficiency else 0.0)
            else:
                want = 0.0 if c["link_set_ok"] else -1.5
            assert near(got[arm, c["question_id"], c["kind"]], want), (arm, c["kind"], c["family"])


def test_gate_and_modes(spark, sf, cands):
    right = [c for c in cands if c["pattern_ok"]]
    for (suite,), r in run(spark, sf, "w21", "suite").items():
        here = [c for c in right if c["suite"] == suite]
        failed = [c for c in here if not c["sim"] >= 0.6]
        assert r["texts"] == len({c["sql"] for c in here}) and r["avoided"] == len({c["sql"] for c in failed})
        assert r["right_rejected"] == sum(c["equal"] for c in failed) and r["wrong_passed"] == sum(not c["equal"] for c in here if c["sim"] >= 0.6)
    for (alpha, tau), r in run(spark, sf, "w17", "alpha", "tau").items():
        passed = [c for c in right if alpha * c["ratio"] + (1 - alpha) * c["jac"] >= tau]
        assert (r["n"], r["passed"]) == (len(right), len(passed))
        assert near(r["precision"], mean([c["equal"] for c in passed]) if passed else None) and near(r["recall"], sum(c["equal"] for c in passed) / sum(c["equal"] for c in right))
    for (mode,), r in run(spark, sf, "w22", "mode").items():
        here = [c for c in cands if c["mode"] == mode]
        assert near(r["valid"], mean([c["pattern_ok"] for c in here])) and near(r["tokens_out"], mean([c["n_tok_out"] for c in here])) and r["n"] == len(here)


def test_readings_and_traces(spark, sf, cands):
    flips = run(spark, sf, "w20", "reading")
    assert set(flips) == {(r,) for r in reward.READINGS} and flips["default",]["flips"] == 0 and flips["ran",]["flips"] > 0
    runs = workloads.trained(spark, sf)
    for wid, at in (("w12", (1, 2)), ("w13", (3,))):
        for (arm, step), r in run(spark, sf, wid, "arm", "step").items():
            assert tuple(r)[2:] == tuple(runs[arm].trace[step][i] for i in at)
    assert all(r.trace[-1][1] > r.trace[0][1] for a, r in runs.items() if r.trace)


def test_distillation_yields(spark, sf, cands):
    known = {(c["question_id"], c["kind"]): c for c in cands}
    teachers = {0: workloads.start_policy(), **workloads.trained(spark, sf)["full"].snapshots}
    qs = workloads.training_questions(spark, sf).select("question_id", "family")
    last = {}
    got = run(spark, sf, "w15", "snapshot")
    for s, teacher in teachers.items():
        tried = defaultdict(dict)
        for r in teacher.sample(qs, 6, 11, s).collect():
            tried[r.question_id][r.slot] = known[r.question_id, r.kind]
        good = lambda c: bool(c["pattern_ok"] and c["equal"])
        text = lambda x: " ".join(x.replace(";", " ").lower().split())
        runs = {q for q, a in tried.items() if any(all(good(a[i + k]) for k in range(3)) for i in range(4))}
        assert got[s,]["asked"] == len(tried) and got[s,]["run_of_three"] == len(runs)
        assert got[s,]["exact"] == sum(any(text(c["sql"]) == text(c["gold_sql"]) for c in a.values()) for a in tried.values())
        assert got[s,]["same_rows"] == sum(any(c["equal"] for c in a.values()) for a in tried.values())
        for q in runs:
            last[q] = max(s, last.get(q, s))
    assert {s: r["progressive"] for (s,), r in got.items()} == {s: sum(v == s for v in last.values()) for s in teachers}


def test_outcomes_are_those_of_runs(spark, sf):
    """A fifth of all texts run once more."""
    load.views(spark, sf)
    rng, known = random.Random(3), {(r.family, r.kind): r for r in workloads.executions(spark, sf).where("engine = 'adaptive'").collect()}
    some = [r for r in replay.texts(spark).collect() if r.kind != "timeout" and "LIMIT" not in r.sql and rng.random() < 0.2]
    assert len(known) == 36 * len(mutate.KINDS)
    for r in some:
        tables = load.DATABASES[r.db_id]
        pred, gold = (execution.run_one(spark, s, tables, repeats=0) for s in (r.sql, r.gold_sql))
        x = known[r.family, r.kind]
        assert (x.status, x.equal) == (pred[0], pred[0] == "ok" and pred[3:7] == gold[3:7]), (r.family, r.kind)
    assert {r.status for (_, k), r in known.items() if k == "timeout"} == {"timeout"}
    assert all(r.equal and r.status == "ok" for (_, k), r in known.items() if k in ("exact", "equivalent", "slow", "fast"))
    assert all(0 <= r.overlap < 1 for r in known.values() if r.overlap is not None)


def test_supervised_and_chosen_arms(spark, sf, rows):
    by = {a: mean([bool(r["ex"]) for r in v]) for (a,), v in grouped(one_engine(rows), "arm").items()}
    assert by["sft"] > by["base"] and by["feedback"] > by["base"] and by["best_of_n"] > by["base"] and by["majority"] >= by["base"] and by["tree_search"] > by["base"]
    routed = grouped(one_engine(rows, arm=("base", "full", "router")), "question_id", "arm")
    for (q, arm), (r,) in routed.items():
        if arm == "router":
            assert r["kind"] == routed[q, "base" if workloads.LEVEL[r["tier"]] == "L1" else "full"][0]["kind"]


def test_the_method_leads(spark, sf, rows):
    """What the reference reports of its own arms, as far as a tabular policy can show it."""
    ex = {a: mean([bool(r["ex"]) for r in v]) for (a,), v in grouped(one_engine(rows), "arm").items()}
    assert ex["full"] >= max(ex[a] for a in workloads.ARMS) - 0.02 and all(ex[a] > ex["base"] for a in workloads.ARMS if a != "base")
    spread = {arm: [t[2] for t in workloads.trained(spark, sf)[arm].trace] for arm in ("full", "skeleton_efficiency")}
    assert mean(spread["full"]) < mean(spread["skeleton_efficiency"])


def test_tempered_policies():
    p = workloads.start_policy()
    top = lambda q: q.probs().max(axis=1).min()
    assert top(p.tempered(0.5)) < top(p) < top(p.tempered(1.5)) and isinstance(p, grouprl.Policy)
