"""The paper's experiments, re-run on suites over the given tables with the tabular policy.

``executions`` runs every family's edits for real under both engines with the family's own parameters, ``answered`` those of
every question with the question's; ``prepared`` scores all candidates of all questions
once, ``trained`` trains every arm and baseline once; all are kept per session and data folder. Each is made of parts that
are kept for themselves, and an experiment asks for the parts that its result depends on: ``need`` is "rows" (status and
equality), "shared" (and shared rows of wrong answers), "times" (rows, and what runs took) or "all", ``text`` a level of ``TEXT``, ``suites``
and ``kinds`` whose runs count, ``only`` the candidates that do. Training depends on its own questions and so on two suites,
measures of arms on the texts that these answered with. Results are this library's own and say nothing about a language
model's accuracy; times are measured, so they differ from run to run.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import response
from .functions.similarity import sweep
from .operators import baselines, dataset, distill, grouprl, judging, linking, metrics, mutate, published, replay, reward
from .operators.suites import FAMILIES, questions
from .plans.execution import ADAPTIVE, STATIC, EngineProfile
from .session import reach_workers
from .sources.load import owners
from .sources.load import sql as run_sql
from .store import written

ARMS = ("base", *reward.ARMS)
#: Rewards of rival families, trained with the same loop; supervised fits; choices made when answering.
RIVALS = {"sparse": reward.RewardSpec.sparse(), "clausewise": reward.RewardSpec.clausewise(), "result_overlap": reward.RewardSpec.result_overlap()}
SUPERVISED = ("sft", "feedback", "synthetic")
CHOSEN = ("best_of_n", "majority", "tree_search", "router")
BASELINES = (*RIVALS, *SUPERVISED, *CHOSEN)
TIERS = {"A": ["simple", "moderate", "challenging"], "B": ["easy", "medium", "hard", "extra"]}
LEVEL = {"simple": "L1", "easy": "L1", "moderate": "L2", "medium": "L2", "challenging": "L3", "hard": "L3", "extra": "L3"}
GRID = [x / 10 for x in range(11)]
#: Logits of the untrained policy by kind: about half of its errors are linking errors, then structure, then conditions.
LEAN = {"exact": 2.2, "equivalent": 1.2, "fast": 0.2, "slow": 1.6, "table": 1.3, "attribute": 1.6, "unknown_column": 0.6, "subquery": 0.4, "clause": 0.7, "operator": 0.5, "function": 0.4,
        "condition": 0.6, "value": 0.4, "syntax_error": -0.5, "bad_cast": -0.5, "timeout": -1.5}
_TABLES: dict[tuple[str, str, str], DataFrame] = {}
_RUNS: dict[tuple, dict[str, grouprl.Run]] = {}
STEPS, GROUP, EVERY, SAMPLES = 6, 8, 2, 8
#: What is known of a candidate's text, each level with all before it: its response keeps to its mode; skeletons and their
#: similarity; schema elements; clause matches and error classes.
TEXT = ("form", "sim", "links", "all")
LEARNT = "AB"


def _made(spark: SparkSession, sf_dir: str, name: str) -> bool:
    return (spark.sparkContext.applicationId, sf_dir, name) in _TABLES


def _kept(spark: SparkSession, sf_dir: str, name: str, make) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _TABLES:
        _TABLES[key] = written(spark, make(), name)
    return _TABLES[key]


def asked(spark: SparkSession, sf_dir: str, suites: str = "ABC") -> DataFrame:
    if suites != "ABC" and _made(spark, sf_dir, "questions"):
        return asked(spark, sf_dir).where(F.col("suite").isin(*suites))
    return _kept(spark, sf_dir, "questions" if suites == "ABC" else f"questions-{suites}", lambda: questions(spark, sf_dir, [f.id for f in FAMILIES if f.suite in suites]))


def _parts(spark: SparkSession, sf_dir: str, name, suites: str, make, share) -> DataFrame:
    """The part that ``name`` tells of these suites. Those that lack it are made together, by one ``make``, and each keeps its ``share``."""
    if lacking := "".join(s for s in suites if not _made(spark, sf_dir, name(s))):
        whole = make(lacking)
        for s in lacking:
            _TABLES[spark.sparkContext.applicationId, sf_dir, name(s)] = share(whole, s)
    out = None
    for s in suites:
        one = _kept(spark, sf_dir, name(s), None)
        out = one if out is None else out.unionByName(one)
    return out


def _of_family(rows: DataFrame, suite: str) -> DataFrame:
    return rows.where(F.substring("family", 1, 1) == suite)


def _checked(spark: SparkSession, sf_dir: str, suites: str, profile: EngineProfile, kinds: tuple[str, ...] = mutate.KINDS) -> DataFrame:
    """Every text's run for its status and rows under ``profile``; wrong ones run under the first engine only. A text of two
    suites has a row of each."""
    def make(lacking: str) -> DataFrame:
        first = None if profile == ADAPTIVE else _checked(spark, sf_dir, lacking, ADAPTIVE, kinds).dropDuplicates(["db_id", "sql"])
        return replay.checked(spark, sf_dir, replay.texts(spark, kinds, lacking), profile, first)

    def share(whole: DataFrame, suite: str) -> DataFrame:
        return whole.join(F.broadcast(replay.texts(spark, kinds, suite).select("db_id", "sql").distinct()), ["db_id", "sql"], "left_semi")

    return _parts(spark, sf_dir, lambda s: f"checked-{_named(s, kinds)}-{profile.name}", suites, make, share)


def _named(suite: str, kinds: tuple[str, ...]) -> str:
    return suite if kinds == mutate.KINDS else f"{suite}-{'-'.join(kinds)}"


def executions(spark: SparkSession, sf_dir: str, suites: str = "ABC", profiles: tuple[EngineProfile, ...] = (ADAPTIVE, STATIC), need: str = "all",
               kinds: tuple[str, ...] = mutate.KINDS) -> DataFrame:
    """Outcomes of guarded runs by family, kind and engine: ``status``, ``equal`` and ``fp``; with times, also what the runs took;
    with all, also ``overlap``. Suites that lack a part are run together, and golds are run whatever ``kinds`` are asked for."""
    ran = kinds if "exact" in kinds else ("exact", *kinds)
    if all(_made(spark, sf_dir, f"checked-{s}-{p.name}") for s in suites for p in profiles):
        ran = mutate.KINDS
    out = None

    def plain(some: str, profile: EngineProfile) -> DataFrame:
        return _parts(spark, sf_dir, lambda s: f"rows-{_named(s, ran)}-{profile.name}", some, lambda lacking: compared(lacking, seen(lacking, profile)), _of_family)

    def timed(some: str, profile: EngineProfile) -> DataFrame:
        return _parts(spark, sf_dir, lambda s: f"times-{_named(s, ran)}-{profile.name}", some, lambda lacking: compared(lacking, replay.clocked(spark, sf_dir, seen(lacking, profile), profile)), _of_family)

    def seen(some: str, profile: EngineProfile) -> DataFrame:
        return _checked(spark, sf_dir, some, profile, ran).dropDuplicates(["db_id", "sql"])

    def compared(some: str, runs: DataFrame) -> DataFrame:
        return replay.compared(replay.texts(spark, ran, some), runs)

    for p in profiles:
        took = "".join(s for s in suites if need in ("times", "all") or _made(spark, sf_dir, f"times-{_named(s, ran)}-{p.name}"))
        for some, rows in ((took, timed), ("".join(s for s in suites if s not in took), plain)):
            if not some:
                continue
            one = rows(some, p)
            one = one.select("family", "kind", "engine", "status", "equal", "fp") if need in ("rows", "shared") else one
            if need in ("shared", "all"):
                shared = _parts(spark, sf_dir, lambda s: f"overlaps-{_named(s, ran)}", some,
                                lambda lacking: written(spark, replay.overlaps(spark, sf_dir, replay.texts(spark, ran, lacking), plain(lacking, ADAPTIVE)), "overlaps"), _of_family)
                one = one.join(F.broadcast(shared), ["family", "kind"], "left")
            out = one if out is None else out.unionByName(one)
    return out if ran == kinds else out.where(F.col("kind").isin(*kinds))


def _ran(spark: SparkSession, sf_dir: str, suites: str, profile: EngineProfile = ADAPTIVE) -> DataFrame:
    """Runs of all questions' texts of these suites for status and rows, as ``_checked``."""
    def wanted(some: str) -> DataFrame:
        return replay.asked_texts(asked(spark, sf_dir, some)).where(F.substring("family", 1, 1).isin(*some))

    def make(lacking: str) -> DataFrame:
        first = None if profile == ADAPTIVE else _ran(spark, sf_dir, lacking).dropDuplicates(["db_id", "sql"])
        return replay.checked(spark, sf_dir, wanted(lacking), profile, first)

    def share(whole: DataFrame, suite: str) -> DataFrame:
        return whole.join(wanted(suite).select("db_id", "sql").distinct(), ["db_id", "sql"], "left_semi")

    return _parts(spark, sf_dir, lambda s: f"ran-{s}-{profile.name}", suites, make, share)


def _clocked(spark: SparkSession, sf_dir: str, seen: DataFrame, texts: DataFrame, profile: EngineProfile) -> DataFrame:
    """``seen`` with times of those ``texts`` that ran and were right; each is timed once a session."""
    app, tag, on = spark.sparkContext.applicationId, f"clocked-{profile.name}-", ["db_id", "sql"]
    have = [df for (a, d, name), df in _TABLES.items() if (a, d) == (app, sf_dir) and name.startswith(tag)]
    todo = seen.where("right AND status = 'ok'").join(texts, on, "left_semi")
    for one in have:
        todo = todo.join(one, on, "left_anti")
    have.append(_kept(spark, sf_dir, f"{tag}{len(have)}", lambda: replay.clocked(spark, sf_dir, todo, profile)))
    for one in have:
        one = one.join(seen, on, "left_semi")
        seen = seen.join(one, on, "left_anti").unionByName(one)
    return seen


def answered(spark: SparkSession, sf_dir: str, suites: str = "ABC", profiles: tuple[EngineProfile, ...] = (ADAPTIVE,), need: str = "all",
             only: tuple[str, DataFrame] | None = None) -> DataFrame:
    """Outcomes as those of ``executions``, but by question, kind and engine: every question's texts run with its own parameters.
    ``only`` as in ``scored``; nothing else is timed or compared row by row."""
    def make() -> DataFrame:
        wanted = _among(replay.asked_texts(asked(spark, sf_dir, suites)).where(F.substring("family", 1, 1).isin(*suites)), only)
        out = None
        for p in profiles:
            runs = _ran(spark, sf_dir, suites, p).dropDuplicates(["db_id", "sql"])
            if need in ("times", "all"):
                texts = wanted.select("db_id", "sql").union(wanted.select("db_id", "gold_sql")).distinct()
                runs = _clocked(spark, sf_dir, runs, texts, p)
            one = replay.compared(wanted, runs)
            out = one if out is None else out.unionByName(one)
        if need in ("shared", "all"):
            golds = replay.asked_texts(asked(spark, sf_dir, suites)).where("kind = 'exact'").join(wanted.select("question_id").distinct(), "question_id", "left_semi")
            both = wanted.unionByName(golds).dropDuplicates(["question_id", "kind"])
            rows = replay.compared(both, _ran(spark, sf_dir, suites).dropDuplicates(["db_id", "sql"]))
            out = out.join(replay.overlaps(spark, sf_dir, both, rows), ["question_id", "kind"], "left")
        return out

    return _kept(spark, sf_dir, f"answered-{suites}-{need}-{'-'.join(p.name for p in profiles)}-{only[0] if only else ''}", make)


def scored(spark: SparkSession, sf_dir: str, suites: str = "ABC", text: str = "all", only: tuple[str, DataFrame] | None = None) -> DataFrame:
    """Candidates of these suites with what their texts tell, up to the level ``text``. ``only``: a name and the questions, or
    questions and kinds, that matter."""
    reach_workers(spark)
    where = suites if only is None else f"{suites}-{only[0]}"
    name = lambda level: f"scored-{level}-{where}"
    for level in TEXT[TEXT.index(text):]:
        if _made(spark, sf_dir, name(level)):
            return _kept(spark, sf_dir, name(level), None)
        for whole in (x for x in (suites, "ABC") if _made(spark, sf_dir, f"scored-{level}-{x}")):
            return _among(_kept(spark, sf_dir, f"scored-{level}-{whole}", None).where(F.col("suite").isin(*suites)), only)

    def cands() -> DataFrame:
        parts = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))  # texts are short, the work on them is not
        rows = asked(spark, sf_dir, suites).where(F.col("suite").isin(*suites))
        if only is not None:
            rows = _among(rows, (only[0], only[1].select("question_id")))
        return _among(mutate.candidates(rows), only).repartition(parts, "question_id", "slot")

    def make() -> DataFrame:
        # each step joins its input with scores of that input's distinct texts; written inputs are computed once
        if text == "form":
            return cands().withColumn("pattern_ok", response.valid_in(F.col("mode"), F.col("response")))
        if text == "sim":
            return reward.assembled(cands())
        if text == "links":
            rows = linking.with_elements(scored(spark, sf_dir, suites, "sim", only), ["sql", "gold_sql"], owners(spark, sf_dir))
            return linking.score(written(spark, rows, "linked"), "sql_elements", "gold_sql_elements")
        return judging.judged(scored(spark, sf_dir, suites, "links", only))

    return _kept(spark, sf_dir, name(text), make)


def _among(rows: DataFrame, only: tuple[str, DataFrame] | None) -> DataFrame:
    if only is None:
        return rows
    on = [c for c in ("question_id", "kind") if c in only[1].columns]
    return rows.join(only[1].select(*on).distinct(), on, "left_semi")


def prepared(spark: SparkSession, sf_dir: str, suites: str = "ABC", need: str = "all", text: str = "all", only=None) -> DataFrame:
    """``scored`` candidates with what their own texts did when they ran under the first engine. Texts are scored while others run,
    as one more user; times are taken afterwards. ``only`` as in ``scored``, or a function that tells it."""
    asked(spark, sf_dir, suites)
    with ThreadPoolExecutor(1) as pool:
        texts = pool.submit(inheritable_thread_target(spark)(lambda: scored(spark, sf_dir, suites, text, only() if callable(only) else only)))
        _ran(spark, sf_dir, suites)
        rows = texts.result()
    rows = replay.replayed(rows, answered(spark, sf_dir, suites, (ADAPTIVE,), need, only() if callable(only) else only))
    return rows.withColumn("error", F.when(F.col("equal"), None).otherwise(F.coalesce("error", F.lit("condition")))) if text == "all" else rows


def _level() -> F.Column:
    out = F.lit("L3")
    for t, level in LEVEL.items():
        out = F.when(F.col("tier") == t, level).otherwise(out)
    return out


def training_questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suite A and 15 % of suite B; suite C is never trained on. The policy's class is the level of difficulty."""
    mixed = dataset.mix(asked(spark, sf_dir, LEARNT), {"A": 1.0, "B": 0.15})
    return _kept(spark, sf_dir, "train", lambda: mixed.withColumn("family", _level()))


def start_policy() -> grouprl.Policy:
    return grouprl.Policy.initial(sorted(set(LEVEL.values())), list(mutate.KINDS), {k: LEAN.get(k, -1.0) for k in mutate.KINDS})


def rehearsed(spark: SparkSession, sf_dir: str, need: str, text: str) -> DataFrame:
    """Candidates of the training questions, prepared. Texts begin to run before it is known which questions these are."""
    return prepared(spark, sf_dir, LEARNT, need, text, lambda: ("train", training_questions(spark, sf_dir).select("question_id")))


def _right(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which kinds answer which training question rightly and in the form of their mode."""
    return rehearsed(spark, sf_dir, "rows", "form").select("question_id", "kind", "gold_sql", "sql", F.col("equal").alias("equal"), (F.col("pattern_ok") & F.col("equal")).alias("correct"))


def cold_start(spark: SparkSession, sf_dir: str, teachers: dict[int, grouprl.Policy], k: int = 3, n: int = 6) -> grouprl.Policy:
    """One pass of maximum likelihood of the untrained policy on what its teachers, checkpoints of an earlier run, got right
    ``k`` times in a row: one record a question, the latest teacher's."""
    qs = training_questions(spark, sf_dir)
    tried = distill.attempts(qs.select("question_id", "family"), teachers, n).join(_right(spark, sf_dir).select("question_id", "kind", "correct"), ["question_id", "kind"])
    return grouprl.fit_mle(distill.progressive(distill.keep_run(tried, k)), start_policy())


def supervised(spark: SparkSession, sf_dir: str) -> dict[str, grouprl.Policy]:
    """Fits without reward training: on gold answers, on sampled answers that ran and were right, and on answers that a
    strong generator got right where a weak one went wrong."""
    right, start = _right(spark, sf_dir), start_policy()
    qs = training_questions(spark, sf_dir).select("question_id", "family")
    tried = start.sample(qs, SAMPLES, 5).join(right.where("correct").select("question_id", "kind"), ["question_id", "kind"])
    strong, weak = start.tempered(1.5), start.tempered(0.5)
    pairs = baselines.preferred(strong.sample(qs, SAMPLES, 6), weak.sample(qs, SAMPLES, 7), right.select("question_id", "kind", "correct"))
    return {"sft": grouprl.fit_mle(qs.withColumn("kind", F.lit("exact")), start), "feedback": grouprl.fit_mle(tried, start),
            "synthetic": grouprl.fit_mle(pairs.select("question_id", "family", F.col("chosen").alias("kind")), start)}


def trained(spark: SparkSession, sf_dir: str, steps: int = STEPS, group: int = GROUP, arms: tuple[str, ...] | None = None) -> dict[str, grouprl.Run]:
    """Arms and baselines that have a policy, all of them unless ``arms`` names some. The last arm starts from what checkpoints
    of the arm with the same reward taught; its steps are the same. Arms that don't depend on one another train side by side."""
    runs = _RUNS.setdefault((spark.sparkContext.applicationId, sf_dir, steps, group), {})
    specs = {**reward.ARMS, **RIVALS}
    wanted = ["base", *specs, *SUPERVISED] if arms is None else [a for a in ("base", *specs, *SUPERVISED) if a in arms]
    if "base" in wanted and "base" not in runs:
        runs["base"] = grouprl.Run(start_policy())
    todo = [a for a in specs if a not in runs and (a in wanted or a == "skeleton_efficiency" and any(w in specs and specs[w].cold_start for w in wanted))]
    if todo:
        rows = rehearsed(spark, sf_dir, "all" if "result_overlap" in todo else "times", "all" if "clausewise" in todo else "links")
        qs = training_questions(spark, sf_dir)

        def learn(arm: str, start: grouprl.Policy) -> grouprl.Run:
            cube = _kept(spark, sf_dir, f"cube-{arm}", lambda: grouprl.reward_cube(reward.score(rows, specs[arm])))
            return grouprl.train(qs, cube, start, steps=steps, group=group, every=EVERY)

        with ThreadPoolExecutor(len(todo)) as pool:
            going = {}
            for arm in sorted(todo, key=lambda a: a != "skeleton_efficiency"):  # another arm waits for this one
                if not specs[arm].cold_start:
                    going[arm] = pool.submit(inheritable_thread_target(spark)(learn), arm, start_policy())
            for arm in (a for a in todo if specs[a].cold_start):
                if "skeleton_efficiency" in going:
                    runs["skeleton_efficiency"] = going["skeleton_efficiency"].result()
                first = cold_start(spark, sf_dir, runs["skeleton_efficiency"].snapshots)
                going[arm] = pool.submit(inheritable_thread_target(spark)(learn), arm, first)
            runs |= {arm: run.result() for arm, run in going.items()}
    if any(a in SUPERVISED and a not in runs for a in wanted):
        runs |= {arm: grouprl.Run(p) for arm, p in supervised(spark, sf_dir).items()}
    return {a: runs[a] for a in wanted}


def answers(spark: SparkSession, sf_dir: str, arms: tuple[str, ...] = (*ARMS, *BASELINES), suites: str = "ABC") -> DataFrame:
    """``(question_id, kind, arm)``: each arm's answer to every question of these suites."""
    qs = asked(spark, sf_dir, suites).select("question_id", _level().alias("family"), "tier")

    def own(arm: str, run: grouprl.Run) -> DataFrame:
        return run.policy.sample(qs.select("question_id", "family"), 1, 77).select("question_id", "kind", F.lit(arm).alias("arm"))

    def make() -> DataFrame:
        chosen = [a for a in CHOSEN if a in arms]
        runs = trained(spark, sf_dir, arms=arms)
        parts = [own(arm, run) for arm, run in runs.items()]
        if set(chosen) - {"router"}:
            totals = reward.score(prepared(spark, sf_dir, suites, "times", "links")).select("question_id", "kind", "family", "mode", "total", F.col("fp"))
            tried = start_policy().sample(qs.select("question_id", "family"), SAMPLES, 78).select("question_id", "slot", "kind").join(totals, ["question_id", "kind"])
        if "best_of_n" in chosen:
            parts.append(baselines.best_of_n(tried).select("question_id", "kind", F.lit("best_of_n").alias("arm")))
        if "majority" in chosen:
            parts.append(baselines.majority_by_result(tried).join(tried.select("question_id", "slot", "kind"), ["question_id", "slot"]).select("question_id", "kind", F.lit("majority").alias("arm")))
        if "tree_search" in chosen:
            parts.append(baselines.tree_search(totals.select("question_id", "family", "kind", "total"), baselines.clause_paths(spark)).select("question_id", "kind", F.lit("tree_search").alias("arm")))
        if "router" in chosen:
            two = trained(spark, sf_dir, arms=("base", "full"))
            hard = own("base", two["base"]).unionByName(own("full", two["full"])).join(qs.select("question_id", "tier"), "question_id")
            parts.append(baselines.route(hard, [t for t, level in LEVEL.items() if level != "L1"], "base", "full").select("question_id", "kind", "arm"))
        out = parts[0]
        for one in parts[1:]:
            out = out.unionByName(one)
        return out

    return _kept(spark, sf_dir, f"answers-{suites}-{'-'.join(arms)}", make)


def evaluated(spark: SparkSession, sf_dir: str, arms: tuple[str, ...] = ARMS, profiles: tuple[EngineProfile, ...] = (ADAPTIVE, STATIC), need: str = "times", suites: str = "ABC",
              read: bool = True) -> DataFrame:
    """``eval_rows``: each arm's answers with what they did on each engine; times are there if needed. Only what was answered is
    scored as text, and no text if nobody will ``read`` its scores. What nobody times runs beside the training, once the times that training depends on are taken."""
    def make() -> DataFrame:
        if set(arms) - {"base"}:
            rehearsed(spark, sf_dir, "all" if "result_overlap" in arms else "times", "all" if "clausewise" in arms else "links")
        chosen = {a for a in CHOSEN if a in arms}
        asked(spark, sf_dir, suites)
        if chosen:
            _ran(spark, sf_dir, suites)
        with ThreadPoolExecutor(1) as pool:
            beside = pool.submit(inheritable_thread_target(spark)(lambda: _ran(spark, sf_dir, suites)))
            said = answers(spark, sf_dir, arms, suites)
            only = (f"answers-{'-'.join(arms)}", said)
            if read:
                scored(spark, sf_dir, suites, "all", only)
            beside.result()
        took = ["t_gold", "t_pred", "t_cv"] if need == "times" else []
        seen = answered(spark, sf_dir, suites, profiles, need, only).select("question_id", "kind", "engine", "status", F.col("equal").alias("ex"), *took)
        if not read:
            qs = asked(spark, sf_dir, suites).select("question_id", "family", "suite", "tier")
            return said.join(qs, "question_id").join(seen, ["question_id", "kind"])
        rows = prepared(spark, sf_dir, suites, "rows", "all", only).select("question_id", "family", "kind", "suite", "tier", "em", "jac", "n_tok_in", "n_tok_out", "error", "pattern_ok", "mode")
        return said.join(rows, ["question_id", "kind"]).join(seen, ["question_id", "kind"])

    name = f"eval-{suites}-{need}-{len(profiles)}-{'-'.join(arms)}"
    return _kept(spark, sf_dir, name if read or _made(spark, sf_dir, name) else f"{name}-unread", make)


def _first(spark: SparkSession, sf_dir: str, arms: tuple[str, ...] = ARMS, need: str = "rows", suites: str = "ABC") -> DataFrame:
    return evaluated(spark, sf_dir, arms, (ADAPTIVE,), need, suites)


def w1(spark, sf_dir):
    """What each arm is rewarded for, and its mean reward of the leaves that events carry."""
    from .registry import LEAVES  # it imports this module

    paid = reward.score_arms(run_sql(spark, sf_dir, LEAVES)).groupBy("arm").agg(F.avg("total").alias("mean_total"))
    return reward.arms(spark).join(paid, "arm", "left")


def w2(spark, sf_dir):
    """Published places beside this library's arms, marked by origin."""
    ours = metrics.ex(evaluated(spark, sf_dir, need="rows", read=False), ["suite", "arm"]).select("suite", F.col("arm").alias("model"), F.round(100 * F.col("ex"), 4).alias("score"), F.lit("ours").alias("origin"))
    return metrics.leaderboard(published.leaderboard(spark).withColumn("origin", F.lit("published")).unionByName(ours), ["origin", "suite"])


def w3(spark, sf_dir):
    rows = _first(spark, sf_dir, (*ARMS, *BASELINES))
    per = metrics.ex(rows, ["arm", "suite"])
    return (metrics.em(rows, ["arm", "suite"]).join(metrics.pgr(per, "base", "full", ["suite"]), ["arm", "suite"])
            .join(metrics.tep(rows, "base", ["suite"]), ["arm", "suite"]))


def w4(spark, sf_dir):
    """EX, and percent over the untrained policy and over the supervised fit."""
    per = metrics.ex(_first(spark, sf_dir, (*ARMS, *BASELINES)), ["arm", "suite"])
    return _gains(per, "ex")


def w5(spark, sf_dir):
    return metrics.cdf(_first(spark, sf_dir, suites="AB"), ["arm", "suite"], "jac", GRID)


def _gains(per: DataFrame, value: str) -> DataFrame:
    for other in ("base", "sft"):
        per = per.join(metrics.efficiency_gain(per, other, ["suite"], value).withColumnRenamed("gain", f"over_{other}"), ["arm", "suite"])
    return per


def w6(spark, sf_dir):
    """VES, mean of both engines, and percent over the untrained policy and over the supervised fit."""
    return _gains(metrics.across_engines(evaluated(spark, sf_dir, (*ARMS, *BASELINES)), ["arm", "suite"]), "ves")


def _tiers(measure, need="rows"):
    def run(spark, sf_dir):
        return metrics.by_tier(_first(spark, sf_dir, need=need, suites="AB"), measure, TIERS["A"] + TIERS["B"])

    return run


def w10(spark, sf_dir):
    return judging.reduction(_first(spark, sf_dir), "base")


def w11(spark, sf_dir):
    return judging.shares(_first(spark, sf_dir, ("base",), suites="A"), ["arm"], "coarse")


def _trace(columns):
    def run(spark, sf_dir):
        arms = ("full", "skeleton_efficiency")
        runs = trained(spark, sf_dir, arms=arms)
        rows = [(arm, *t) for arm in arms for t in runs[arm].trace]
        return spark.createDataFrame(rows, f"arm string, {grouprl.TRACE}").select("arm", "step", *columns)

    return run


def w14(spark, sf_dir):
    ours = dataset.stats(asked(spark, sf_dir), ["suite"], "question", "gold_sql").withColumn("origin", F.lit("ours"))
    return ours.unionByName(published.training(spark).withColumn("origin", F.lit("published")))


def w15(spark, sf_dir):
    """How many questions each distillation filter keeps, per checkpoint of the full arm: text equal to gold's, rows equal
    to gold's, three right in a row, and the latest checkpoint's of these."""
    run = trained(spark, sf_dir, arms=("full",))["full"]
    qs = training_questions(spark, sf_dir)
    tried = distill.attempts(qs.select("question_id", "family"), {0: start_policy(), **run.snapshots}, 6).join(_right(spark, sf_dir), ["question_id", "kind"])
    count = lambda df, name: df.select("question_id", "snapshot").distinct().groupBy("snapshot").agg(F.count("*").alias(name))
    kept = distill.keep_run(tried)
    per = {"exact": distill.keep_exact(tried), "same_rows": distill.keep_exact(tried.withColumn("correct", F.col("equal")), "ex"), "run_of_three": kept, "progressive": distill.progressive(kept)}
    out = count(tried, "asked")
    for name, df in per.items():
        out = out.join(count(df, name), "snapshot", "left")
    return out.fillna(0)


def w16(spark, sf_dir):
    return metrics.rank_stability(evaluated(spark, sf_dir, read=False), ["suite"])


def w17(spark, sf_dir):
    return sweep(prepared(spark, sf_dir, need="rows", text="sim").where("pattern_ok"), [0.0, 0.3, 0.5, 0.7, 1.0], [0.5, 0.6, 0.7, 0.8, 0.9])


def w18(spark, sf_dir):
    """What training leaves of each suite's score, over the result rows that line items carry."""
    from .registry import EVAL  # it imports this module

    return metrics.retention(run_sql(spark, sf_dir, EVAL), "5-LOW", "1-URGENT")


def w19(spark, sf_dir):
    """Generalisation: suite C, which no arm was trained on."""
    rows = _first(spark, sf_dir, suites="C")
    return metrics.ex(rows, ["arm"]).join(metrics.em(rows, ["arm"]), "arm")


def w20(spark, sf_dir):
    """Candidates whose reward changes under each other reading of the method."""
    rows, out = prepared(spark, sf_dir, need="times", text="links"), None
    base = reward.score(rows).select("question_id", "kind", F.col("total").alias("t0"))
    for name, spec in reward.READINGS.items():
        one = reward.score(rows, spec).select("question_id", "kind", "total").join(base, ["question_id", "kind"]).agg(
            F.sum((F.col("total") != F.col("t0")).cast("long")).alias("flips"), F.count("*").alias("n"), F.avg("total").alias("mean_total")).withColumn("reading", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def w21(spark, sf_dir):
    """What the gate saves and costs: executions avoided, right candidates turned away."""
    rows = prepared(spark, sf_dir, need="rows", text="sim").where("pattern_ok").withColumn("passed", F.col("sim") >= 0.6)
    return rows.groupBy("suite").agg(
        F.countDistinct("sql").alias("texts"), F.countDistinct(F.when(~F.col("passed"), F.col("sql"))).alias("avoided"),
        F.sum((~F.col("passed") & F.col("equal")).cast("long")).alias("right_rejected"), F.sum((F.col("passed") & ~F.col("equal")).cast("long")).alias("wrong_passed"))


def w22(spark, sf_dir):
    rows = scored(spark, sf_dir, text="form")
    return rows.groupBy("mode").agg(F.avg(F.col("pattern_ok").cast("double")).alias("valid"), F.avg("n_tok_out").alias("tokens_out"), F.count("*").alias("n"))


RUNS = {"w1": w1, "w2": w2, "w3": w3, "w4": w4, "w5": w5, "w6": w6, "w7": _tiers("ex"), "w8": _tiers("jac"), "w9": _tiers("ves", "times"), "w10": w10, "w11": w11,
        "w12": _trace(["mean_reward", "sd_reward"]), "w13": _trace(["mean_len"]), "w14": w14, "w15": w15, "w16": w16, "w17": w17, "w18": w18, "w19": w19, "w20": w20, "w21": w21, "w22": w22}


def run(wid: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    reach_workers(spark)
    return RUNS[wid](spark, sf_dir)


__all__ = ["ARMS", "BASELINES", "FAMILIES", "RUNS", "baselines", "evaluated", "executions", "prepared", "run", "trained"]
