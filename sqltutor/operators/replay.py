"""What candidates do when they run: every family's edits are executed for real, under each engine, and looked up after.

``texts`` are templates with their family's own parameter row, ``asked_texts`` those of all questions, each with its own
parameters. Texts of one template that differ in parameters run for their rows together, as one query over all parameter
rows (``together``); what that cannot tell runs text by text. Times are of single texts in either case.
"""

from __future__ import annotations

import re
import time
import uuid
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import execution
from ..sources.load import DATABASES, views
from ..store import Shelf
from . import mutate
from .baselines import result_overlap
from .suites import BY_ID, FAMILIES, Family

#: The runaway answer's own limit, so that it costs seconds and no more.
RUNAWAY_S = 1.5
SEEN = ("n", "sum_h", "xor_h", "ncols")


def filled(family: Family, template: str) -> str:
    return template.replace("{p1}", family.default[0]).replace("{p2}", family.default[1])


def texts(spark: SparkSession, kinds: tuple[str, ...] = mutate.KINDS, suites: str = "ABC") -> DataFrame:
    """``(family, db_id, kind, sql, gold_sql)``: a row per family of these suites and kind."""
    rows = [(f.id, f.db, k, filled(f, mutate.edit(f.gold, k)), f.text()) for f in FAMILIES if f.suite in suites for k in kinds]
    return spark.createDataFrame(rows, "family string, db_id string, kind string, sql string, gold_sql string")


def asked_texts(questions: DataFrame, kinds: tuple[str, ...] = mutate.KINDS) -> DataFrame:
    """``(question_id, family, db_id, kind, template, p1, p2, sql, gold_sql)``: a row per question and kind. A question that
    names no values has its family's own."""
    rows = [(f.id, f.db, k, mutate.edit(f.gold, k), f.gold, *f.default) for f in BY_ID.values() for k in kinds]
    edits = questions.sparkSession.createDataFrame(rows, "family string, db_id string, kind string, template string, gold string, d1 string, d2 string")
    named = [F.coalesce(F.col(p) if p in questions.columns else F.lit(None), F.col(d)).alias(p) for p, d in (("p1", "d1"), ("p2", "d2"))]
    asked = questions.select("question_id", "family", *[p for p in ("p1", "p2") if p in questions.columns])
    out = asked.join(F.broadcast(edits), "family").select("question_id", "family", "db_id", "kind", "template", "gold", *named)
    text = lambda c: F.replace(F.replace(F.col(c), F.lit("{p1}"), F.col("p1")), F.lit("{p2}"), F.col("p2"))
    return out.withColumns({"sql": text("template"), "gold_sql": text("gold")}).drop("gold")


def outcomes(spark: SparkSession, sf_dir: str, profiles: tuple[execution.EngineProfile, ...] = (execution.ADAPTIVE, execution.STATIC),
             warmup: int = 0, repeats: int = 2, kinds: tuple[str, ...] = mutate.KINDS, users: int = 8, suites: str = "ABC") -> DataFrame:
    """``(family, kind, engine, status, equal, overlap, t_gold, t_pred, t_cv, cpu_ms, shuffled, spilled, peak, ..., fp)``.

    Every text runs once under the first engine for its status and rows, ``users`` at a time (``checked``). Those whose rows
    are gold's run once under each other engine in the same way, and then under each engine one at a time, as a single user's:
    ``warmup`` times unseen and ``repeats`` times by the clock (``clocked``). A wrong answer's status holds for all engines and its
    time, that of its one run under load, counts in no measure."""
    wanted, first, out = texts(spark, kinds, suites), None, None
    for profile in profiles:
        seen = checked(spark, sf_dir, wanted, profile, first, users)
        first = seen if first is None else first
        rows = compared(wanted, clocked(spark, sf_dir, seen, profile, warmup, repeats))
        out = rows if out is None else out.union(rows)
    return out.join(overlaps(spark, sf_dir, wanted, compared(wanted, first)), ["family", "kind"], "left")


def checked(spark: SparkSession, sf_dir: str, wanted: DataFrame, profile: execution.EngineProfile, first: DataFrame | None = None, users: int = 8) -> DataFrame:
    """``(db_id, right, ...)``, a row per text: its one run under ``profile``, ``users`` at a time, and whether its rows are
    gold's under the first engine. Given that engine's rows as ``first``, right texts run and the others keep theirs.
    ``asked_texts`` run together by template."""
    views(spark, sf_dir)
    profile, scratch = _sized(spark, profile), Shelf(spark, "replay")
    runaway = wanted.where("kind = 'timeout'").select("db_id", "sql").distinct()
    mine = wanted.where("kind <> 'timeout'") if first is None else first.where("right")
    if "template" in wanted.columns:
        right = mine.select("db_id", "sql").distinct()
        mine = wanted.where("kind <> 'timeout'").join(right, ["db_id", "sql"], "left_semi") if first is not None else mine
        some = together(spark, mine, profile, users=users)
        out = some.unionByName(execution.run(spark, mine, DATABASES, profile, done=some, repeats=0, concurrency=users))
    else:
        out = execution.run(spark, mine, DATABASES, profile, repeats=0, concurrency=users)
    # by themselves: what is cancelled would take texts that run beside it along
    away = execution.run(spark, runaway, DATABASES, profile, repeats=0, limit_s=RUNAWAY_S, concurrency=users).withColumn("right", F.lit(False))
    if first is None:
        prints = out.where("status = 'ok'").select("db_id", "sql", _print().alias("fp"))
        gold = prints.select("db_id", F.col("sql").alias("gold_sql"), F.col("fp").alias("gold_fp"))
        right = wanted.join(prints, ["db_id", "sql"]).join(gold, ["db_id", "gold_sql"]).where("fp = gold_fp").select("db_id", "sql")
        right = right.union(wanted.select("db_id", F.col("gold_sql").alias("sql"))).distinct().withColumn("right", F.lit(True))
        out = out.join(right, ["db_id", "sql"], "left").withColumn("right", F.coalesce("right", F.lit(False)))
    else:
        kept = first.where(~F.col("right")).join(runaway, ["db_id", "sql"], "left_anti")
        out = out.withColumn("right", F.lit(True)).unionByName(kept.withColumn("engine", F.lit(profile.name)))
    return scratch.put(out.unionByName(away), "checked")


def together(spark: SparkSession, wanted: DataFrame, profile: execution.EngineProfile, limit_s: float = 30.0, users: int = 8) -> DataFrame:
    """``execution.run``'s rows of those ``asked_texts`` whose template runs as one query over all its parameter rows, or isn't
    let run, which values that stay values can't change.

    A query that takes longer than one text may is split by parameter row until its parts do not; texts whose part fails, or
    whose parameters would change more than a value, have no row here. ``t_first`` is a text's share of its query's time."""
    shelf, made = Shelf(spark, "together"), []
    where, heads = _filed(shelf, wanted)

    def put(rows: DataFrame, head, status: str, error: str | None) -> str:
        name = f"part-{uuid.uuid4().hex}"
        rows.withColumns({"db_id": F.lit(head["db_id"]), "part": F.lit(name), "status": F.lit(status), "error": F.lit(error).cast("string")}).write.parquet(shelf.path(name))
        return name

    def part(head, query: str, way: str, n: int) -> None:
        picked = "".join(f" AND pmod(shiftright(xxhash64(p1, p2), {k}), 2) = {b}" for k, b in enumerate(way))
        rows = spark.sql(query.replace("{texts}", f"{where(head)}{picked}"))
        began = time.perf_counter()
        try:
            name = execution.limited(spark, limit_s, lambda: put(rows, head, "ok", None))
        except execution.TimeLimit:
            if n > 1 and len(way) < _SPLITS:
                for b in "01":
                    part(head, query, way + b, (n + 1) // 2)
            return
        except Exception:  # one text's failure is all texts' here; they run by themselves
            return
        made.append((name, (time.perf_counter() - began) / n))

    def one(head) -> None:
        if _filled_by_values(head) and (why := execution.refused(spark, head["sql"], DATABASES[head["db_id"]])):
            none = {"n": "long", "sum_h": "string", "xor_h": "long", "ncols": "int"}
            made.append((put(spark.sql(where(head)).select("sql", *[F.lit(None).cast(k).alias(c) for c, k in none.items()]), head, *why), None))
        elif (kinds := _kinds(spark, head)) and (query := _planned(spark, where(head), over_parameters(head["template"], kinds))):
            part(head, query, "", head["n"])

    with execution.engine(spark, profile), execution.quiet(), ThreadPoolExecutor(users) as pool:
        list(pool.map(inheritable_thread_target(spark)(one), heads))
    out = spark.createDataFrame([], f"{execution.SCHEMA}, db_id string")
    if not made:
        return out
    rows = spark.read.schema("sql string, n long, sum_h string, xor_h long, ncols int, db_id string, part string, status string, error string").parquet(*[shelf.path(name) for name, _ in made])
    rows = rows.join(F.broadcast(spark.createDataFrame(made, "part string, t_first double")), "part")
    blank = {c: F.lit(None).cast(dict(out.dtypes)[c]) for c in ("t_mean", *execution.COSTS)}
    return shelf.put(rows.withColumns({"engine": F.lit(profile.name), "times": F.array().cast("array<double>"), **blank}).select(*out.columns), "rows")


#: Values that stand in a quoted literal as they are, and those that are a literal of their own.
_HARMLESS, _WHOLE = r"^[^'\\`{}]*$", r"^-?[0-9]{1,17}$"
_LITERAL = re.compile(r"'[^']*'")
_SPLITS = 12


def _filed(shelf: Shelf, wanted: DataFrame):
    """Writes the distinct ``asked_texts`` whose values are harmless. Returns SQL of a template's rows, and the templates."""
    plain = F.col("p1").rlike(_HARMLESS) & F.col("p2").rlike(_HARMLESS)
    texts = shelf.put(wanted.where(plain).select("db_id", "template", "p1", "p2", "sql").distinct(), "texts")
    heads = texts.groupBy("db_id", "template").agg(F.count("*").alias("n"), F.min("sql").alias("sql"), *[F.min(F.col(p).rlike(_WHOLE)).alias(p) for p in ("p1", "p2")]).collect()  # families times kinds at most
    quoted = lambda x: "'" + x.replace("\\", "\\\\").replace("'", "\\'") + "'"
    return lambda h: f"SELECT p1, p2, sql FROM parquet.`{shelf.path('texts')}` WHERE db_id = {quoted(h['db_id'])} AND template = {quoted(h['template'])}", heads


def _filled_by_values(head) -> bool:
    """Whether each of a template's parameters is a value of its own, or in a quoted literal, in all its texts."""
    bare = [p for p in ("p1", "p2") if "{" + p + "}" in _LITERAL.sub("", head["template"])]
    return bool(re.search(r"\{p[12]\}", head["template"])) and all(head[p] for p in bare)


def _kinds(spark: SparkSession, head) -> list[str] | None:
    """Types of the columns of a template's texts; none where values are more than values or the texts don't run."""
    if not _filled_by_values(head) or execution.guard(spark, head["sql"], DATABASES[head["db_id"]]) != "ok":
        return None
    try:
        return [k for _, k in spark.sql(head["sql"]).dtypes]
    except AnalysisException:
        return None


def _planned(spark: SparkSession, rows: str, query: str) -> str | None:
    try:
        spark.sql(query.replace("{texts}", rows))
    except AnalysisException:  # parameters stand where the engine lets no column of another row stand
        return None
    return query


def over_parameters(template: str, kinds: list[str], rows: bool = False) -> str:
    """A query of the fingerprints, or with ``rows`` the rows' hashes, of all texts of ``template``, whose columns have these
    types: its parameters are columns of the rows that ``{texts}`` stands for."""
    def quoted(m) -> str:
        parts = [x for x in re.split(r"(\{p[12]\})", m.group(0)[1:-1]) if x]
        parts = [f"asked.{x[1:3]}" if re.fullmatch(r"\{p[12]\}", x) else f"'{x}'" for x in parts]
        return parts[0] if len(parts) == 1 else f"concat({', '.join(parts)})"

    body = re.sub(r"'[^']*\{p[12]\}[^']*'", quoted, template)
    body = re.sub(r"\{(p[12])\}(\d*)", lambda m: f"CAST(concat(asked.{m[1]}, '{m[2]}') AS BIGINT)", body)
    h = f"xxhash64({', '.join(f'coalesce({c}, chr(0))' for c in execution.cell_texts(kinds))})"
    table = f"({body}) AS t({', '.join(f'c{i}' for i in range(len(kinds)))})"
    if rows:
        return f"SELECT asked.p1, asked.p2, found.h FROM ({{texts}}) AS asked, LATERAL (SELECT {h} AS h FROM {table}) AS found"
    return (f"SELECT asked.sql, found.* FROM ({{texts}}) AS asked, LATERAL (SELECT count(*) AS n, CAST(coalesce(sum(CAST({h} AS DECIMAL(38, 0))), 0) AS STRING) AS sum_h, "
            f"coalesce(bit_xor({h}), 0) AS xor_h, {len(kinds)} AS ncols FROM {table}) AS found")


def clocked(spark: SparkSession, sf_dir: str, seen: DataFrame, profile: execution.EngineProfile, warmup: int = 0, repeats: int = 2) -> DataFrame:
    """Rows of ``checked`` with times and costs of right texts that ran, one at a time."""
    views(spark, sf_dir)
    profile, scratch, out = _sized(spark, profile), Shelf(spark, "replay"), seen.where("NOT (right AND status = 'ok')")
    todo = seen.where("right AND status = 'ok'")
    runs = execution.run(spark, todo.select("db_id", "sql"), DATABASES, profile, warmup=warmup, repeats=repeats, costs=True, rows=False)
    out = out.unionByName(runs.drop(*SEEN).join(todo.select("sql", "db_id", "right", *SEEN), ["db_id", "sql"]))
    return scratch.put(out, "clocked")


def compared(wanted: DataFrame, runs: DataFrame) -> DataFrame:
    """A row per family or question and kind: what its text did in ``runs`` of one engine, beside what gold did."""
    runs = runs.withColumn("t_mean", F.coalesce("t_mean", "t_first"))
    spent = ["t_mean", "cpu_ms", "shuffled", "spilled", "peak"]
    off, n = lambda x: x - F.col("t_mean"), F.size("times")
    cv = F.try_divide(F.sqrt(F.try_divide(F.aggregate("times", F.lit(0.0), lambda a, x: a + off(x) * off(x)), n - 1)), F.col("t_mean"))
    one = runs.select("db_id", "sql", "engine", "status", _print().alias("fp"), cv.alias("t_cv"), *spent)
    gold = runs.select("db_id", F.col("sql").alias("gold_sql"), "engine", _print().alias("gold_fp"), *[F.col(c).alias(f"gold_{c}") for c in spent])
    rows = wanted.join(one, ["db_id", "sql"]).join(gold, ["db_id", "gold_sql", "engine"])
    rows = rows.withColumn("equal", F.coalesce(F.col("fp") == F.col("gold_fp"), F.lit(False))).withColumnsRenamed({"t_mean": "t_pred", "gold_t_mean": "t_gold"})
    return Shelf(wanted.sparkSession, "replay").put(rows.drop("gold_fp", "sql", "gold_sql", "db_id", "template", "p1", "p2"), "outcomes")


def _sized(spark: SparkSession, profile: execution.EngineProfile) -> execution.EngineProfile:
    """An engine that cannot adapt shuffles into no more parts than there are cores, or most of its tasks would be empty."""
    if profile.conf.get("spark.sql.adaptive.enabled") != "false":
        return profile
    parts = min(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return execution.EngineProfile(profile.name, {**profile.conf, "spark.sql.shuffle.partitions": str(parts)})


def _print() -> F.Column:
    return F.when(F.col("status") == "ok", F.concat_ws("/", "n", "sum_h", "xor_h", "ncols"))


def overlaps(spark: SparkSession, sf_dir: str, wanted: DataFrame, rows: DataFrame, users: int = 8) -> DataFrame:
    """``(family, kind, overlap)``, or by question where texts are ``asked_texts``: shared rows over all rows of the results of
    candidate and gold, where both ran and differ in ``rows``, outcomes under one engine. Each pair is one small query, or each
    pair of templates one over all parameter rows; ``users`` of them run at a time, since nobody times them."""
    views(spark, sf_dir)
    by = "question_id" if "template" in wanted.columns else "family"
    odd = rows.where("status = 'ok' AND NOT equal").join(rows.where("kind = 'exact' AND status = 'ok'").select(by), by, "left_semi")
    odd = odd.select(by, "kind").join(wanted, [by, "kind"])

    def one(r) -> tuple:
        a, b = spark.sql(r["gold_sql"]), spark.sql(r["sql"])
        if len(a.columns) != len(b.columns):
            return r["sql"], r["gold_sql"], 0.0
        even = lambda df: df.select(*[F.round(c, 6).cast("string") if "double" in k or "decimal" in k else F.col(c).cast("string") for c, k in df.toDF(*names).dtypes])
        names = [f"c{i}" for i in range(len(a.columns))]
        return r["sql"], r["gold_sql"], result_overlap(even(a.toDF(*names)).toDF(*names), even(b.toDF(*names)).toDF(*names)).first()["overlap"]

    pairs, found = odd.select("db_id", "sql", "gold_sql").distinct(), None
    if by == "question_id":
        found = overlaps_together(spark, odd, users)
        pairs = pairs.join(found, ["sql", "gold_sql"], "left_anti")
    with ThreadPoolExecutor(users) as pool:
        alone = pool.map(inheritable_thread_target(spark)(one), pairs.collect())  # families times kinds, and few questions' besides
        alone = spark.createDataFrame(list(alone), "sql string, gold_sql string, overlap double")
    found = alone if found is None else found.unionByName(alone)
    return odd.select(by, "kind", "sql", "gold_sql").join(found, ["sql", "gold_sql"]).select(by, "kind", "overlap")


def overlaps_together(spark: SparkSession, odd: DataFrame, users: int = 8) -> DataFrame:
    """``(sql, gold_sql, overlap)`` of those ``asked_texts`` whose template and gold's run as one query over their parameter rows."""
    shelf, made = Shelf(spark, "overlaps"), []
    odd = shelf.put(odd.join(F.broadcast(spark.createDataFrame([(f.id, f.gold) for f in FAMILIES], "family string, gold string")), "family"), "odd")
    where, heads = _filed(shelf, odd)
    golds = {(r["db_id"], r["template"], r["gold"]): r["gold_sql"] for r in odd.groupBy("db_id", "template", "gold").agg(F.min("gold_sql").alias("gold_sql")).collect()}  # families times kinds at most

    def one(pair) -> None:
        head, gold, gold_sql = pair
        gold = {**head.asDict(), "template": gold, "sql": gold_sql}
        (kinds, of_gold), some = (_kinds(spark, h) for h in (head, gold)), where(head)
        if not kinds or not of_gold:
            return
        texts = spark.sql(some).join(odd.where(F.col("gold") == gold["template"]).select("sql", "gold_sql").distinct(), "sql")
        if len(kinds) != len(of_gold):
            out = texts.select("sql", "gold_sql", F.lit(0.0).alias("overlap"))
        else:
            sides = [_planned(spark, some, over_parameters(h["template"], k, rows=True)) for h, k in ((head, kinds), (gold, of_gold))]
            if not all(sides):
                return
            a, b = (spark.sql(x.replace("{texts}", some)) for x in sides)
            bag = a.select("p1", "p2", "h", F.lit(1).alias("a"), F.lit(0).alias("b")).unionByName(b.select("p1", "p2", "h", F.lit(0).alias("a"), F.lit(1).alias("b")))
            per = bag.groupBy("p1", "p2", "h").agg(F.sum("a").alias("na"), F.sum("b").alias("nb"))
            per = per.groupBy("p1", "p2").agg((F.sum(F.least("na", "nb")) / F.sum(F.greatest("na", "nb"))).alias("overlap"))
            out = texts.join(per, ["p1", "p2"]).select("sql", "gold_sql", "overlap")
        name = f"part-{uuid.uuid4().hex}"
        try:
            out.write.parquet(shelf.path(name))
        except Exception:  # these pairs run by themselves
            return
        made.append(shelf.path(name))

    with execution.quiet(), ThreadPoolExecutor(users) as pool:
        list(pool.map(inheritable_thread_target(spark)(one), [(h, g, s) for h in heads for (db, t, g), s in golds.items() if (db, t) == (h["db_id"], h["template"])]))
    schema = "sql string, gold_sql string, overlap double"
    return spark.read.schema(schema).parquet(*made) if made else spark.createDataFrame([], schema)


def replayed(cands: DataFrame, results: DataFrame, engine: str = "adaptive") -> DataFrame:
    """Candidates with what their own question's text of their kind did under ``engine``."""
    return cands.join(results.where(F.col("engine") == engine).drop("engine", "family"), ["question_id", "kind"], "left")
