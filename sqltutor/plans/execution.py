"""Sandboxed, timed execution of SQL text, one row of results per distinct text.

Executors cannot start queries, so the driver leads: texts come in pages, each is guarded, analysed, fingerprinted and
timed; only one fingerprint row per text returns. Texts already in a result table are not run again.
"""

from __future__ import annotations

import contextlib
import itertools
import logging
import re
import threading
import time
import uuid
from collections.abc import Iterable, Iterator, Mapping
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from py4j.protocol import Py4JJavaError
from pyspark import inheritable_thread_target
from pyspark.errors import AnalysisException, ParseException
from pyspark.logger import PySparkLogger
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import Shelf

SCHEMA = "sql string, engine string, status string, times array<double>, t_mean double, n long, sum_h string, xor_h long, ncols int, error string, cpu_ms long, shuffled long, spilled long, peak long, t_first double"
#: Plan nodes that a query may be made of; anything else (commands, writes, table functions) is blocked.
NODES = frozenset("Project Filter UnresolvedRelation Join Aggregate Sort GlobalLimit LocalLimit Offset SubqueryAlias UnresolvedWith CTE Union Intersect Except "
                  "Distinct OneRowRelation UnresolvedHaving WithWindowDefinition UnresolvedSubqueryColumnAliases LateralJoin UnresolvedInlineTable Limit".split())


@dataclass(frozen=True)
class EngineProfile:
    """Runtime settings that make the session behave as one of two engines."""

    name: str
    conf: dict[str, str] = field(default_factory=dict)


ADAPTIVE = EngineProfile("adaptive", {"spark.sql.adaptive.enabled": "true"})
#: Much like ADAPTIVE, but sorts where that hashes.
SORTING = EngineProfile("sorting", {"spark.sql.adaptive.enabled": "true", "spark.sql.join.preferSortMergeJoin": "true", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.execution.useObjectHashAggregateExec": "false"})
STATIC = EngineProfile("static", {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.codegen.wholeStage": "false"})
#: For joins without keys inside one another. Tasks notice that they were cancelled when they read from a scan or from a
#: buffer that may spill, which is seldom or never in loops over broadcast rows; and a product of products has as many
#: parts as all its inputs' parts multiplied, so each input is one.
STOPPABLE = {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1", "spark.sql.cartesianProductExec.buffer.in.memory.threshold": "0",
             "spark.sql.files.minPartitionNum": "1", "spark.sql.files.maxPartitionBytes": str(1 << 50)}
_CANCEL_S = 0.2


@contextlib.contextmanager
def engine(spark: SparkSession, profile: EngineProfile) -> Iterator[None]:
    before = {k: spark.conf.get(k, None) for k in profile.conf}
    try:
        for k, v in profile.conf.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            if v is None:
                spark.conf.unset(k)
            else:
                spark.conf.set(k, v)


@contextlib.contextmanager
def quiet() -> Iterator[None]:
    """Texts that fail are results here; the client's log of failed queries stays silent meanwhile."""
    log = PySparkLogger.getLogger("SQLQueryContextLogger")
    before = log.level
    log.setLevel(logging.CRITICAL)
    try:
        yield
    finally:
        log.setLevel(before)


def plan_text(spark: SparkSession, sql: str) -> str:
    """The parser's tree; raises ``ParseException``. Nothing is resolved or run."""
    return spark._jsparkSession.sessionState().sqlParser().parsePlan(sql).toString()


def parses(spark: SparkSession, sql: str) -> bool:
    try:
        plan_text(spark, sql)
    except ParseException:
        return False
    return True


def guard(spark: SparkSession, sql: str | None, tables: Iterable[str], functions: Iterable[str] | None = None) -> str:
    """"ok", "parse_error" or "blocked": queries over listed one-part tables only and, where ``functions`` is given, over
    these functions only. Granting a view and not what is under it gives its columns and rows and no others."""
    if not sql or not sql.strip():
        return "parse_error"
    try:
        tree = plan_text(spark, sql)
    except ParseException:
        return "parse_error"
    names = {x.lower() for x in re.findall(r"UnresolvedRelation \[([^\]]*)\]", tree)}
    local = {x.lower() for x in re.findall(r"(?:CTE \[|, )(\w+)(?=[,\]])", tree)} | {x.lower() for x in re.findall(r"\bWITH (\w+) AS|\), (\w+) AS \(", sql, re.I) for x in x if x}
    for line in tree.splitlines():
        m = re.match(r"[\s:+\-|*]*'?([A-Z]\w*)", line)
        if m and m.group(1) not in NODES and not m.group(1)[0].islower():
            return "blocked"
    called = {x.lower() for x in re.findall(r"'(\w+)\(", tree)} if functions is not None else set()
    return "ok" if names <= {t.lower() for t in tables} | local and called <= {f.lower() for f in functions or ()} else "blocked"


def cell_texts(kinds: list[str]) -> list[str]:
    """SQL of the texts that ``fingerprint`` makes of columns c0, c1, ... of these types."""
    whole = ("int", "bigint", "smallint", "tinyint")
    return [f"CAST(round(CAST(c{i} AS DOUBLE), 6) AS STRING)" if re.match("double|float|decimal", k) else f"CAST(CAST(c{i} AS BIGINT) AS STRING)" if k in whole else f"CAST(c{i} AS STRING)"
            for i, k in enumerate(kinds)]


def fingerprint(df: DataFrame, mode: str = "bag", digits: int = 6) -> DataFrame:
    """One row ``(n, sum_h, xor_h, ncols)`` that equal results share: order and column names do not matter, doubles are
    rounded. ``set`` drops repeated rows; ``ordered`` numbers rows as they come from the query's own sort."""
    kinds = [k for _, k in df.dtypes]
    plain = df.toDF(*[f"c{i}" for i in range(len(kinds))])
    cells = [F.round(F.col(f"c{i}").cast("double"), digits).cast("string") if re.match("double|float|decimal", k) else
             (F.col(f"c{i}").cast("long").cast("string") if k in ("int", "bigint", "smallint", "tinyint") else F.col(f"c{i}").cast("string")) for i, k in enumerate(kinds)]
    if mode == "set":
        plain = plain.select(*[c.alias(f"c{i}") for i, c in enumerate(cells)]).distinct()
        cells = [F.col(f"c{i}") for i in range(len(kinds))]
    if mode == "ordered":
        plain = plain.withColumn("place", F.monotonically_increasing_id())
        cells = [*cells, F.col("place").cast("string")]
    h = F.xxhash64(*[F.coalesce(c, F.lit("\x00")) for c in cells])
    return plain.select(h.alias("h")).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.col("h").cast("decimal(38,0)")), F.lit(0)).cast("string").alias("sum_h"),
                                          F.coalesce(F.bit_xor("h"), F.lit(0)).alias("xor_h"), F.lit(len(kinds)).alias("ncols"))


def equal(spark: SparkSession, a: str, b: str, mode: str = "bag") -> bool:
    x, y = fingerprint(spark.sql(a), mode).first(), fingerprint(spark.sql(b), mode).first()
    return x == y


def equal_exactly(a: DataFrame, b: DataFrame) -> bool:
    """Without hashing: no row is left over on either side."""
    names = [f"c{i}" for i in range(len(a.columns))]
    if len(a.columns) != len(b.columns):
        return False
    a, b = a.toDF(*names), b.toDF(*names)
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


class TimeLimit(Exception):
    pass


def limited(spark: SparkSession, limit_s: float, work):
    """Runs ``work`` and cancels its jobs by tag once ``limit_s`` seconds have gone, those that it starts later too."""
    sc, tag, late, done = spark.sparkContext, f"limit-{uuid.uuid4().hex}", threading.Event(), threading.Event()

    def stop():
        wait = limit_s
        while not done.wait(wait):
            late.set()
            sc.cancelJobsWithTag(tag)
            wait = _CANCEL_S

    sc.setInterruptOnCancel(True)
    sc.addJobTag(tag)
    watch = threading.Thread(target=stop, daemon=True)
    watch.start()
    try:
        return work()
    except Exception as e:
        if late.is_set():
            raise TimeLimit from e
        raise
    finally:
        done.set()
        watch.join()
        sc.removeJobTag(tag)


def stoppable(spark: SparkSession, sql: str) -> SparkSession:
    """The session to run ``sql`` in: a copy with ``STOPPABLE`` settings if its plan has loops inside loops, else this one.
    Rows are the same in both; what such a text costs is not."""
    if len(re.findall(r"\bJoin\b", plan_text(spark, sql))) < 2:
        return spark
    plan = spark.sql(sql)._jdf.queryExecution().sparkPlan().toString()
    if len(re.findall(r"\b(?:BroadcastNestedLoopJoin|CartesianProduct)\b", plan)) < 2:
        return spark
    apart = SparkSession(spark.sparkContext, spark._jsparkSession.cloneSession())
    for k, v in STOPPABLE.items():
        apart.conf.set(k, v)
    return apart


#: What a run used, summed over its stages.
COSTS = ("cpu_ms", "shuffled", "spilled", "peak")
_RECENT = 64


def used(spark: SparkSession, tag: str) -> tuple[int, ...]:
    """CPU milliseconds, bytes shuffled, bytes spilled and peak execution memory of the jobs under ``tag``."""
    bus, store = spark.sparkContext._jsc.sc().listenerBus(), spark.sparkContext._jsc.sc().statusStore()
    bus.waitUntilEmpty()
    jobs, stages = store.jobsList(None), set()
    for k in range(min(jobs.size(), _RECENT)):  # newest first
        job = jobs.apply(k)
        if job.jobTags().contains(tag):
            ids = job.stageIds()
            stages.update(ids.apply(j) for j in range(ids.size()))
        elif stages:
            break
    total = [0] * len(COSTS)
    for j in stages:
        try:
            x = store.lastStageAttempt(j)
        except Py4JJavaError:  # a stage that was skipped and is forgotten
            continue
        for k, v in enumerate((x.executorCpuTime() // 1_000_000, x.shuffleWriteBytes(), x.memoryBytesSpilled() + x.diskBytesSpilled(), x.peakExecutionMemory())):
            total[k] = max(total[k], v) if COSTS[k] == "peak" else total[k] + v
    return tuple(total)


def refused(spark: SparkSession, sql: str, tables: Iterable[str]) -> tuple[str, str | None] | None:
    """Status and error of a text that guard, parser or analyser don't let run. These look at names and kinds of literals, not
    at values."""
    if (status := guard(spark, sql, tables)) != "ok":
        return status, None
    try:
        spark.sql(sql)
    except AnalysisException as e:  # a parser's error is one too
        return "parse_error" if isinstance(e, ParseException) else "analysis_error", str(e).splitlines()[0][:200]
    return None


def run_one(spark: SparkSession, sql: str | None, tables: Iterable[str], profile: EngineProfile = ADAPTIVE, warmup: int = 1, repeats: int = 3, limit_s: float = 30.0, costs: bool = False, rows: bool = True) -> tuple:
    """``(status, times, t_mean, n, sum_h, xor_h, ncols, error, *costs, t_first)`` of one text; ``repeats=0`` only
    fingerprints.

    The fingerprint comes from a run of its own, so the text has run once before warm-up, which ``t_first`` tells; ``costs``
    reads what the last timed run used. ``rows=False`` leaves the fingerprint out, for texts whose rows are known."""
    fail = lambda status, e="": (status, [], None, None, None, None, None, str(e).splitlines()[0][:200] if str(e) else None, *[None] * (len(COSTS) + 1))
    status = guard(spark, sql, tables)
    if status != "ok":
        return fail(status)
    try:
        df = spark.sql(sql)
    except ParseException as e:
        return fail("parse_error", e)
    except AnalysisException as e:
        return fail("analysis_error", e)
    tag = f"costs-{uuid.uuid4().hex}"
    try:
        with engine(spark, profile):
            home = stoppable(spark, sql)
            df = df if home is spark else home.sql(sql)
            began = time.perf_counter()
            fp = limited(spark, limit_s, lambda: fingerprint(df).first()) if rows else {}
            t_first, times = time.perf_counter() - began, []
            for k in range((warmup + repeats) if repeats else 0):
                last = costs and k == warmup + repeats - 1
                if last:
                    spark.sparkContext.addJobTag(tag)
                began = time.perf_counter()
                limited(spark, limit_s, lambda: home.sql(sql).write.format("noop").mode("overwrite").save())
                if k >= warmup:
                    times.append(time.perf_counter() - began)
                if last:
                    spark.sparkContext.removeJobTag(tag)
    except TimeLimit:
        return fail("timeout")
    except Exception as e:  # a run may fail in many ways; each is the query's own failure
        return fail("runtime_error", e)
    finally:
        spark.sparkContext.removeJobTag(tag)
    spent = used(spark, tag) if costs and times else [None] * len(COSTS)
    return ("ok", times, sum(times) / len(times) if times else None, *[fp[c] if rows else None for c in ("n", "sum_h", "xor_h", "ncols")], None, *spent, t_first if rows else None)


def run(spark: SparkSession, texts: DataFrame, tables: Iterable[str] | Mapping[str, Iterable[str]], profile: EngineProfile = ADAPTIVE, done: DataFrame | None = None, warmup: int = 1, repeats: int = 3,
        limit_s: float = 30.0, page: int = 10_000, concurrency: int = 1, costs: bool = False, rows: bool = True) -> DataFrame:
    """Executes the distinct ``sql`` of ``texts`` that ``done`` lacks for this engine. One after the other they are a single
    user's and their times mean something; ``concurrency`` users at a time are a load, whose times belong to that load.
    Texts reach the driver through a local iterator, and results leave it for the shared folder every ``page`` texts.

    Where ``tables`` are given by database, each text runs over those of its ``db_id``, which the result has too."""
    by_db = isinstance(tables, Mapping)
    keys, schema = (["db_id"], f"{SCHEMA}, db_id string") if by_db else ([], SCHEMA)
    todo = texts.select("sql", *keys).where("sql IS NOT NULL").distinct()
    if done is not None:
        todo = todo.join(done.where(F.col("engine") == profile.name).select("sql", *keys), ["sql", *keys], "left_anti")
    allowed = {db: list(ts) for db, ts in tables.items()} if by_db else list(tables)

    def one(r) -> tuple:
        granted = allowed[r["db_id"]] if by_db else allowed
        return r["sql"], profile.name, *run_one(spark, r["sql"], granted, EngineProfile(profile.name), warmup, repeats, limit_s, costs, rows), *[r[k] for k in keys]

    scratch, names = Shelf(spark, "runs"), []
    with engine(spark, profile), quiet(), ThreadPoolExecutor(concurrency) as pool:
        left = todo.orderBy("sql", *keys).toLocalIterator()
        while some := list(itertools.islice(left, page)):
            found = list(pool.map(inheritable_thread_target(spark)(one), some)) if concurrency > 1 else [one(x) for x in some]
            names.append(f"page-{len(names)}")
            spark.createDataFrame(found, schema).coalesce(1).write.parquet(scratch.path(names[-1]))
    return spark.read.schema(schema).parquet(*[scratch.path(n) for n in names]) if names else spark.createDataFrame([], schema)


def judged(cands: DataFrame, runs: DataFrame) -> DataFrame:
    """Adds ``status``, ``equal``, ``t_pred``, ``t_gold`` and ``fp`` from a result table, by text."""
    one = runs.select("sql", "status", F.col("t_mean").alias("t_pred"), F.when(F.col("status") == "ok", F.concat_ws("/", "n", "sum_h", "xor_h", "ncols")).alias("fp"))
    gold = one.select(F.col("sql").alias("gold_sql"), F.col("t_pred").alias("t_gold"), F.col("fp").alias("gold_fp"))
    out = cands.join(one, "sql", "left").join(gold, "gold_sql", "left")
    return out.withColumn("equal", F.coalesce(F.col("fp") == F.col("gold_fp"), F.lit(False))).drop("gold_fp")
