"""Plan-level signals: what the optimiser says of a query before any run."""

from __future__ import annotations

import re
from collections.abc import Iterable

from pyspark.sql import SparkSession

from . import execution

SHUFFLE_PENALTY = 0.25


def features(spark: SparkSession, sql: str) -> dict[str, float]:
    """Node counts, joins, exchanges and the sum of estimated sizes over all nodes of the optimised plan."""
    df = spark.sql(sql)
    qe = df._jdf.queryExecution()
    nodes, size, todo = 0, 0, [qe.optimizedPlan()]
    while todo:
        node = todo.pop()
        nodes += 1
        size += int(str(node.stats().sizeInBytes()))
        kids = node.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    physical = qe.sparkPlan().toString()
    exchanges = len(re.findall(r"Aggregate\(.*partial|SortMergeJoin|ShuffledHashJoin|Sort \[|partial_", physical))
    return {"nodes": nodes, "bytes": float(size), "joins": len(re.findall(r"Join", qe.optimizedPlan().toString())), "exchanges": exchanges}


def cost(spark: SparkSession, sql: str) -> float:
    """Bytes of all nodes, more for each shuffle; the root's estimate alone would say nothing."""
    f = features(spark, sql)
    return f["bytes"] * (1 + SHUFFLE_PENALTY * f["exchanges"])


def ratio(spark: SparkSession, gold: str, pred: str) -> float:
    """Efficiency part of a reward by plan: gold's cost over the candidate's, at most 1."""
    c = cost(spark, pred)
    return 1.0 if c == 0 else min(1.0, cost(spark, gold) / c)


def within(spark: SparkSession, sqls: list[str], limit: float) -> list[str]:
    """The texts whose plans cost no more than ``limit``; texts that cannot be planned cost too much."""
    from pyspark.errors import AnalysisException, ParseException

    def fits(sql: str) -> bool:
        try:
            return cost(spark, sql) <= limit
        except (ParseException, AnalysisException):
            return False

    return [s for s in sqls if fits(s)]


def results(spark: SparkSession, sqls: list[str], tables: Iterable[str], users: int = 8) -> dict[str, tuple]:
    """Fingerprints of the texts that ran, ``users`` of them at a time; those that failed are left out."""
    texts = spark.createDataFrame([(s,) for s in sqls], "sql string")
    runs = execution.run(spark, texts, tables, repeats=0, concurrency=users).where("status = 'ok'")
    return {r["sql"]: (r["n"], r["sum_h"], r["xor_h"], r["ncols"]) for r in runs.select("sql", "n", "sum_h", "xor_h", "ncols").collect()}  # a row a text


def critic(spark: SparkSession, sqls: list[str], seconds: list[float]):
    """A linear model of log time on plan features, fitted by least squares."""
    import numpy as np

    rows = [features(spark, s) for s in sqls]
    x = np.array([[1.0, np.log1p(f["nodes"]), np.log1p(f["bytes"]), f["joins"], f["exchanges"]] for f in rows])
    weights, *_ = np.linalg.lstsq(x, np.log(np.maximum(seconds, 1e-6)), rcond=None)
    return weights
