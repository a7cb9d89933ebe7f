"""Clause matching and error classes of candidate and gold texts, over distinct pairs."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import sqltext

KIND = T.StructType([T.StructField("em", T.BooleanType()), T.StructField("em_no_values", T.BooleanType()), T.StructField("clause_share", T.DoubleType()),
                     T.StructField("error", T.StringType()), T.StructField("errors", T.ArrayType(T.StringType()))])


def decompose(sql: Column, values: bool = True) -> Column:
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            rows = [None if s is None else list(sqltext.decompose(s, values).items()) for s in b.to_pylist()]
            yield pa.array(rows, pa.map_(pa.string(), pa.list_(pa.string())))

    return F.arrow_udf(run, T.MapType(T.StringType(), T.ArrayType(T.StringType())))(sql)


def _judge(gold: str | None, pred: str | None) -> dict:
    g, p = sqltext._known(gold, True), sqltext._known(pred, True)
    share = sum(g[c] == p.get(c) for c in g) / len(g) if g else 0.0
    wrong = sqltext.differences(gold, pred) if pred is not None else list(sqltext.ERRORS[:1])
    return {"em": sqltext.set_match(gold, pred), "em_no_values": sqltext.set_match(gold, pred, False), "clause_share": share,
            "error": wrong[0] if wrong else None, "errors": wrong}


def judged(df: DataFrame, gold: str = "gold_sql", pred: str = "sql") -> DataFrame:
    """Adds ``em``, ``em_no_values``, ``clause_share``, ``error`` (first class) and ``errors`` (all that hold)."""
    def run(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        kind = pa.struct([("em", pa.bool_()), ("em_no_values", pa.bool_()), ("clause_share", pa.float64()), ("error", pa.string()), ("errors", pa.list_(pa.string()))])
        for g, p in batches:
            yield pa.array([_judge(a, b) for a, b in zip(g.to_pylist(), p.to_pylist(), strict=True)], kind)

    once = df.select(gold, pred).distinct().withColumn("__j", F.arrow_udf(run, KIND)(F.col(gold), F.col(pred)))
    left, right = df.alias("l"), once.alias("r")
    on = F.col(f"l.{gold}").eqNullSafe(F.col(f"r.{gold}")) & F.col(f"l.{pred}").eqNullSafe(F.col(f"r.{pred}"))
    return left.join(right, on, "left").select("l.*", "r.__j.*")


def exact(a: Column, b: Column) -> Column:
    """String equality after case and white space are evened."""
    even = lambda c: F.trim(F.regexp_replace(F.lower(c), r"[\s;]+", " "))
    return even(a) == even(b)


COARSE = {"table": "schema linking", "attribute": "schema linking", "condition": "condition", "value": "condition"}


def shares(df: DataFrame, by: list[str], scheme: str = "fine", column: str = "error") -> DataFrame:
    """Share of each error class within ``by``."""
    cls = F.col(column)
    if scheme == "coarse":
        cls = F.when(cls.isin("table", "attribute"), "schema linking").when(cls.isin("condition", "value"), "condition").otherwise("structural")
    counts = df.where(F.col(column).isNotNull()).groupBy(*by, cls.alias("class")).agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(*by)))


def distribution(df: DataFrame, arm: str = "arm", suite: str = "suite", column: str = "error") -> DataFrame:
    """Counts of error classes by arm and suite with all subtotals."""
    return (df.where(F.col(column).isNotNull()).cube(arm, suite, column).agg(F.count("*").alias("n"), F.grouping_id().alias("level")))


def reduction(df: DataFrame, base: str, arm: str = "arm", suite: str = "suite", column: str = "error") -> DataFrame:
    """Percent by which each arm has fewer errors of a class than ``base``; null where base has none."""
    counts = df.where(F.col(column).isNotNull()).groupBy(arm, suite, column).agg(F.count("*").alias("n"))
    before = counts.where(F.col(arm) == base).select(suite, column, F.col("n").alias("n_base"))
    grid = df.select(arm, suite).distinct().join(before, suite)
    return (grid.join(counts, [arm, suite, column], "left").where(F.col(arm) != base)
            .select(arm, suite, column, F.coalesce("n", F.lit(0)).alias("n"), "n_base", (100.0 * (F.col("n_base") - F.coalesce("n", F.lit(0))) / F.col("n_base")).alias("reduction")))
