"""Self-distillation: teacher attempts, filters for what was right, and records in all thinking modes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.response import NO_THINK, THINK, render
from .grouprl import Policy
from .judging import exact
from .mutate import think_of


def attempts(questions: DataFrame, teachers: dict[int, Policy], n: int, seed: int = 11) -> DataFrame:
    """``n`` attempts per question and teacher snapshot, in order."""
    out = None
    for snapshot, teacher in teachers.items():
        one = teacher.sample(questions, n, seed, snapshot).withColumn("snapshot", F.lit(snapshot)).withColumnRenamed("slot", "attempt")
        out = one if out is None else out.unionByName(one)
    return out


def keep_exact(df: DataFrame, rule: str = "text", gold: str = "gold_sql", pred: str = "sql") -> DataFrame:
    """First filter: outputs whose SQL is gold's text (case and space aside), or, ``rule="ex"``, whose rows are gold's."""
    return df.where(exact(F.col(pred), F.col(gold)) if rule == "text" else F.coalesce(F.col("correct"), F.lit(False)))


def keep_run(df: DataFrame, k: int = 3, take: str = "last", by: list[str] = ["question_id", "snapshot"], order: str = "attempt") -> DataFrame:  # noqa: B006
    """Second filter: items with ``k`` correct attempts in a row; the ``take`` ("last" or "first") attempt of the first run stays."""
    w = Window.partitionBy(*by).orderBy(order).rowsBetween(-(k - 1), 0)
    ends = df.withColumn("__ok", (F.count("*").over(w) == k) & (F.min(F.col("correct").cast("int")).over(w) == 1))
    first = ends.where("__ok").groupBy(*by).agg(F.min(order).alias("__end"))
    at = F.col("__end") if take == "last" else F.col("__end") - (k - 1)
    return df.join(first, by).where(F.col(order) == at).drop("__end")


def runs(df: DataFrame, by: list[str] = ["question_id"], order: str = "attempt") -> DataFrame:  # noqa: B006
    """Maximal runs of correct attempts (gaps and islands): start, end and length."""
    good = df.where("correct").withColumn("__island", F.col(order) - F.row_number().over(Window.partitionBy(*by).orderBy(order)))
    return good.groupBy(*by, "__island").agg(F.min(order).alias("first"), F.max(order).alias("last"), F.count("*").alias("length")).drop("__island")


def records(kept: DataFrame, modes: tuple[str, ...] = ("slow", "fast", "suppressed")) -> DataFrame:
    """Training records: kept reasoning goes into the think part of slow records; twins keep the other modes alive."""
    think = think_of(F.col("question"), F.col("tier"))
    cells = F.array(*[F.struct(F.lit(m).alias("mode"),
                               F.concat(F.col("question"), F.lit({"slow": THINK, "fast": NO_THINK}.get(m, ""))).alias("prompt"),
                               render(m, think, F.col("gold_sql")).alias("response")) for m in modes])
    return kept.select("question_id", "family", "suite", F.explode(cells).alias("r")).select("question_id", "family", "suite", "r.mode", "r.prompt", "r.response")


def rl_records(questions: DataFrame) -> DataFrame:
    """Prompts for training by reward: tags demanded, content and length free."""
    return questions.select("question_id", "family", "suite", F.lit("tags_only").alias("mode"), F.concat("question", F.lit(THINK)).alias("prompt"), "gold_sql")


def progressive(kept: DataFrame) -> DataFrame:
    """One record per question over all teacher snapshots, the latest one's."""
    w = Window.partitionBy("question_id").orderBy(F.desc("snapshot"), F.desc("attempt"))
    return kept.withColumn("__k", F.row_number().over(w)).where("__k = 1").drop("__k")
