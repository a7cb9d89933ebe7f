"""Shared plumbing of the corpus operators: tables in the cluster's shared folder, and files beside them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..store import Shelf


class Scratch(Shelf):
    """Written tables that cut lineage, so a lost executor costs a read and no recomputation."""

    def save(self, df: DataFrame, name: str) -> DataFrame:
        return self.put(df, name)

    def save_small(self, df: DataFrame, name: str) -> DataFrame:
        """For columns of plain bytes: a stronger codec than the session's."""
        df.write.option("compression", "zstd").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))


def text_of(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def packed_rows(docs: DataFrame) -> Column:
    """The caller's columns as one struct, so that no working name can meet one of theirs."""
    return F.struct(*[F.col(f"`{c.replace('`', '``')}`") for c in docs.columns])


def unpacked(rows: DataFrame, column: str, names: list[str]) -> DataFrame:
    return rows.select(*[F.col(column).getField(c).alias(c) for c in names])


def prefix_sums(totals: DataFrame, key: str, amount: str, out: str) -> DataFrame:
    """Running total of ``amount`` before each ``key``; ``totals`` has one row per partition or bucket, never per record."""
    from pyspark.sql import Window

    before = Window.orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    return totals.withColumn(out, F.coalesce(F.sum(amount).over(before), F.lit(0)).cast("long"))


def parts_for(spark, amount: int, each: int) -> int:
    """Tasks for ``amount`` bytes or files at ``each`` a task, and no fewer than the cluster has cores for."""
    return max(1, min(max(-(-amount // each), spark.sparkContext.defaultParallelism), max(1, amount)))
