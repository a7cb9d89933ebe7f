"""Tables, external question sets, dictionaries of schemas, and sinks."""

from __future__ import annotations

import re
from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The three databases that questions refer to, and their tables.
DATABASES = {
    "retail": ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"),
    "web": ("documents", "labels", "pages", "benchmark", "embeddings"),
    "activity": ("events", "conversations"),
}
TABLES = tuple(t for ts in DATABASES.values() for t in ts)
KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey",
        "lineitem": "l_orderkey", "documents": "doc_id", "labels": "doc_id", "pages": "page_id", "benchmark": "item_id", "embeddings": "vec_id",
        "events": "event_id", "conversations": "conv_id"}
DICTIONARY_MOST = 100_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """``text`` over those of the given tables that it names; they are named inside the statement, so no view stays behind."""
    named = [f"{t} AS (SELECT * FROM parquet.`{sf_dir}/{t}.parquet`)" for t in TABLES if re.search(rf"\b(?:FROM|JOIN)\s+{t}\b", text)]
    return spark.sql(f"WITH {', '.join(named)} {text}" if named else text)


def tables(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> dict[str, DataFrame]:
    """Tables by name; their schemas, a small job each, are read side by side."""
    with ThreadPoolExecutor(len(names)) as pool:
        return dict(zip(names, pool.map(inheritable_thread_target(spark)(lambda n: table(spark, sf_dir, n)), names), strict=True))


def views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for n, df in tables(spark, sf_dir, names).items():
        df.createOrReplaceTempView(n)


def schema_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(db_id, tab, col, dtype)``: a row per column of each database, bounded by the number of columns there are."""
    rows = [(db, t, c, kind) for db, ts in DATABASES.items() for t in ts for c, kind in table(spark, sf_dir, t).dtypes]
    if len(rows) > DICTIONARY_MOST:
        raise ValueError("a dictionary of this size is not to be broadcast")
    return spark.createDataFrame(rows, "db_id string, tab string, col string, dtype string")


def owners(spark: SparkSession, sf_dir: str) -> dict[str, str]:
    """Column -> table, for columns that only one table has."""
    seen: dict[str, list[str]] = {}
    for t, df in tables(spark, sf_dir).items():
        for c in df.columns:
            seen.setdefault(c, []).append(t)
    return {c: ts[0] for c, ts in seen.items() if len(ts) == 1}


QUESTIONS = "question_id long, suite string, db_id string, source string, tier string, family string, question string, gold_sql string"


def external_questions(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    """Question sets from outside as JSON lines, CSV with header, or Parquet, under a fixed schema."""
    if kind == "json":
        return spark.read.schema(QUESTIONS).json(path)
    if kind == "csv":
        return spark.read.schema(QUESTIONS).option("header", True).option("escape", '"').option("multiLine", True).csv(path)
    return spark.read.schema(QUESTIONS).parquet(path)


def jdbc(spark: SparkSession, url: str, name: str, column: str, low: int, high: int, parts: int) -> DataFrame:
    """A table of an outside engine, read in parallel ranges; needs that engine's driver on the class path."""
    return (spark.read.format("jdbc").option("url", url).option("dbtable", name).option("partitionColumn", column)
            .option("lowerBound", low).option("upperBound", high).option("numPartitions", parts).load())


#: What each role may read: views over tables, never the tables, and functions of its own.
GRANTS = {"auditor": (("order_totals",), ("sum", "count", "avg", "min", "max")), "analyst": (("order_totals", "open_orders"), ("sum", "count", "avg", "min", "max", "net_price", "year"))}


def granted_views(spark: SparkSession, sf_dir: str, path: str) -> None:
    """A materialised view (written once under ``path``), a view that hides rows and columns, and a function of the schema."""
    totals = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n_orders"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))
    totals.write.mode("overwrite").parquet(f"{path}/order_totals")
    spark.read.parquet(f"{path}/order_totals").createOrReplaceTempView("order_totals")
    table(spark, sf_dir, "orders").where("o_orderstatus = 'O'").select("o_orderkey", "o_orderdate", "o_totalprice").createOrReplaceTempView("open_orders")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION net_price(price DOUBLE, cut DOUBLE) RETURNS DOUBLE RETURN price * (1 - cut)")


def keep(df: DataFrame, path: str, by: list[str] | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.mode(mode)
    (writer.partitionBy(*by) if by else writer).parquet(path)


def keep_records(df: DataFrame, path: str) -> None:
    """Training records as JSON lines."""
    df.select(F.to_json(F.struct("*")).alias("value")).write.text(path)
