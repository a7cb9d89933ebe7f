"""Schema linking: elements of a query, resolved against a dictionary and compared with gold's."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.sqltext import elements

WORD = r"[A-Za-z_][A-Za-z0-9_]*"


def elements_of(sql: Column, owners: dict[str, str] | None = None) -> Column:
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            yield pa.array([None if s is None else elements(s, owners) for s in b.to_pylist()], pa.list_(pa.string()))

    return F.arrow_udf(run, T.ArrayType(T.StringType()))(sql)


def with_elements(df: DataFrame, columns: list[str], owners: dict[str, str] | None = None) -> DataFrame:
    """Adds ``<column>_elements`` for each text column; every distinct text is read once."""
    texts = None
    for c in columns:
        one = df.select(F.col(c).alias("__sql"))
        texts = one if texts is None else texts.union(one)
    known = texts.where("__sql IS NOT NULL").distinct().withColumn("__e", elements_of(F.col("__sql"), owners))
    for c in columns:
        df = df.join(known.select(F.col("__sql").alias(c), F.col("__e").alias(f"{c}_elements")), c, "left")
    return df


def score(df: DataFrame, pred: str, gold: str) -> DataFrame:
    """``link_set_ok`` (subset; the empty set is one), ``link_equal``, ``link_f1`` and ``n_elements`` from element arrays."""
    p, g = F.coalesce(F.col(pred), F.array().cast("array<string>")), F.coalesce(F.col(gold), F.array().cast("array<string>"))
    both = F.size(F.array_intersect(p, g))
    return df.withColumns({"link_set_ok": F.size(F.array_except(p, g)) == 0, "link_equal": (F.size(F.array_except(p, g)) == 0) & (F.size(F.array_except(g, p)) == 0),
                           "link_f1": F.when(F.size(p) + F.size(g) == 0, 1.0).otherwise(2.0 * both / (F.size(p) + F.size(g))), "n_elements": F.size(p)})


def resolve(df: DataFrame, column: str, dictionary: DataFrame, key: str) -> DataFrame:
    """``(key, known array, unknown array)``: elements found in the dictionary (one row a column; size checked where it
    is built) and those that are not."""
    names = dictionary.select(F.concat_ws(".", "tab", "col").alias("element")).union(dictionary.select("tab")).distinct().withColumn("there", F.lit(True))
    rows = df.select(key, F.explode_outer(column).alias("element")).join(F.broadcast(names), "element", "left")
    return rows.groupBy(key).agg(F.sort_array(F.collect_set(F.when(F.col("there"), F.col("element")))).alias("known"),
                                 F.sort_array(F.collect_set(F.when(F.col("there").isNull(), F.col("element")))).alias("unknown"))


def ground(questions: DataFrame, dictionary: DataFrame, text: str = "question", most: int = 3) -> DataFrame:
    """Reverse linking: question words that are a column's or table's words, or one edit away from them.

    Words meet dictionary words by equality on a deletion key (the word, or the word less one letter), so there is no
    comparison of all with all."""
    def keys(w: Column) -> Column:
        cut = F.transform(F.sequence(F.lit(1), F.length(w)), lambda i: F.concat(F.substring(w, F.lit(1), i - 1), F.substring(w, i + 1, F.length(w))))
        return F.array_distinct(F.concat(F.array(w), F.when(F.length(w) >= 5, cut).otherwise(F.array().cast("array<string>"))))

    words = questions.select("question_id", F.explode(F.array_distinct(F.split(F.lower(text), r"[^a-z0-9]+"))).alias("w")).where("length(w) >= 3")
    parts = (dictionary.select(F.concat_ws(".", "tab", "col").alias("element"), F.explode(F.split(F.concat_ws("_", "tab", "col"), "_")).alias("part"))
             .where("length(part) >= 3").distinct())
    left = words.select("question_id", "w", F.explode(keys(F.col("w"))).alias("k"))
    right = parts.select("element", "part", F.explode(keys(F.col("part"))).alias("k"))
    hits = (left.join(F.broadcast(right), "k").withColumn("d", F.levenshtein("w", "part")).where("d <= 1")
            .groupBy("question_id", "element").agg(F.countDistinct("w").alias("hits"), F.min("d").alias("d")))
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy("question_id").orderBy(F.desc("hits"), "d", "element"))
    return hits.withColumn("place", place).where(F.col("place") <= most)


def contents(mine: DataFrame, other: DataFrame, tables: dict[str, DataFrame]) -> DataFrame:
    """``(tab, col, n, digest)``: count and digest of the values of each column of ``tables`` that one dictionary has and the
    other lacks; equal columns have equal digests in whatever order rows come. Each table is read once, these columns only."""
    only, out = mine.join(other, ["db_id", "tab", "col"], "left_anti").select("tab", "col").collect(), None  # columns of the schema at most
    for t, df in tables.items():
        cols = sorted(r["col"] for r in only if r["tab"] == t)
        cells = [F.struct(F.lit(t).alias("tab"), F.lit(c).alias("col"), F.count(c).alias("n"), F.sum(F.xxhash64(c).cast("decimal(38,0)")).alias("digest")) for c in cols]
        one = df.agg(F.array(*cells).alias("x")).select(F.inline("x")) if cols else None
        out = one if out is None else out if one is None else out.unionByName(one)
    return out if out is not None else mine.sparkSession.createDataFrame([], "tab string, col string, n long, digest decimal(38,0)")


def drift(old: DataFrame, new: DataFrame, was: DataFrame | None = None, now: DataFrame | None = None) -> DataFrame:
    """Columns gained, lost and probably renamed (same table and type, nearest name) between two dictionaries. With
    ``contents`` of both sides a column that holds the same values goes before one that has the nearer name."""
    from pyspark.sql import Window

    gone, came = old.join(new, ["db_id", "tab", "col"], "left_anti"), new.join(old, ["db_id", "tab", "col"], "left_anti")
    if was is not None and now is not None:
        gone, came = gone.join(F.broadcast(was), ["tab", "col"], "left"), came.join(F.broadcast(now), ["tab", "col"], "left")
        same = F.coalesce((F.col("g.n") == F.col("c.n")) & F.col("g.digest").eqNullSafe(F.col("c.digest")), F.lit(False))
    else:
        same = F.lit(True)
    pairs = gone.alias("g").join(came.alias("c"), ["db_id", "tab", "dtype"]).select("db_id", "tab", F.col("g.col").alias("was"), F.col("c.col").alias("now"),
                                                                                    same.alias("same"), F.levenshtein("g.col", "c.col").alias("distance"))
    first = F.row_number().over(Window.partitionBy("db_id", "tab", "was").orderBy(F.desc("same"), "distance", "now"))
    best = pairs.withColumn("k", first).where("k = 1").drop("k")
    lost = gone.join(best.select("db_id", "tab", F.col("was").alias("col"), "now"), ["db_id", "tab", "col"], "left")
    return (lost.select("db_id", "tab", F.col("col").alias("was"), "now", F.when(F.col("now").isNull(), "lost").otherwise("renamed").alias("change"))
            .union(came.join(best.select("db_id", "tab", F.col("now").alias("col")), ["db_id", "tab", "col"], "left_anti")
                   .select("db_id", "tab", F.lit(None).cast("string"), "col", F.lit("gained"))))
