"""Training data: cleaning, deduplication, order, mixing, statistics, leakage guard, longer prompts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import number

PARTS = 256


def normalised(text: Column) -> Column:
    """Lower case, runs of white space as one space, ends trimmed."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"\s+", " "))


def clean(df: DataFrame, text: str = "text", least: int = 3) -> DataFrame:
    """Even white space; rows of fewer than ``least`` words go."""
    even = F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), r"\s+", " "))
    return df.withColumn(text, even).where(F.size(F.split(even, " ")) >= least)


def dedup(df: DataFrame, how: str = "exact", text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row (smallest key) per text; ``normalised`` compares cleaned lower-case texts. Only digests are grouped.

    Null texts are one text of their own (``normalised``: the empty one); a text whose rows all lack a key keeps a row."""
    digest = F.coalesce(F.sha2(F.col(text) if how == "exact" else normalised(F.col(text)), 256), F.lit(""))
    keep = df.groupBy(digest.alias("__h")).agg(F.min(key).alias("__k"))
    marked = df.withColumn("__d", digest)
    return marked.join(keep, F.col("__d").eqNullSafe(F.col("__h")) & F.col(key).eqNullSafe(F.col("__k")), "left_semi").dropDuplicates(["__d"]).drop("__d")


def shuffle(df: DataFrame, seed: int, key: str = "doc_id") -> DataFrame:
    """An order that depends on seed and key alone."""
    return df.orderBy(number(F.lit(seed), F.col(key)), key)


def mix(df: DataFrame, fractions: dict[str, float], by: str = "suite", key: str = "question_id", seed: int = 3) -> DataFrame:
    """Keeps the named share of each source by a hash of the key, so that layouts agree."""
    u = F.pmod(number(F.lit(seed), F.col(key)), F.lit(10_000)) / 10_000.0
    share = F.lit(0.0)
    for name, f in fractions.items():
        share = F.when(F.col(by) == name, f).otherwise(share)
    return df.where(u < share)


def stats(df: DataFrame, by: list[str], question: str, query: str | None = None) -> DataFrame:
    words = lambda c: F.size(F.filter(F.split(F.coalesce(F.col(c), F.lit("")), r"\s+"), lambda x: x != ""))
    aggs = [F.count("*").alias("items"), F.avg(words(question)).alias("tokens_question")]
    return df.groupBy(*by).agg(*aggs, *([F.avg(words(query)).alias("tokens_query")] if query else []))


def truncate(df: DataFrame, most: int = 8192, text: str = "text") -> DataFrame:
    return df.where(F.size(F.split(F.col(text), r"\s+")) <= most)


def grams(text: Column, n: int) -> Column:
    """Distinct hashes of all ``n``-word sequences. Words are hashed once; hashes of longer sequences come from two
    shorter ones side by side (or, for odd remainders, overlapping), so the work is linear in the text, whatever ``n``."""
    words = F.transform(F.filter(F.split(normalised(text), " "), lambda x: x != ""), lambda x: F.xxhash64(x))
    hashes, have = words, 1

    def longer(step: int):
        part = lambda h, at: F.slice(h, F.lit(at), F.greatest(F.size(h) - step, F.lit(0)))
        return lambda h: F.zip_with(part(h, 1), part(h, step + 1), lambda a, b: F.xxhash64(a, b))

    while have < n:
        step = min(have, n - have)
        hashes, have = F.get(F.transform(F.array(hashes), longer(step)), F.lit(0)), have + step
    return F.array_distinct(hashes)


def contaminated(docs: DataFrame, tests: DataFrame, n: int = 8, text: str = "text", key: str = "doc_id", test_key: str = "item_id") -> DataFrame:
    """``(key, hits)``: documents that share an ``n``-word sequence with a test passage, and how many test passages.
    Sequences meet by hash, eight bytes each. Spark sends the tests' hashes to all tasks while they are small, so that
    documents' hashes pass by without a shuffle; larger ones meet by a shuffle of hashes."""
    marks = tests.select(test_key, F.explode(grams(F.col(text), n)).alias("h"))
    seen = docs.select(key, F.explode(grams(F.col(text), n)).alias("h"))
    return seen.join(marks, "h").groupBy(key).agg(F.countDistinct(test_key).alias("hits"))


def decontaminate(docs: DataFrame, tests: DataFrame, n: int = 8, key: str = "doc_id") -> DataFrame:
    return docs.join(contaminated(docs, tests, n, key=key), key, "left_anti")


def lengthen_schema(questions: DataFrame, dictionary: DataFrame, distractors: int) -> DataFrame:
    """Prompts with the tables of the question's own database and ``distractors`` tables of others, for long contexts.
    The listing per database is as small as the dictionary and joins by database."""
    tables = dictionary.groupBy("db_id", "tab").agg(F.sort_array(F.collect_list("col")).alias("cols")).select(
        "db_id", F.concat(F.col("tab"), F.lit("("), F.array_join("cols", ", "), F.lit(")")).alias("ddl"))
    own = tables.groupBy("db_id").agg(F.sort_array(F.collect_list("ddl")).alias("own"))
    dbs = own.select("db_id")
    others = (dbs.alias("a").join(tables.alias("b"), F.col("a.db_id") != F.col("b.db_id")).groupBy("a.db_id")
              .agg(F.slice(F.sort_array(F.collect_list("b.ddl")), 1, distractors).alias("rest")).select(F.col("db_id"), "rest"))
    listing = own.join(others, "db_id", "left").select("db_id", F.array_join(F.concat("own", F.coalesce("rest", F.array().cast("array<string>"))), "; ").alias("listing"))
    return questions.join(F.broadcast(listing), "db_id").withColumn("prompt", F.concat("listing", F.lit("\n"), "question")).drop("listing")


def value_hints(df: DataFrame, columns: list[str], k: int = 3) -> DataFrame:
    """The ``k`` most frequent values of each column, as hints for a prompt: the best of each part of a column's values
    first, then the best of these, so that no task ranks all values of a column."""
    cells = F.array(*[F.struct(F.lit(c).alias("col"), F.col(c).cast("string").alias("value")) for c in columns])
    counts = df.select(F.explode(cells).alias("x")).groupBy("x.col", "x.value").agg(F.count("*").alias("n"))
    best = lambda *by: F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("n"), "value"))
    some = counts.withColumn("part", F.pmod(F.xxhash64("value"), F.lit(PARTS))).withColumn("place", best("col", "part")).where(F.col("place") <= k)
    return some.withColumn("place", best("col").cast("long")).where(F.col("place") <= k).drop("part")


def noisy(questions: DataFrame, rate: float, text: str = "question", seed: int = 5) -> DataFrame:
    """Deterministic typos: in a hash-chosen share of words two inner letters change places."""
    words = F.split(F.col(text), " ")
    odd = lambda w, i: (F.pmod(number(F.lit(seed), F.col("question_id"), i, w), F.lit(1000)) < int(1000 * rate)) & (F.length(w) >= 4)
    swap = lambda w: F.concat(F.substring(w, 1, 1), F.substring(w, 3, 1), F.substring(w, 2, 1), F.substring(w, 4, 1 << 20))
    return questions.withColumn(text, F.array_join(F.transform(words, lambda w, i: F.when(odd(w, i), swap(w)).otherwise(w)), " "))
