"""Line-first quality rules in DataFrame functions only.

Base counts decide ``base_failed``. The method's own verdict goes line by line: a line fails by punctuation (shouting or
symbol clusters on much of its words), navigation (short items between separators) or boilerplate (stock phrases).
Failing lines are removed, and a document that loses too much of its text is rejected.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import packed_rows, text_of, unpacked

SPACES, SPACE_CLASS = " \t\n\x0b\f\r", r"[\x20\x09-\x0D]+"
SYMBOLS = r"[^#*$%&|<>]+"
WINDOW = 8
#: Fixed stock phrases, lower case, of web boilerplate.
BOILERPLATE = ("lorem ipsum", "javascript", "cookie", "all rights reserved", "privacy policy", "terms of use", "terms of service",
               "click here", "subscribe to", "sign up", "log in", "share this", "read more")
#: Separators between navigation items.
SEPARATORS = r" [|\x{00BB}\x{203A}\x{00B7}\x{2022}] "


@dataclass(frozen=True)
class LineRules:
    """A line fails if clusters of two or more marks stand on over ``cluster_share`` of its words, or if at least
    ``nav_items`` separators leave no more than ``nav_words`` words an item, or if it is short (``stock_words``) and has a
    stock phrase. A document is rejected if failing lines hold over ``max_lost`` of its word characters."""

    cluster_share: float = 0.3
    nav_items: int = 2
    nav_words: float = 3.0
    stock_words: int = 25
    max_lost: float = 0.5
    min_words: int = 20
    max_repeat_percent: int = 30


def _words(text: Column) -> Column:
    spaced = F.regexp_replace(text, r"[\x09-\x0D]", " ")
    return F.array_remove(F.split(spaced, " "), "")


def _chars(text: Column) -> Column:
    return F.length(F.regexp_replace(text, SPACE_CLASS, ""))


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` over ``value``, which is computed once however often ``body`` names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _windows(words: Column) -> Column:
    """Hashes of all eight-word windows by doubling (1, 2, 4, 8 words), so the work is linear in the text."""
    hashes = F.transform(words, lambda w: F.xxhash64(w))

    def doubled(step: int) -> Callable[[Column], Column]:
        part = lambda h, at: F.slice(h, F.lit(at), F.size(h) - step)
        return lambda h: F.zip_with(part(h, 1), part(h, step + 1), lambda a, b: F.xxhash64(a, b))

    for step in (1, 2, 4):
        hashes = _let(hashes, doubled(step))
    return hashes


def _covered(windows: Column) -> Column:
    """Words in windows found at least twice: windows sorted by hash and place, equal neighbours kept, and each start
    counts what the start before it doesn't cover."""
    ordered = F.sort_array(F.transform(windows, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))

    def places(o: Column) -> Column:
        same = lambda x, k: F.get(o, k)["h"] == x["h"]
        return F.transform(o, lambda x, k: F.when(
            F.coalesce(F.when(k > 0, same(x, k - 1)), F.lit(False)) | F.coalesce(same(x, k + 1), F.lit(False)), x["i"]))

    starts = F.sort_array(F.filter(_let(ordered, places), lambda i: i.isNotNull()))
    return F.aggregate(
        starts, F.struct(F.lit(0).alias("n"), F.lit(-WINDOW).alias("last")),
        lambda acc, i: F.struct((acc["n"] + F.least(F.lit(WINDOW), i - acc["last"])).alias("n"), i.alias("last")))["n"]


def measured(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """``row`` (the caller's columns as one struct, so that no name clashes), the text, the base counts, ``base_failed``,
    ``lost`` (share of word characters on failing lines) and ``kept``, under names with ``__`` in front.

    Null text counts as empty: zero words, so the base fails. Repeated rows are judged one by one. Empty table: no rows.
    """
    text = F.col("__text")
    line = lambda x: x.rlike(r"[^\x20\x09-\x0D]")
    base = (docs.select(packed_rows(docs).alias("row"), text_of().alias("__text"))
            .withColumn("__words", _words(text)).withColumn("__lines", F.filter(F.split(text, "\n"), line))
            .withColumn("__windows", F.when(F.size("__words") >= WINDOW, _windows(F.col("__words")))))
    base = (base.withColumn("__n_words", F.size("__words").cast("long"))
            .withColumn("__word_chars", F.length(F.array_join("__words", "")).cast("long"))
            .withColumn("__n_symbols", F.length(F.regexp_replace(text, SYMBOLS, "")).cast("long"))
            .withColumn("__n_dup_lines", (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("long"))
            .withColumn("__n_repeat_words", F.when(
                F.col("__windows").isNotNull() & (F.size(F.array_distinct("__windows")) < F.size("__windows")), _covered(F.col("__windows")))
                .otherwise(F.lit(0)).cast("long")))
    failing = F.filter("__lines", lambda x: _line_fails(x, rules))
    lost = F.aggregate(failing, F.lit(0), lambda n, x: n + _chars(x))
    return (base.withColumn("__base_failed", (F.col("__n_words") < rules.min_words)
                            | (100 * F.col("__n_repeat_words") > rules.max_repeat_percent * F.col("__n_words")))
            .withColumn("__lost", F.when(F.col("__word_chars") > 0, lost / F.col("__word_chars")).otherwise(F.lit(0.0)))
            .withColumn("__kept", ~F.col("__base_failed") & (F.col("__lost") <= rules.max_lost)))


def _line_fails(x: Column, rules: LineRules) -> Column:
    spaces = F.length(x) - F.length(F.replace(x, F.lit(" "), F.lit(""))) + 1
    clusters = F.regexp_count(x, F.lit(r"[!?#*$%&|<>=~^]{2,}"))
    items = F.regexp_count(x, F.lit(SEPARATORS))
    stock = F.lower(x).rlike("|".join(BOILERPLATE))
    return ((clusters > rules.cluster_share * spaces)
            | ((items >= rules.nav_items) & (spaces - items <= rules.nav_words * (items + 1)))
            | ((spaces <= rules.stock_words) & stock))


RESULT = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def verdicts(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """A row for each row of ``docs``: base counts, base verdict and the verdict by lines. Null and empty text: no words,
    so the base fails. Rows that repeat, ids too, are judged alike. Other columns are ignored. Empty table: no rows."""
    return measured(docs, rules).select(F.col("row.doc_id").alias("doc_id"), *[F.col(f"__{c}").alias(c) for c in RESULT])


def kept(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """The documents that stay, with the columns and whole text they had; null and empty texts go, repeated rows stay or
    go together, an empty table gives none."""
    # a filter would be pushed below the counts and compute them anew for each use; an array of no row or one is not
    rows = measured(docs, rules).select(F.explode(F.filter(F.array(F.struct("row", "__kept")), lambda x: x["__kept"])).alias("x"))
    return unpacked(rows.select("x.row"), "row", docs.columns)


def cleaned(docs: DataFrame, rules: LineRules = LineRules()) -> DataFrame:
    """``(doc_id, text)`` of the kept documents without their failing lines; rows as in ``kept``."""
    lines = F.filter(F.split(F.col("__text"), "\n"), lambda x: ~_line_fails(x, rules))
    return measured(docs, rules).where("__kept").select(F.col("row.doc_id").alias("doc_id"), F.array_join(lines, "\n").alias("text"))


def oracle(rules: LineRules = LineRules()) -> str:
    stock = "|".join(BOILERPLATE)
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT r, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM d),
p AS (SELECT r, unnest(ws) AS word, unnest(range(len(ws))) AS i FROM w),
g AS (SELECT r, i, string_agg(word, ' ') OVER (PARTITION BY r ORDER BY i ROWS BETWEEN CURRENT ROW AND 7 FOLLOWING) AS gram,
             count(*) OVER (PARTITION BY r ORDER BY i ROWS BETWEEN CURRENT ROW AND 7 FOLLOWING) AS n FROM p),
t AS (SELECT r, i, count(*) OVER (PARTITION BY r, gram) AS times FROM g WHERE n = 8),
s AS (SELECT r, sum(least(8, coalesce(nxt - i, 8))) AS covered
      FROM (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS nxt FROM t WHERE times > 1) GROUP BY r),
l AS (SELECT r, unnest(ls) AS line FROM w),
f AS (SELECT r, sum(length(regexp_replace(line, '[\x20\x09-\x0D]+', '', 'g'))) AS lost FROM (
        SELECT r, line, length(line) - length(replace(line, ' ', '')) + 1 AS spaces,
               len(regexp_extract_all(line, '[!?#*$%&|<>=~^]{{2,}}')) AS clusters,
               len(regexp_extract_all(line, ' [|\x{{00BB}}\x{{203A}}\x{{00B7}}\x{{2022}}] ')) AS items FROM l)
      WHERE clusters > {rules.cluster_share} * spaces OR (items >= {rules.nav_items} AND spaces - items <= {rules.nav_words} * (items + 1))
         OR (spaces <= {rules.stock_words} AND regexp_matches(lower(line), '{stock}')) GROUP BY r),
b AS (SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
             CAST(length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
             CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines,
             CAST(coalesce(covered, 0) AS BIGINT) AS n_repeat_words, coalesce(lost, 0) AS lost
      FROM d JOIN w USING (r) LEFT JOIN s USING (r) LEFT JOIN f USING (r)),
j AS (SELECT *, n_words < {rules.min_words} OR 100 * n_repeat_words > {rules.max_repeat_percent} * n_words AS base_failed FROM b)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND CASE WHEN word_chars > 0 THEN CAST(lost AS DOUBLE) / word_chars ELSE 0 END <= {rules.max_lost} AS kept
FROM j"""
