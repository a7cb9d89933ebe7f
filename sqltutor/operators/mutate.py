"""Candidates: the place of the language model's answers is taken by fixed edits of each family's gold.

Edits act on the few templates; rows come from native string functions, so their number may be any.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.response import render
from ..sources.load import DATABASES, KEYS
from .suites import BY_ID

OTHER_TABLE = {"orders": "lineitem", "lineitem": "orders", "customer": "supplier", "supplier": "customer", "part": "lineitem", "nation": "region",
               "region": "nation", "events": "conversations", "documents": "labels", "pages": "benchmark", "conversations": "events", "embeddings": "labels"}
OTHER_COLUMN = {"l_extendedprice": "l_tax", "o_totalprice": "o_orderkey", "c_acctbal": "c_custkey", "p_type": "p_name", "p_size": "p_partkey", "n_name": "n_nationkey",
                "s_suppkey": "s_nationkey", "p_partkey": "p_size", "o_custkey": "o_orderkey", "s_name": "s_suppkey", "s_nationkey": "s_suppkey", "l_quantity": "l_tax",
                "c_custkey": "c_nationkey", "c_nationkey": "c_custkey", "p_brand": "p_type", "event_type": "props", "user_id": "event_id", "value": "event_id", "quality": "toxic",
                "n_chars": "doc_id", "source": "lang", "url": "html", "turn": "conv_id", "label": "vec_id", "text": "lang"}
OTHER_CALL = (("COUNT(DISTINCT", "MAX("), ("COUNT(*)", "MAX(1)"), ("SUM(", "AVG("), ("AVG(", "MAX("), ("MAX(", "MIN("), ("SELECT DISTINCT p_type", "SELECT UPPER(p_type)"),
              ("SELECT n_name", "SELECT UPPER(n_name)"), ("SELECT s_name", "SELECT UPPER(s_name)"), ("SELECT o_custkey", "SELECT ABS(o_custkey) + 1"),
              ("SELECT p_partkey", "SELECT ABS(p_partkey) + 1"), ("SELECT c_custkey", "SELECT ABS(c_custkey) + 1"), ("SELECT c_nationkey", "SELECT ABS(c_nationkey) + 99"))
#: Kinds in order of slots. What each does is measured (``replay``), not assumed.
KINDS = ("exact", "equivalent", "fast", "slow", "value", "operator", "function", "condition", "attribute", "table", "subquery", "clause", "syntax_error",
         "unknown_column", "bad_cast", "timeout", "no_fence", "think_in_suppressed", "empty_think_in_slow", "text_in_fast_think", "unclosed_tag")
#: Thinking mode that a kind answers in.
MODE = {"exact": "slow", "equivalent": "suppressed", "fast": "slow", "slow": "fast", "value": "slow", "operator": "slow", "function": "fast", "condition": "suppressed", "attribute": "slow",
        "table": "fast", "subquery": "slow", "clause": "suppressed", "syntax_error": "slow", "unknown_column": "fast", "bad_cast": "suppressed", "timeout": "fast", "no_fence": "slow",
        "think_in_suppressed": "suppressed", "empty_think_in_slow": "slow", "text_in_fast_think": "fast", "unclosed_tag": "slow"}
#: An answer that no limit of a few seconds lets through, and the tables that it may run away with.
RUNAWAY = ("SELECT COUNT(*) AS n FROM {table} AS a CROSS JOIN {table} AS b CROSS JOIN {table} AS c CROSS JOIN {table} AS d CROSS JOIN {table} AS e "
           "WHERE hash(a.{key}, b.{key}, c.{key}, d.{key}, e.{key}) = 7")
LARGEST = {"retail": "lineitem", "web": "documents", "activity": "events"}


def _dropped(gold: str) -> str:
    """The first WHERE without its last condition, or without the clause if it has one only."""
    begin = gold.index(" WHERE ")
    depth, at, last, end = 0, begin + 7, None, len(gold)
    for i in range(at, len(gold)):
        depth += (gold[i] == "(") - (gold[i] == ")")
        if depth < 0 or depth == 0 and re.match(r" (?:GROUP BY|ORDER BY|EXCEPT|UNION|INTERSECT|LIMIT)\b", gold[i:]):
            end = i
            break
        if depth == 0 and gold.startswith(" AND ", i):
            last = i
    return gold[: begin if last is None else last] + gold[end:]


def edit(gold: str, kind: str) -> str:
    """A template's text with one edit. Kinds that only spoil the response keep the SQL."""
    table = re.search(r"\bFROM (\w+)", gold).group(1)
    where = lambda extra: gold.replace(" WHERE ", f" WHERE {extra} AND ", 1) if " WHERE " in gold else f"{gold} WHERE {extra}"
    if kind == "equivalent":
        return f"WITH answer AS ({gold}) SELECT * FROM answer"
    if kind == "slow":
        key = KEYS[table]
        return where(f"{table}.{key} IN (SELECT {key} FROM {table})") if " AS a JOIN" not in gold else where("a.event_id IN (SELECT event_id FROM events)")
    if kind == "value":
        for a, b in (("'{p1}'", "'{p1}x'"), ("{p2}", "{p2}9"), ("{p1}", "{p1}9")):
            if a in gold:
                return gold.replace(a, b, 1)
    if kind == "operator":
        for a, b in ((" > ", " <= "), (" < ", " >= "), (" <> ", " = "), (" >= ", " < "), (" LIKE ", " NOT LIKE ")):
            if a in gold:
                return gold.replace(a, b, 1)
        at = gold.find(" = ", gold.find(" WHERE "))
        return gold[:at] + " <> " + gold[at + 3 :]
    if kind == "function":
        for a, b in OTHER_CALL:
            if a in gold:
                return gold.replace(a, b, 1)
    if kind == "condition":
        return _dropped(gold)
    if kind == "attribute":
        found = min(((gold.find(c), c) for c in OTHER_COLUMN if re.search(rf"\b{c}\b", gold)), default=None)
        if not found:
            return gold
        other = "role" if table == "conversations" and found[1] == "text" else OTHER_COLUMN[found[1]]
        return re.sub(rf"(?<!\bAS )\b{found[1]}\b", other, gold)
    if kind == "table":
        return re.sub(rf"\bFROM {table}\b", f"FROM {OTHER_TABLE[table]}", gold, count=1)
    if kind == "subquery":
        return where(f"0 < (SELECT COUNT(*) FROM {table} WHERE {KEYS[table]} < 0)")
    if kind == "fast":
        return _lighter(gold)
    if kind == "timeout":
        big = LARGEST[next(db for db, ts in DATABASES.items() if table in ts)]
        return RUNAWAY.format(table=big, key=KEYS[big])
    if kind == "clause":
        if " ORDER BY " in gold and " OVER " not in gold:
            return re.sub(r" ORDER BY .*", "", gold) + " LIMIT 3"
        if ", " in gold.split(" FROM ")[0]:
            return gold + " LIMIT 0"
        return re.sub(r" GROUP BY .*", "", gold) + " GROUP BY 1 LIMIT 0" if "GROUP BY" not in gold and "COUNT" not in gold and "SUM" not in gold and "MAX" not in gold and "AVG" not in gold else gold + " LIMIT 0"
    if kind == "syntax_error":
        return gold.replace(" FROM ", " FORM ", 1)
    if kind == "unknown_column":
        return where(f"{table}.no_such_column = 1") if " AS a JOIN" not in gold else where("a.no_such_column = 1")
    if kind == "bad_cast":
        return where("CAST('x' AS INT) = 1")
    return gold


def _lighter(gold: str) -> str:
    """The same rows by less work where a rule knows how, else gold itself: a range of dates instead of a function of each,
    digests of texts instead of texts, EXISTS instead of a distinct join."""
    gold = re.sub(r"year\((\w+)\) = (\{p\d\}|\d{4})", r"\1 >= CAST('\2-01-01' AS TIMESTAMP) AND \1 < CAST('\2-01-01' AS TIMESTAMP) + INTERVAL '1' YEAR", gold)
    gold = gold.replace("SELECT text FROM documents", "SELECT md5(text) FROM documents").replace("GROUP BY text", "GROUP BY md5(text)")
    return gold.replace("l_quantity = (SELECT MAX(l_quantity) FROM lineitem)", "l_quantity >= (SELECT MAX(l_quantity) FROM lineitem WHERE l_quantity > 40)")


def _spoiled(kind: Column, sql: Column) -> Column:
    fence = F.concat(F.lit("```sql\n"), sql, F.lit("\n```"))
    tagged = lambda inside: F.concat(F.lit(f"<think>{inside}</think>\n\n"), fence)
    return (F.when(kind == "no_fence", F.concat(F.lit("<think>look at the tables</think>\n\n"), sql)).when(kind == "think_in_suppressed", tagged("hm"))
            .when(kind == "empty_think_in_slow", tagged("\n\n")).when(kind == "text_in_fast_think", tagged("quick thought"))
            .when(kind == "unclosed_tag", F.concat(F.lit("<think>no end\n\n"), fence)))


def think_of(question: Column, tier: Column) -> Column:
    steps = F.when(tier.isin("simple", "easy"), 1).when(tier.isin("moderate", "medium"), 2).otherwise(4)
    return F.concat(F.lit("The question is: "), question, F.repeat(F.lit(" Find the tables, join them, filter, then aggregate."), steps))


def candidates(questions: DataFrame, kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """One row per question and kind: ``(question_id, ..., slot, kind, mode, response, sql, n_tok_in, n_tok_out)``.

    Edited templates, one row per family and kind, are broadcast: their number is that of families times kinds."""
    spark = questions.sparkSession
    edits = spark.createDataFrame([(fid, slot, kind, MODE[kind], edit(f.gold, kind)) for fid, f in BY_ID.items() for slot, kind in enumerate(kinds)],
                                  "family string, slot int, kind string, mode string, template string")
    sql = F.replace(F.replace(F.col("template"), F.lit("{p1}"), F.col("p1")), F.lit("{p2}"), F.col("p2"))
    rows = questions.join(F.broadcast(edits), "family").withColumn("sql", sql)
    think = think_of(F.col("question"), F.col("tier"))
    said = F.coalesce(_spoiled(F.col("kind"), F.col("sql")), F.when(F.col("mode") == "slow", render("slow", think, F.col("sql")))
                      .when(F.col("mode") == "fast", render("fast", think, F.col("sql"))).otherwise(render("suppressed", think, F.col("sql"))))
    words = lambda c: F.size(F.split(F.trim(c), r"\s+"))
    rows = rows.withColumn("response", said)
    return rows.select("question_id", "suite", "db_id", "tier", "family", "question", "gold_sql", "slot", "kind", "mode", "response", "sql",
                       words(F.col("question")).alias("n_tok_in"), words(F.col("response")).alias("n_tok_out"))


def repair(sql: str, error: str, names: list[str]) -> str:
    """A failed query with an unknown name replaced by the nearest name of the dictionary (edit distance)."""
    m = re.search(r"(?:column|variable|function parameter)[^`]*with name ((?:`[^`]+`\.?)+)", error)
    if not m:
        return sql
    bad = m.group(1).replace("`", "").rpartition(".")[2]

    def distance(a: str, b: str) -> int:
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    return re.sub(rf"\b{re.escape(bad)}\b", min(names, key=lambda n: (distance(bad, n), n)), sql)
