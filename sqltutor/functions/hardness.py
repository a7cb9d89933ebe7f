"""Difficulty tiers by rule: joins, predicates, grouping, nesting, set operations and windows are counted in the text."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Part of the text and what one occurrence adds.
POINTS = ((r"\bJOIN\b", 1), (r"\b(?:AND|OR)\b", 1), (r"\bGROUP BY\b", 1), (r"\bHAVING\b", 1), (r"\bORDER BY\b", 1), (r"\(\s*SELECT\b", 2),
          (r"\b(?:UNION|INTERSECT|EXCEPT)\b", 2), (r"\bOVER\b", 2), (r"\bNOT (?:IN|EXISTS)\b", 1))
SCHEMES = {"A": (("simple", 1), ("moderate", 4), ("challenging", None)), "B": (("easy", 0), ("medium", 2), ("hard", 4), ("extra", None))}


def points(sql: Column) -> Column:
    up = F.upper(F.coalesce(sql, F.lit("")))
    return sum((F.regexp_count(up, F.lit(p)) * w for p, w in POINTS), F.lit(0))


def tier(sql: Column, scheme: str = "A") -> Column:
    n, names = points(sql), SCHEMES[scheme]
    out = F.lit(names[-1][0])
    for name, most in reversed(names[:-1]):
        out = F.when(n <= most, F.lit(name)).otherwise(out)
    return out


def duck_tier(sql: str, scheme: str = "A") -> str:
    quote = lambda s: s.replace("'", "''")
    n = " + ".join(f"{w} * len(regexp_extract_all(upper(coalesce({sql}, '')), '{quote(p)}'))" for p, w in POINTS)
    cases = " ".join(f"WHEN ({n}) <= {most} THEN '{name}'" for name, most in SCHEMES[scheme][:-1])
    return f"CASE {cases} ELSE '{SCHEMES[scheme][-1][0]}' END"
