"""SQL skeletons: names, literals and numbers become placeholders, keywords stay. One rule set, two renderings.

Rules: comments go; strings become ``'[str]'``; quoted, qualified and plain names ``[col]``; numbers ``[val]``; names after
FROM or JOIN ``[tab]``; a name before a bracket is a function and stays in upper case; alias definitions go; ``*`` stays.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed set of words that are structure, not names.
KEYWORDS = tuple(
    "SELECT DISTINCT FROM WHERE GROUP BY HAVING ORDER LIMIT OFFSET JOIN INNER LEFT RIGHT FULL OUTER CROSS SEMI ANTI ON USING AND OR NOT IN EXISTS "
    "BETWEEN LIKE IS NULL CASE WHEN THEN ELSE END AS UNION INTERSECT EXCEPT ALL ANY SOME ASC DESC NULLS FIRST LAST OVER PARTITION ROWS RANGE "
    "PRECEDING FOLLOWING UNBOUNDED CURRENT ROW WITH INTERVAL TRUE FALSE INT INTEGER BIGINT DOUBLE REAL FLOAT DECIMAL STRING VARCHAR DATE TIMESTAMP".split())
TYPES = ("INT", "INTEGER", "BIGINT", "DOUBLE", "REAL", "FLOAT", "DECIMAL", "STRING", "VARCHAR", "DATE", "TIMESTAMP")
#: Clause words that count more, and how often they are written.
WEIGHTS = (("WHERE", 3), ("JOIN", 2), ("GROUP BY", 2))
STR, VAL, COL, CALL = "\x01", "\x02", "\x03", "\x04"
#: Replacements before tokens are cut, in order: pattern and text. No look-around, so that Java and RE2 agree.
STEPS = (
    (r"--[^\n]*", " "), (r"(?s)/\*.*?\*/", " "), (r"'(?:[^']|'')*'", STR), (r"\"[^\"]*\"|`[^`]*`", COL),
    (r"[A-Za-z_][A-Za-z0-9_]*\s*\.\s*\*", "*"), (r"(?:[A-Za-z_][A-Za-z0-9_]*|" + COL + r")\s*\.\s*(?:[A-Za-z_][A-Za-z0-9_]*|" + COL + ")", COL),
    (r"\b[0-9]+(?:\.[0-9]+)?(?:[eE][+-]?[0-9]+)?\b", VAL), (r"(<=|>=|<>|!=|[(),=<>+*/%-]|" + STR + "|" + VAL + "|" + COL + ")", r" {1} "), (r"[\s;]+", " "),
)
TIDY = ((CALL + r" \( ?", "("), (r"\( ", "("), (r" \)", ")"), (STR, "'[str]'"), (VAL, "[val]"), (COL, "[col]"))


#: Marks of a name that is no keyword, a table, and a name that goes.
NAME, TAB, GONE = "\x05", "\x06", "\x07"
_WORD = "[A-Z_][A-Z0-9_]*"
#: What becomes of the tokens, which stand between single spaces in upper case: names are marked, then functions, tables,
#: aliases (and names in a row) and AS go, and what is left is a column. A table may follow a table after a comma.
KINDS = (
    (rf"(?<= )(?!(?:{'|'.join(KEYWORDS)}) )({_WORD})(?= )", rf"{NAME}$1"),
    (rf"{NAME}({_WORD}) \(", rf"$1{CALL} ("),
    (rf"(?<= (?:FROM|JOIN) ){NAME}{_WORD}", TAB),
    (rf"(?<= (?:AS|\)|END|[{STR}{VAL}{COL}{TAB}]) ){NAME}{_WORD}(?: {NAME}{_WORD})*", GONE),
    (rf"({NAME}{_WORD})(?: {NAME}{_WORD})+", "$1"),
    (rf"(?<= )AS (?!(?:{'|'.join(TYPES)}) )", ""),
)
COMMAS = 6


def _chain(sql: Column, steps: tuple[tuple[str, str], ...]) -> Column:
    for pattern, text in steps:
        sql = F.regexp_replace(sql, pattern, text.replace("{1}", "$1"))
    return sql


def extract(sql: Column, tables: tuple[str, ...] = ()) -> Column:
    """Skeleton of a query's text; null stays null. ``tables``: names that are tables wherever they stand. One pass of a
    pattern for each rule, all inside generated code."""
    spaced = F.upper(F.concat(F.lit(" "), F.trim(_chain(sql, STEPS)), F.lit(" ")))
    named = _chain(spaced, KINDS)
    if tables:
        named = F.regexp_replace(named, rf"{NAME}(?:{'|'.join(t.upper() for t in tables)})(?= )", TAB)
    named = _chain(named, ((rf"{NAME}{_WORD}", COL), (f" {GONE}(?= )", ""), (f"{TAB}", "[tab]")))
    named = _chain(named, ((rf"(FROM \[tab\](?: , \[tab\])*) , {COL}(?= )", "$1 , [tab]"),) * COMMAS)
    return F.trim(_chain(F.trim(named), TIDY))


def emphasise(skeleton: Column, weights: tuple[tuple[str, int], ...] = WEIGHTS) -> Column:
    """Clause words repeated by weight; ``LEFT JOIN`` repeats JOIN."""
    for word, times in weights:
        skeleton = F.regexp_replace(skeleton, rf"\b{word}\b", " ".join([word] * times))
    return skeleton


def duck_extract(sql: str) -> str:
    """The same rules as DuckDB SQL over an expression."""
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    for pattern, text in STEPS:
        sql = f"regexp_replace({sql}, {quoted(pattern)}, {quoted(text.replace('{1}', chr(92) + '1'))}, 'g')"
    toks = f"list_filter(string_split(trim({sql}), ' '), lambda x: x <> '')"
    keys, types = ", ".join(map(quoted, KEYWORDS)), ", ".join(map(quoted, TYPES))
    name = lambda t: f"regexp_matches({t}, '\\A[A-Z_][A-Z0-9_]*\\z')"
    before, after = "upper(coalesce(ts[i - 1], ''))", "upper(coalesce(ts[i + 1], ''))"
    before = f"(CASE WHEN i > 1 THEN {before} ELSE '' END)"
    body = (f"CASE WHEN upper(x) = 'AS' AND NOT {after} IN ({types}) THEN '' WHEN upper(x) IN ({keys}) THEN upper(x) WHEN NOT {name('upper(x)')} THEN upper(x) "
            f"WHEN {after} = '(' THEN upper(x) || {quoted(CALL)} WHEN {before} IN ('FROM', 'JOIN') THEN '[tab]' "
            f"WHEN {before} IN ('AS', ')', 'END', {quoted(STR)}, {quoted(VAL)}, {quoted(COL)}) OR ({name(before)} AND NOT {before} IN ({keys})) THEN '' "
            f"ELSE {quoted(COL)} END")
    out = f"list_transform([{toks}], lambda ts: array_to_string(list_filter(list_transform(ts, lambda x, i: {body}), lambda x: x <> ''), ' '))[1]"
    for pattern, text in (*(((rf"(FROM \[tab\](?: , \[tab\])*) , {COL}( |$)", "\\1 , [tab]\\2"),) * COMMAS), *TIDY):
        out = f"regexp_replace({out}, {quoted(pattern)}, {quoted(text)}, 'g')"
    return f"trim({out})"


def duck_emphasise(skeleton: str, weights: tuple[tuple[str, int], ...] = WEIGHTS) -> str:
    for word, times in weights:
        skeleton = f"regexp_replace({skeleton}, '\\b{word}\\b', '{' '.join([word] * times)}', 'g')"
    return skeleton


def gate(score: Column, tau: float = 0.6) -> Column:
    return F.when(score >= tau, F.lit("pass")).otherwise(F.lit("fail"))
