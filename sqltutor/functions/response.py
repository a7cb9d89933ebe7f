"""Responses: think part, SQL part, thinking modes. Native expressions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MODES = ("suppressed", "fast", "slow", "tags_only")
#: Fixed switches at the end of a prompt.
NO_THINK, THINK = "/no_think", "/think"
_FENCE = r"(?s)```sql\n(.*?)\n?```"
_THINK = r"(?s)<think>(.*?)</think>"
#: Whole-response patterns of the modes; both Java and RE2 read them.
SHAPES = {
    "suppressed": r"(?s)\A\s*```sql\n\s*\S.*?\n```\s*\z",
    "fast": r"(?s)\A<think>\n\n</think>\n\n```sql\n\s*\S.*?\n```\s*\z",
    "slow": r"(?s)\A<think>\s*\S.*?</think>\n\n```sql\n\s*\S.*?\n```\s*\z",
    "tags_only": r"(?s)<think>.*?</think>.*?```sql\n\s*\S.*?\n```",
}


def _clean(text: Column) -> Column:
    return F.replace(F.coalesce(text, F.lit("")), F.lit("\r\n"), F.lit("\n"))


def _count(text: Column, part: str) -> Column:
    return ((F.length(text) - F.length(F.replace(text, F.lit(part), F.lit("")))) / len(part)).cast("int")


def _tags_ok(text: Column) -> Column:
    """One pair of lower-case tags in order, or none of any case."""
    opens, closes = _count(text, "<think>"), _count(text, "</think>")
    odd = F.lower(text).rlike(r"</?think>") & ~text.rlike(r"</?think>")
    return ~odd & (((opens == 1) & (closes == 1) & (F.instr(text, "<think>") < F.instr(text, "</think>"))) | ((opens == 0) & (closes == 0)))


def _bound(values: dict[str, Column], body) -> Column:
    """``body`` over a struct of ``values``, each computed once however often ``body`` names it."""
    return F.get(F.transform(F.array(F.struct(*[v.alias(k) for k, v in values.items()])), body), F.lit(0))


def parse(response: Column) -> Column:
    """``struct(think, sql, fenced, tags_ok, reason)``; parts that are missing are null. Null response: all missing."""
    def named(x: Column) -> Column:
        reason = (F.when(x["none"], "missing").when(~x["tags"], "tags").when(x["fences"] == 0, "no fence").when(x["fences"] > 2, "several fences")
                  .when(~x["fenced"], "open fence").otherwise("ok"))
        return F.struct(F.when(x["tags"] & x["t"].contains("<think>"), F.regexp_extract(x["t"], _THINK, 1)).alias("think"),
                        F.when(x["fenced"], F.trim(F.regexp_extract(x["t"], _FENCE, 1))).alias("sql"),
                        x["fenced"].alias("fenced"), x["tags"].alias("tags_ok"), reason.alias("reason"))

    def counted(x: Column) -> Column:
        fences = _count(x["t"], "```")
        return _bound({"t": x["t"], "none": x["none"], "fences": fences, "fenced": (fences == 2) & x["t"].rlike(_FENCE), "tags": _tags_ok(x["t"])}, named)

    return _bound({"t": _clean(response), "none": response.isNull()}, counted)


def valid(response: Column, mode: str) -> Column:
    """Does the response keep to ``mode``? Two fences, unclosed, nested or upper-case tags and nulls are invalid."""
    t = _clean(response)
    tagged = F.lower(t).rlike("</?think>")
    good = (_count(t, "```") == 2) & t.rlike(SHAPES[mode])
    return good & ~tagged if mode == "suppressed" else good & _tags_ok(t) & t.contains("<think>")


def mode_of_prompt(prompt: Column) -> Column:
    p = F.rtrim(F.coalesce(prompt, F.lit("")))
    return F.when(p.endswith(NO_THINK), "fast").when(p.endswith(THINK), "slow").otherwise("suppressed")


def valid_for(prompt: Column, response: Column) -> Column:
    """The validator of the mode that the prompt demands."""
    mode = mode_of_prompt(prompt)
    return F.when(mode == "fast", valid(response, "fast")).when(mode == "slow", valid(response, "slow")).otherwise(valid(response, "suppressed"))


def valid_in(mode: Column, response: Column) -> Column:
    out = F.lit(False)
    for m in MODES:
        out = F.when(mode == m, valid(response, m)).otherwise(out)
    return out


def sql_shape_ok(sql: Column) -> Column:
    """SELECT and FROM in this order, balanced brackets and quotes."""
    s = F.coalesce(sql, F.lit(""))
    return (s.rlike(r"(?is)\A\s*(select|with)\b.*\bfrom\b") & (_count(s, "(") == _count(s, ")")) & (_count(s, "'") % 2 == 0))


def length_budget(response: Column, max_words: int) -> Column:
    return F.size(F.split(F.trim(F.coalesce(response, F.lit(""))), r"\s+")) <= max_words


def render(mode: str, think: Column, sql: Column) -> Column:
    """A response of a mode from a reasoning text and SQL."""
    fence = F.concat(F.lit("```sql\n"), sql, F.lit("\n```"))
    if mode == "suppressed":
        return fence
    body = F.lit("\n\n") if mode == "fast" else think
    return F.concat(F.lit("<think>"), body, F.lit("</think>\n\n"), fence)
