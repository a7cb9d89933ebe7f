"""URL filters: fixed host and path rules, then association rules mined from labelled pages.

Mining: a page's tokens (host names and their parts, path parts, query keys) and, for pages of labelled documents, one
more token for the label make a basket; FP-growth finds frequent token sets, and sets that imply the bad label with
enough confidence and support become rules. Matching: an inverted index from each rule's rarest token to its other
tokens; a page looks up its own tokens and compares the few rules it meets.
"""

from __future__ import annotations

import json

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch

#: Fixed rules: verdict, host, path.
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
BAD, SUPPORT, CONFIDENCE, LIFT, DEVIATIONS, ROWS = "label=bad", 0.002, 0.3, 1.5, 4.0, 200_000


def _rest(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_rest(url), r"\A([^/?#]*)", 1), UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), r"\A[^/?#]*([^?#]*)", 1), F.lit(""))


def fixed_rule(host: Column, path: Column) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null where none does."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for what, h, p in sorted(RULES, key=lambda r: len(r[1] + r[2])):
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        name, verdict = F.when(fits, F.lit(h + p)).otherwise(name), F.when(fits, F.lit(what)).otherwise(verdict)
    return name, verdict


def tokens(url: Column) -> Column:
    """Distinct tokens of a URL; ids in paths are not tokens."""
    host, path = host_of(url), path_of(url)
    parts = F.transform(F.split(host, r"\."), lambda x: F.concat(F.lit("h:"), x))
    steps = F.transform(F.filter(F.split(path, "/"), lambda x: (x != "") & ~x.rlike(r"\d")), lambda x: F.concat(F.lit("p:"), F.lower(x)))
    keys = F.transform(F.regexp_extract_all(F.coalesce(url, F.lit("")), F.lit(r"[?&]([^=&#?]+)"), 1), lambda x: F.concat(F.lit("q:"), F.lower(x)))
    return F.array_distinct(F.concat(F.array(F.concat(F.lit("host:"), host)), parts, steps, keys))


def document_of(url: Column) -> Column:
    """Id of the document that a page shows: the number in its path."""
    return F.regexp_extract(path_of(url), r"/(\d{1,18})(?:/|\.|$)", 1).try_cast("long")


def mine(pages: DataFrame, labels: DataFrame, support: float = SUPPORT, confidence: float = CONFIDENCE) -> list[dict]:
    """All rules ``{"tokens", "confidence", "support"}`` that none of their subsets makes needless, shorter ones first.

    Pruned: rules below ``support`` or ``confidence``, rules whose confidence is less than ``LIFT`` times the bad rate or
    within ``DEVIATIONS`` standard errors of it, and rules that a subset of their tokens makes needless. Where labels
    say nothing about URLs no rule is left. Trained on at most ``ROWS`` labelled pages, by hash order of the page's id."""
    known = labels.groupBy("doc_id").agg(F.max(((F.col("quality") == 0) | (F.col("toxic") == 1)).cast("int")).alias("bad"))
    seen = pages.select(document_of(F.col("url")).alias("doc_id"), tokens(F.col("url")).alias("items"), "page_id").join(known.where("bad IS NOT NULL"), "doc_id")
    seen = seen.orderBy(F.xxhash64("page_id"), "page_id").limit(ROWS).persist()
    n, rate = seen.agg(F.count("*"), F.coalesce(F.avg("bad"), F.lit(0.0))).first()
    if not n:
        seen.unpersist()
        return []
    baskets = seen.select(F.when(F.col("bad") == 1, F.array_append("items", F.lit(BAD))).otherwise(F.col("items")).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(baskets)
    found = (model.associationRules.where((F.size("consequent") == 1) & (F.element_at("consequent", 1) == BAD))
             .where((F.col("confidence") >= LIFT * rate) & (F.col("confidence") - rate >= DEVIATIONS * F.sqrt(
                 F.lit(rate * (1 - rate)) * F.col("confidence") / (F.col("support") * n))))
             .select(F.sort_array("antecedent").alias("t"), "confidence", "support"))
    kept = _irredundant(Scratch(pages.sparkSession, "rules"), found)
    seen.unpersist()
    return [{"tokens": list(r["t"]), "confidence": r["confidence"], "support": r["support"]} for r in kept]


def _subsets(t: Column, size: int) -> Column:
    """All subsets of ``size`` tokens, each in the order of ``t``."""
    none = F.array().cast("array<string>")
    grown = lambda acc, x: F.concat(acc, F.transform(F.filter(acc, lambda y: F.size(y) < size), lambda y: F.array_append(y, x)))
    return F.filter(F.aggregate(t, F.array(none), grown), lambda y: F.size(y) == size)


def _irredundant(scratch: Scratch, found: DataFrame) -> list:
    """Rules that hold no other rule's tokens, length by length: rules of one length stay, and all longer ones that have
    one of them as a subset go before the next length. Only what stays comes to the driver."""
    left, kept, step = scratch.save(found, "left-0"), [], 0
    while size := left.agg(F.min(F.size("t"))).first()[0]:
        step += 1
        kept += left.where(F.size("t") == size).orderBy(F.desc("confidence"), F.desc("support"), "t").collect()
        short = left.where(F.size("t") == size).select(F.col("t").alias("part"))
        longer = left.where(F.size("t") > size)
        needless = longer.select("t", F.explode(_subsets(F.col("t"), size)).alias("part")).join(short, "part", "left_semi").select("t")
        left = scratch.save(longer.join(needless, "t", "left_anti"), f"left-{step}")
        scratch.drop(f"left-{step - 1}")
    return kept


def inverted(rules: list[dict]) -> dict[str, list[list[str]]]:
    """Rarest token of each rule (by rules that have it) -> the rule's other tokens."""
    times: dict[str, int] = {}
    for r in rules:
        for t in r["tokens"]:
            times[t] = times.get(t, 0) + 1
    index: dict[str, list[list[str]]] = {}
    for r in rules:
        key = min(r["tokens"], key=lambda t: (times[t], t))
        index.setdefault(key, []).append([t for t in r["tokens"] if t != key])
    return index


def matches(items: Column, rules: list[dict]) -> Column:
    """Does any rule's token set lie within ``items``? The index is a constant inside the plan, as large as the rules."""
    index = inverted(rules)
    if not index:
        return F.lit(False)
    table = F.from_json(F.lit(json.dumps(index)), "map<string, array<array<string>>>")
    return F.exists(items, lambda t: F.exists(F.coalesce(F.try_element_at(table, t), F.array().cast("array<array<string>>")),
                                              lambda rest: F.size(F.array_except(rest, items)) == 0))


def judged(spark: SparkSession, pages: DataFrame, labels: DataFrame) -> DataFrame:
    """``(page_id, host, path, rule, verdict)``, a row per row of ``pages``. Null URL or one without ``://``: empty host
    and path, no fixed rule, and no tokens but the empty host's. No labelled page: mined rules are none, so what no
    fixed rule decides is allowed. Empty table: no rows."""
    return decided(pages, mine(pages, labels))


def decided(pages: DataFrame, rules: list[dict]) -> DataFrame:
    url = F.col("url")
    rows = pages.select("page_id", host_of(url).alias("host"), path_of(url).alias("path"), tokens(url).alias("__items"))
    name, verdict = fixed_rule(F.col("host"), F.col("path"))
    mined = F.when(matches(F.col("__items"), rules), F.lit("block")).otherwise(F.lit("allow"))
    return rows.select("page_id", "host", "path", name.alias("rule"), F.coalesce(verdict, mined).alias("verdict"))
