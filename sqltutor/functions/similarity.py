"""Similarity of skeletons: matching blocks, edit distance, token sets, and their mix.

Matching blocks has no native form; it runs in Arrow batches over distinct pairs only, after exact shortcuts.
"""

from __future__ import annotations

from collections.abc import Iterator
from difflib import SequenceMatcher
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .skeleton import KEYWORDS

ALPHA, TAU = 0.7, 0.6


@lru_cache(maxsize=65536)
def blocks(a: str, b: str, autojunk: bool = False) -> float:
    """2M/(la+lb) of the standard library's matcher; ``autojunk`` on depends on the order of arguments."""
    if not a and not b:
        return 1.0
    return SequenceMatcher(None, a, b, autojunk=autojunk).ratio()


def block_ratio(a: Column, b: Column, autojunk: bool = False) -> Column:
    def run(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        for x, y in batches:
            yield pa.array([None if p is None or q is None else blocks(p, q, autojunk) for p, q in zip(x.to_pylist(), y.to_pylist(), strict=True)], pa.float64())

    return F.arrow_udf(run, T.DoubleType())(a, b)


def block_bound(a: Column, b: Column) -> Column:
    """No matching-blocks ratio exceeds this: the shorter text can match whole at most."""
    both = F.length(a) + F.length(b)
    return F.when(both == 0, 1.0).otherwise(2.0 * F.least(F.length(a), F.length(b)) / both)


def edit_ratio(a: Column, b: Column) -> Column:
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, 1.0).otherwise(1.0 - F.levenshtein(a, b) / longest)


def tokens(skeleton: Column, only: str = "all") -> Column:
    parts = F.filter(F.split(skeleton, " "), lambda x: x != "")
    return F.filter(parts, lambda x: x.isin(*KEYWORDS)) if only == "keywords" else parts


def jaccard(a: Column, b: Column, only: str = "all", bag: bool = False) -> Column:
    """Shared tokens over all tokens, as sets or (``bag``) with counts. Both empty: 1."""
    x, y = tokens(a, only), tokens(b, only)
    if bag:
        each = F.array_distinct(F.concat(x, y))
        times = lambda arr, t: F.size(F.filter(arr, lambda z: z == t))
        low = F.aggregate(each, F.lit(0), lambda n, t: n + F.least(times(x, t), times(y, t)))
        high = F.aggregate(each, F.lit(0), lambda n, t: n + F.greatest(times(x, t), times(y, t)))
    else:
        low, high = F.size(F.array_intersect(x, y)), F.size(F.array_union(x, y))
    return F.when(high == 0, 1.0).otherwise(low / high)


def mix(ratio: Column, jac: Column, alpha: float = ALPHA) -> Column:
    return alpha * ratio + (1 - alpha) * jac


def scored_pairs(pairs: DataFrame, a: str, b: str, alpha: float = ALPHA, match: str = "blocks", tau: float | None = None) -> DataFrame:
    """Adds ``ratio``, ``jac`` and ``sim``. Each distinct pair is scored once and joined back.

    With ``tau``, pairs whose upper bound stays below it are not matched: their ``sim`` is that bound and surely fails.
    """
    once = pairs.select(a, b).distinct().withColumn("jac", jaccard(F.col(a), F.col(b)))
    if match == "edit":
        return _joined(pairs, once.withColumn("ratio", edit_ratio(F.col(a), F.col(b))), a, b, alpha)
    once = once.withColumn("bound", block_bound(F.col(a), F.col(b)))
    hopeless = (mix(F.col("bound"), F.col("jac"), alpha) < tau) if tau is not None else F.lit(False)
    easy = F.when(F.col(a) == F.col(b), 1.0).when(hopeless, F.col("bound"))
    known = once.withColumn("easy", easy)
    hard = known.where("easy IS NULL").withColumn("ratio", block_ratio(F.col(a), F.col(b)))
    return _joined(pairs, known.where("easy IS NOT NULL").withColumn("ratio", F.col("easy")).unionByName(hard), a, b, alpha)


def _joined(pairs: DataFrame, scored: DataFrame, a: str, b: str, alpha: float) -> DataFrame:
    scored = scored.select(a, b, "ratio", "jac", mix(F.col("ratio"), F.col("jac"), alpha).alias("sim"))
    left, right = pairs.alias("l"), scored.alias("r")
    return left.join(right, F.col(f"l.{a}").eqNullSafe(F.col(f"r.{a}")) & F.col(f"l.{b}").eqNullSafe(F.col(f"r.{b}")), "left").select("l.*", "r.ratio", "r.jac", "r.sim")


def sweep(scored: DataFrame, alphas: list[float], taus: list[float], truth: str = "equal") -> DataFrame:
    """For a grid of weights and thresholds: share passed, precision and recall of passing against ``truth``, and the
    share of right candidates that the gate turns away. ``scored`` has ``ratio`` and ``jac``; the grid is a literal."""
    grid = F.array(*[F.struct(F.lit(a).alias("alpha"), F.lit(t).alias("tau")) for a in alphas for t in taus])
    rows = scored.withColumn("g", F.explode(grid)).select("g.alpha", "g.tau", F.col(truth).cast("int").alias("t"),
        (F.col("g.alpha") * F.col("ratio") + (1 - F.col("g.alpha")) * F.col("jac") >= F.col("g.tau")).cast("int").alias("p"))
    agg = rows.groupBy("alpha", "tau").agg(F.count("*").alias("n"), F.sum("p").alias("passed"), F.sum("t").alias("right"), F.sum(F.col("p") * F.col("t")).alias("both"))
    return agg.select("alpha", "tau", "n", "passed", (F.col("passed") / F.col("n")).alias("pass_rate"), F.try_divide("both", "passed").alias("precision"),
                      F.try_divide("both", "right").alias("recall"), F.try_divide(F.col("right") - F.col("both"), F.col("right")).alias("false_rejection"))
