"""Accuracy and cost measures over ``eval_rows``: one row per arm, suite, engine and question.

Each measure is one partial-and-final aggregation; results have as many rows as arms, suites and tiers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Draws that one digest gives, and the shares of a Poisson variable of mean 1 below 1, 2, 3 and 4, of 65,536.
DRAWS, POISSON = 8, (24_109, 48_219, 60_273, 64_291)


def _rate(flag: str | Column) -> Column:
    col = F.col(flag) if isinstance(flag, str) else flag
    return F.avg(F.coalesce(col, F.lit(False)).cast("double"))


def em(df: DataFrame, by: list[str]) -> DataFrame:
    """Share whose clause sets all match; nulls count as misses."""
    return df.groupBy(*by).agg(_rate("em").alias("em"))


def ex(df: DataFrame, by: list[str]) -> DataFrame:
    """Share whose rows equal gold's; runs that failed stay in the count."""
    return df.groupBy(*by).agg(_rate("ex").alias("ex"))


def efficiency(form: str = "sqrt") -> Column:
    """A question's factor: root of the time ratio, or the ratio capped at 1; 0 unless correct."""
    ratio = F.try_divide("t_gold", "t_pred")
    return F.when(F.coalesce(F.col("ex"), F.lit(False)), F.coalesce(F.sqrt(ratio) if form == "sqrt" else F.least(F.lit(1.0), ratio), F.lit(1.0))).otherwise(0.0)


def ves(df: DataFrame, by: list[str], form: str = "sqrt") -> DataFrame:
    return df.groupBy(*by).agg(F.avg(efficiency(form)).alias("ves"))


def across_engines(df: DataFrame, by: list[str], form: str = "sqrt") -> DataFrame:
    """VES per engine first, then the plain mean of the engines."""
    return ves(df, [*by, "engine"], form).groupBy(*by).agg(F.avg("ves").alias("ves"))


def efficiency_gain(per_arm: DataFrame, base: str, by: list[str], value: str = "ves") -> DataFrame:
    """Percent over the arm ``base``. ``per_arm`` has a row per arm, so its base rows are few."""
    b = per_arm.where(F.col("arm") == base).select(*by, F.col(value).alias("__b"))
    joined = per_arm.join(b, by) if by else per_arm.join(b, F.lit(True))
    return joined.select("arm", *by, (100.0 * F.try_divide(F.col(value) - F.col("__b"), F.col("__b"))).alias("gain"))


def pgr(per_arm: DataFrame, weak: str, strong: str, by: list[str]) -> DataFrame:
    """Part of the gap between a weak and a strong arm that each arm closes; null where there is no gap."""
    ends = per_arm.groupBy(*by).agg(F.max(F.when(F.col("arm") == weak, F.col("ex"))).alias("b"), F.max(F.when(F.col("arm") == strong, F.col("ex"))).alias("a"))
    joined = per_arm.join(ends, by) if by else per_arm.join(ends, F.lit(True))
    return joined.select("arm", *by, (F.try_divide(F.col("ex") - F.col("b"), F.col("a") - F.col("b")) + 0.0).alias("pgr"))


def token_cost(df: DataFrame, by: list[str], mu: float = 1.0) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(F.col("n_tok_in") + mu * F.col("n_tok_out")).alias("tokens"))


def tep(df: DataFrame, base: str, by: list[str], mu: float = 1.0) -> DataFrame:
    """Relative gain in accuracy over relative gain in tokens, both against ``base``, with both parts kept."""
    per = df.groupBy("arm", *by).agg(_rate("ex").alias("ex"), F.avg(F.col("n_tok_in") + mu * F.col("n_tok_out")).alias("tokens"))
    b = per.where(F.col("arm") == base).select(*by, F.col("ex").alias("ex_b"), F.col("tokens").alias("tok_b"))
    joined = per.join(b, by) if by else per.join(b, F.lit(True))
    gain, spent = F.try_divide(F.col("ex") - F.col("ex_b"), F.col("ex_b")), F.try_divide(F.col("tokens") - F.col("tok_b"), F.col("tok_b"))
    return joined.select("arm", *by, gain.alias("gain"), spent.alias("spent"), F.try_divide(gain, spent).alias("tep"))


def cdf(df: DataFrame, by: list[str], column: str, grid: list[float]) -> DataFrame:
    """Share of rows at or below each grid point: one scan to a histogram, then running sums of as many rows as points."""
    at = F.lit(len(grid))
    for k in range(len(grid) - 1, -1, -1):
        at = F.when(F.col(column) <= grid[k], F.lit(k)).otherwise(at)
    hist = df.where(F.col(column).isNotNull()).groupBy(*by, at.alias("k")).agg(F.count("*").alias("c"))
    points = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(x).alias("x")) for k, x in enumerate(grid)]))
    totals = hist.groupBy(*by).agg(F.sum("c").alias("n")).withColumn("p", points)
    filled = totals.select(*by, "n", F.col("p.k").alias("k"), F.col("p.x").alias("x")).join(hist, [*by, "k"], "left")
    upto = Window.partitionBy(*by).orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    return filled.select(*by, "x", (F.sum(F.coalesce("c", F.lit(0))).over(upto) / F.col("n")).alias("share"))


def share_above(df: DataFrame, by: list[str], column: str, x: float) -> DataFrame:
    return df.groupBy(*by).agg(F.avg((F.col(column) > x).cast("double")).alias("share"))


def quantiles(df: DataFrame, by: list[str], column: str, points: list[float], exact: bool = True) -> DataFrame:
    fn = (lambda p: F.percentile(column, F.lit(p))) if exact else (lambda p: F.percentile_approx(column, F.lit(p)))
    return df.groupBy(*by).agg(*[fn(p).alias(f"q{int(p * 100)}") for p in points])


def by_tier(df: DataFrame, measure: str, tiers: list[str]) -> DataFrame:
    """Arms by tiers; tiers are named, so the pivot needs no pass of its own."""
    value = {"ex": _rate("ex"), "em": _rate("em"), "jac": F.avg("jac"), "ves": F.avg(efficiency())}[measure]
    return df.groupBy("arm").pivot("tier", tiers).agg(value)


def tiers_and_totals(df: DataFrame) -> DataFrame:
    """EX by suite and tier with subtotals in one pass."""
    return df.rollup("suite", "tier").agg(_rate("ex").alias("ex"), F.count("*").alias("n"), F.grouping_id().alias("level"))


def gap(df: DataFrame, by: str = "tier") -> DataFrame:
    """Largest difference in EX between arms within each tier."""
    per = df.groupBy("arm", by).agg(_rate("ex").alias("ex"))
    return per.groupBy(by).agg((F.max("ex") - F.min("ex")).alias("gap"))


def leaderboard(scores: DataFrame, by: list[str], score: str = "score") -> DataFrame:
    w = Window.partitionBy(*by).orderBy(F.desc(score))
    return scores.withColumn("place", F.rank().over(w).cast("long")).withColumn("dense", F.dense_rank().over(w).cast("long"))


def arm_table(rows: DataFrame, base: str, best: str) -> DataFrame:
    """``(arm, suite, em, pgr, tep)``; the untrained arm has EM only."""
    wide = em(rows, ["arm", "suite"]).join(pgr(ex(rows, ["arm", "suite"]), base, best, ["suite"]).select("arm", "suite", "pgr"), ["arm", "suite"])
    wide = wide.join(tep(rows, base, ["suite"]).select("arm", "suite", "tep"), ["arm", "suite"])
    return wide.select("arm", "suite", "em", *[F.when(F.col("arm") != base, F.col(c)).alias(c) for c in ("pgr", "tep")])


def retention(rows: DataFrame, base: str, trained: str) -> DataFrame:
    """``(test, base, trained, delta, kept)``: EX of two arms in percent, a row per suite."""
    per = ex(rows.where(F.col("arm").isin(base, trained)), ["arm", "suite"]).withColumn("score", F.round(100 * F.col("ex"), 6))
    one = lambda arm, name: per.where(F.col("arm") == arm).select(F.col("suite").alias("test"), F.col("score").alias(name))
    both = one(base, "base").join(one(trained, "trained"), "test")
    return both.withColumn("delta", F.round(F.col("trained") - F.col("base"), 6)).withColumn("kept", F.col("trained") >= F.col("base"))


def reward_trace(df: DataFrame, step: str = "step", reward: str = "total") -> DataFrame:
    return df.groupBy(step).agg(F.avg(reward).alias("mean_reward"), F.stddev_samp(reward).alias("sd_reward"), F.count("*").alias("n"))


def length_trace(df: DataFrame, step: str = "step", length: str = "n_tok_out", most: float = 1.2) -> DataFrame:
    """Mean length per step and whether it is inflated: over ``most`` times the first step's."""
    per = df.groupBy(step).agg(F.avg(length).alias("mean_len"))
    w = Window.orderBy(step)
    return per.select(step, "mean_len", (F.col("mean_len") - F.lag("mean_len").over(w)).alias("change"),
                      (F.col("mean_len") > most * F.first("mean_len").over(w)).alias("inflated"))


def rank_stability(df: DataFrame, by: list[str]) -> DataFrame:
    """Spearman correlation of arms' VES ranks between the two engines."""
    per = ves(df, ["arm", "engine", *by])
    ranked = per.withColumn("place", F.rank().over(Window.partitionBy("engine", *by).orderBy(F.desc("ves"))).cast("double"))
    two = ranked.groupBy("arm", *by).agg(F.max(F.when(F.col("engine") == "adaptive", F.col("place"))).alias("x"), F.max(F.when(F.col("engine") == "static", F.col("place"))).alias("y"))
    return (two.groupBy(*by) if by else two.groupBy()).agg(F.corr("x", "y").alias("spearman"))


def tail(df: DataFrame, by: list[str], column: str, exact: bool = True) -> DataFrame:
    return quantiles(df, by, column, [0.95, 0.99], exact)


def error_rate(df: DataFrame, by: list[str], failed: Column) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(failed.cast("double")).alias("error_rate"))


def timing_noise(df: DataFrame, times: str = "times") -> DataFrame:
    """Mean and coefficient of variation of repeats, inside each row."""
    n, total = F.size(times), F.aggregate(times, F.lit(0.0), lambda a, x: a + x)
    mean = F.try_divide(total, n)
    var = F.try_divide(F.aggregate(times, F.lit(0.0), lambda a, x: a + (x - mean) * (x - mean)), n - 1)
    return df.withColumn("t_mean", mean).withColumn("t_cv", F.try_divide(F.sqrt(var), mean))


def bootstrap(df: DataFrame, by: list[str], value: Column, b: int = 200, seed: int = 7) -> DataFrame:
    """95 % interval of a mean by Poisson bootstrap: a question draws a weight from 0 to 4 for each of ``b`` replicates from
    a hash of its id and ``seed``. Rows are summed by question first; then all replicates' sums come from one aggregation."""
    per = df.groupBy(*by, "question_id").agg(F.sum(value.cast("double")).alias("v"), F.count(value).alias("n"))
    per = per.withColumn("h", F.transform(F.sequence(F.lit(0), F.lit(-(-b // DRAWS) - 1)), lambda k: F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("question_id").cast("string"), k.cast("string")).cast("binary"))))
    draws = []
    for i in range(b):
        x = F.conv(F.substring(F.get("h", F.lit(i // DRAWS)), 4 * (i % DRAWS) + 1, 4), 16, 10).cast("int")
        draws.append(sum((F.when(x >= edge, 1).otherwise(0) for edge in POISSON), F.lit(0)))
    sums = per.groupBy(*by).agg(*[F.sum(F.col("v") * w).alias(f"v{i}") for i, w in enumerate(draws)], *[F.sum(F.col("n") * w).alias(f"n{i}") for i, w in enumerate(draws)])
    means = sums.select(*by, F.explode(F.array(*[F.try_divide(F.col(f"v{i}"), F.col(f"n{i}")) for i in range(b)])).alias("m"))
    return means.groupBy(*by).agg(F.percentile("m", F.lit(0.025)).alias("low"), F.percentile("m", F.lit(0.975)).alias("high"))


def confidence(df: DataFrame) -> DataFrame:
    """Share of a question's candidates that agree with the most frequent result, and whether to fall back below 0.5."""
    per = df.groupBy("question_id", "fp").agg(F.count("*").alias("n"))
    return per.groupBy("question_id").agg((F.max("n") / F.sum("n")).alias("confidence")).withColumn("fallback", F.col("confidence") < 0.5)


def overhead(executions: DataFrame) -> DataFrame:
    """Executions, distinct texts and seconds spent per arm."""
    return executions.groupBy("arm").agg(F.count("*").alias("asked"), F.countDistinct("sql").alias("texts"), F.sum("t_pred").alias("seconds"))
