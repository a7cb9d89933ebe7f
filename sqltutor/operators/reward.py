"""Staged reward: format, gate, execution, schema linking, efficiency; presets for the ablation arms."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import response as R
from ..functions.similarity import scored_pairs
from ..functions.skeleton import emphasise, extract
from ..store import written


@dataclass(frozen=True)
class RewardSpec:
    """Points of the stages and which reading of them holds.

    ``success_rule`` "equal": finished in time with gold's rows, "ran": any clean run. ``stop_after_success``: no
    efficiency part. ``format_rule``: "pattern+skeleton", "pattern", or "syntax" (SELECT and FROM). ``link_rule``:
    "subset" or "equal". ``kind`` "staged", "sparse" (0 or 1), "clausewise" (share of gold's clauses) or "overlap" (share
    of rows that both results have).
    """

    skeleton: bool = True
    efficiency: bool = True
    cold_start: bool = False
    tau: float = 0.6
    limit_s: float = 30.0
    format_ok: float = 1.0
    format_bad: float = -2.0
    exec_ok: float = 2.0
    exec_bad: float = -2.5
    link_ok: float = 1.5
    link_bad: float = 0.0
    weights: tuple[float, float, float, float] = (1.0, 1.0, 1.0, 1.0)
    success_rule: str = "equal"
    stop_after_success: bool = False
    format_rule: str = "pattern+skeleton"
    link_rule: str = "subset"
    require_nonempty: bool = False
    kind: str = "staged"

    @classmethod
    def sparse(cls) -> RewardSpec:
        return cls(kind="sparse")

    @classmethod
    def result_overlap(cls) -> RewardSpec:
        return cls(kind="overlap")

    @classmethod
    def clausewise(cls) -> RewardSpec:
        return cls(kind="clausewise")


#: Ablation arms: the parts that each adds.
ARMS = {
    "vanilla": RewardSpec(skeleton=False, efficiency=False), "skeleton": RewardSpec(efficiency=False), "efficiency": RewardSpec(skeleton=False),
    "skeleton_efficiency": RewardSpec(), "full": RewardSpec(cold_start=True),
}


def preset(name: str) -> RewardSpec:
    return ARMS[name]


def arms(spark) -> DataFrame:
    """The definition of the six arms; ``base`` has no training."""
    rows = [("base", False, False, False, False, False)] + [(n, True, True, s.skeleton, s.efficiency, s.cold_start) for n, s in ARMS.items()]
    return spark.createDataFrame(rows, "arm string, format boolean, execution_and_linking boolean, skeleton boolean, efficiency boolean, cold_start boolean")


def assembled(cands: DataFrame, match: str = "blocks", tau: float | None = None) -> DataFrame:
    """Candidates with all that the stages need from text: pattern verdict, skeletons, similarity."""
    rows = cands.withColumn("pattern_ok", R.valid_in(F.col("mode"), F.col("response"))).withColumn("shape_ok", R.sql_shape_ok(F.col("sql")))
    texts = cands.select(F.col("sql").alias("__sql")).union(cands.select("gold_sql")).where("__sql IS NOT NULL").distinct()
    known = written(cands.sparkSession, texts.withColumn("__sk", emphasise(extract(F.col("__sql")))), "skeletons")
    for text, name in (("sql", "skeleton"), ("gold_sql", "gold_skeleton")):
        rows = rows.join(known.select(F.col("__sql").alias(text), F.col("__sk").alias(name)), text, "left")
    rows = written(cands.sparkSession, rows, "with-skeletons")  # both sides of the join below would compute them
    return scored_pairs(rows, "skeleton", "gold_skeleton", match=match, tau=tau)


def score(df: DataFrame, spec: RewardSpec = RewardSpec()) -> DataFrame:
    """Adds ``fmt``, ``exec``, ``link``, ``eff``, ``total`` and ``stage`` (the last one reached).

    Needs ``pattern_ok``, ``shape_ok``, ``sim``, ``status``, ``equal``, ``t_gold``, ``t_pred``, ``link_set_ok`` and
    ``link_equal``; ``clause_share`` for the clausewise kind. Nulls count as failures. A predicted time of 0 earns the
    whole efficiency part.
    """
    yes = lambda c: F.coalesce(c, F.lit(False))
    if spec.format_rule == "syntax":
        shaped = yes(F.col("shape_ok"))
    else:
        shaped = yes(F.col("pattern_ok"))
        if spec.skeleton and spec.format_rule == "pattern+skeleton":
            shaped = shaped & yes(F.col("sim") >= spec.tau)
    ran = yes(F.col("status") == "ok") & yes(F.col("t_pred") <= spec.limit_s)
    success = ran if spec.success_rule == "ran" else ran & yes(F.col("equal"))
    linked = yes(F.col("link_equal" if spec.link_rule == "equal" else "link_set_ok"))
    if spec.require_nonempty:
        linked = linked & yes(F.col("n_elements") > 0)
    ratio = F.when(F.col("t_pred") == 0, 1.0).otherwise(F.least(F.lit(1.0), F.try_divide("t_gold", "t_pred")))
    if spec.kind == "sparse":
        whole = F.when(shaped & success, 1.0).otherwise(0.0)
        return df.withColumns({"fmt": F.lit(0.0), "exec": whole, "link": F.lit(0.0), "eff": F.lit(0.0), "total": whole, "stage": F.when(shaped, "execution").otherwise("format")})
    if spec.kind == "clausewise":
        share = F.coalesce(F.col("clause_share"), F.lit(0.0))
        return df.withColumns({"fmt": F.lit(0.0), "exec": share, "link": F.lit(0.0), "eff": F.lit(0.0), "total": share, "stage": F.lit("clauses")})
    if spec.kind == "overlap":
        shared = F.when(shaped, F.when(success, 1.0).otherwise(F.coalesce(F.col("overlap"), F.lit(0.0)))).otherwise(0.0)
        return df.withColumns({"fmt": F.lit(0.0), "exec": shared, "link": F.lit(0.0), "eff": F.lit(0.0), "total": shared, "stage": F.when(shaped, "execution").otherwise("format")})
    wf, we, ws, wt = spec.weights
    timed = spec.efficiency and not spec.stop_after_success
    out = df.withColumns({
        "fmt": F.when(shaped, wf * spec.format_ok).otherwise(F.lit(spec.format_bad)),
        "exec": F.when(~shaped, 0.0).when(success, we * spec.exec_ok).otherwise(we * spec.exec_bad),
        "link": F.when(~shaped | success, 0.0).when(linked, ws * spec.link_ok).otherwise(ws * spec.link_bad),
        "eff": F.when(shaped & success, wt * ratio).otherwise(0.0) if timed else F.lit(0.0),
        "stage": F.when(~shaped, "format").when(success, "efficiency" if timed else "execution").otherwise("linking"),
    })
    return out.withColumn("total", F.col("fmt") + F.col("exec") + F.col("link") + F.col("eff"))


def several(df: DataFrame, weights: dict[str, float], spec: RewardSpec = RewardSpec()) -> DataFrame:
    """The staged reward with an efficiency part made of several objectives. ``weights``: name of what a run used (time,
    shuffled bytes, spill, memory) -> weight; each part is gold's use over the candidate's, at most 1, and 1 where neither
    uses any. Columns: ``t_gold``/``t_pred`` for "t", ``gold_<name>``/``<name>`` for all others."""
    staged, total, whole = score(df, spec), F.lit(0.0), sum(weights.values())
    for name, w in weights.items():
        gold, pred = (F.col("t_gold"), F.col("t_pred")) if name == "t" else (F.col(f"gold_{name}"), F.col(name))
        part = F.when(F.coalesce(pred, F.lit(0)) == 0, 1.0).otherwise(F.least(F.lit(1.0), F.coalesce(gold, F.lit(0)) / pred))
        total = total + w / whole * part
    eff = F.when(F.col("stage") == "efficiency", total).otherwise(0.0)
    return staged.withColumn("total", F.col("total") - F.col("eff") + eff).withColumn("eff", eff)


def score_arms(df: DataFrame, names: list[str] | None = None) -> DataFrame:
    """All arms' rewards of the same candidates, stacked under ``arm``."""
    out = None
    for n in names or list(ARMS):
        one = score(df, ARMS[n]).withColumn("arm", F.lit(n))
        out = one if out is None else out.unionByName(one)
    return out


READINGS = {
    "default": RewardSpec(), "ran": RewardSpec(success_rule="ran"), "stop_after_success": RewardSpec(stop_after_success=True),
    "syntax_format": RewardSpec(format_rule="syntax"), "pattern_format": RewardSpec(format_rule="pattern"), "link_equal": RewardSpec(link_rule="equal"),
    "nonempty_link": replace(RewardSpec(), require_nonempty=True),
}
