"""Group-relative policy optimisation with a tabular softmax policy in place of a language model.

A policy has one logit per question class (family) and candidate kind. Its table is small by construction (classes
times kinds) and goes to executors as a literal map; questions may be any number. A step samples a group of candidates
per question from a hash, looks rewards up in a cube, takes advantages against the group mean, and sums the gradient of
the clipped objective per parameter; only those sums come to the driver.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform

MOST_PARAMETERS = 200_000


@dataclass
class Policy:
    classes: list[str]
    kinds: list[str]
    theta: np.ndarray

    def __post_init__(self):
        if self.theta.size > MOST_PARAMETERS:
            raise ValueError("a policy of this size is not to be sent with every task")

    @classmethod
    def initial(cls, classes: list[str], kinds: list[str], lean: dict[str, float] | None = None) -> Policy:
        """The untrained model: logits by kind, the same for every class (``lean``: kind -> logit)."""
        row = [(lean or {}).get(k, 0.0) for k in kinds]
        return cls(list(classes), list(kinds), np.array([row] * len(classes), float))

    def tempered(self, sharpness: float) -> Policy:
        """The same leanings, stronger (over 1) or weaker."""
        return Policy(self.classes, self.kinds, self.theta * sharpness)

    def probs(self) -> np.ndarray:
        z = np.exp(self.theta - self.theta.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    def frame(self, spark: SparkSession, snapshot: int = 0) -> DataFrame:
        p = self.probs()
        rows = [(snapshot, c, k, float(self.theta[i, j]), float(math.log(p[i, j]))) for i, c in enumerate(self.classes) for j, k in enumerate(self.kinds)]
        return spark.createDataFrame(rows, "snapshot int, question_class string, kind string, theta double, logp double")

    def _table(self, values: np.ndarray) -> Column:
        cells = [F.lit(c) if n == 0 else F.array(*[F.lit(float(x)) for x in values[i]]) for i, c in enumerate(self.classes) for n in (0, 1)]
        return F.create_map(*cells)

    def sample(self, questions: DataFrame, group: int, seed: int, salt: int = 0) -> DataFrame:
        """``group`` rows per question: ``slot`` and ``kind`` by inverse distribution of a hash-uniform; repeats of the
        same seed, question and slot give the same kind whatever the layout."""
        u = uniform(F.lit(seed), F.lit(salt), F.col("question_id"), F.col("slot"))
        edges = F.element_at(self._table(np.cumsum(self.probs(), axis=1)[:, :-1]), F.col("family"))
        at = F.size(F.filter(edges, lambda e: e <= F.col("u")))
        names = F.array(*[F.lit(k) for k in self.kinds])
        return (questions.withColumn("slot", F.explode(F.sequence(F.lit(0), F.lit(group - 1)))).withColumn("u", u)
                .withColumn("kind", F.get(names, at)).drop("u"))

    def logp(self, cls: str = "family", kind: str = "kind") -> Column:
        at = F.array_position(F.array(*[F.lit(k) for k in self.kinds]), F.col(kind)).cast("int")
        return F.element_at(F.element_at(self._table(np.log(self.probs())), F.col(cls)), at)


def _exact(value: Column | str) -> Column:
    """A decimal: sums of these are the same in whatever order rows come."""
    return (F.col(value) if isinstance(value, str) else value).cast("decimal(38,15)")


def advantages(df: DataFrame, group: list[str] = ["question_id"], reward: str = "total", normalise: str = "none", exact: bool = False) -> DataFrame:  # noqa: B006
    """Reward less the group's mean; no division by the deviation unless ``normalise="std"`` asks for it. Groups are small
    (their size is the sampling parameter), so a window by group holds little. ``exact``: the mean comes from decimals, so
    that it doesn't depend on the order of rows."""
    w = Window.partitionBy(*group)
    mean = F.sum(_exact(reward)).over(w).cast("double") / F.count(reward).over(w) if exact else F.avg(reward).over(w)
    out = df.withColumn("adv", F.col(reward) - mean)
    return out.withColumn("adv", F.try_divide("adv", F.stddev_pop(reward).over(w))) if normalise == "std" else out


def ratio(logp: str = "logp", old: str = "logp_old") -> Column:
    return F.exp(F.col(logp) - F.col(old))


def surrogate_term(eps: float = 0.2) -> Column:
    r, a = ratio(), F.col("adv")
    return F.least(r * a, F.greatest(F.lit(1 - eps), F.least(F.lit(1 + eps), r)) * a)


def surrogate(df: DataFrame, eps: float = 0.2, group: list[str] = ["question_id"]) -> DataFrame:  # noqa: B006
    """Mean over groups of the group's mean clipped term."""
    per = df.groupBy(*group).agg(F.avg(surrogate_term(eps)).alias("g"))
    return per.agg(F.avg("g").alias("surrogate"))


def kl_exact(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    return (p * (np.log(p) - np.log(q))).sum(axis=1)


def kl(df: DataFrame, kind: str = "k1") -> DataFrame:
    """Estimates from samples: ``k1`` mean log ratio, ``k3`` the non-negative form; ``exact``: sum over a policy table."""
    d = F.col("logp") - F.col("logp_ref")
    if kind == "exact":
        return df.groupBy("question_class").agg(F.sum(F.exp("logp") * d).alias("kl"))
    return df.agg(F.avg(d if kind == "k1" else F.exp(-d) - 1 + d).alias("kl"))


def dead_groups(df: DataFrame, group: list[str] = ["question_id"], reward: str = "total") -> DataFrame:  # noqa: B006
    """Groups whose rewards are all equal carry no signal."""
    per = df.groupBy(*group).agg((F.min(reward) == F.max(reward)).alias("dead"))
    return per.agg(F.sum(F.col("dead").cast("long")).alias("dead"), F.count("*").alias("groups"))


def reward_cube(scored: DataFrame) -> DataFrame:
    """``(question_id, kind, total, ex, n_tok_out)``: rewards of all kinds once, so that training executes nothing."""
    return scored.select("question_id", "kind", "total", F.coalesce("equal", F.lit(False)).alias("ex"), "n_tok_in", "n_tok_out")


def gradient(df: DataFrame, policy: Policy, eps: float = 0.2) -> tuple[np.ndarray, float]:
    """Gradient of the mean clipped surrogate in theta and the surrogate itself. Rows have ``family``, ``kind``, ``adv``,
    ``logp``, ``logp_old`` and ``group`` size; a clipped row pulls nothing. One row per parameter reaches the driver, in
    decimal sums and taken in one order, so that the result is the same bit for bit on any layout."""
    return _assembled(_sums(df, eps), policy)


def _sums(df: DataFrame, eps: float, *more: Column) -> list:
    """One row a parameter that occurs: its pull, its part of the surrogate and of the groups, and ``more`` sums."""
    r, a = ratio(), F.col("adv")
    live = ~(((a > 0) & (r > 1 + eps)) | ((a < 0) & (r < 1 - eps)))
    pull = F.when(live, r * a).otherwise(0.0)
    return df.groupBy("family", "kind").agg(F.sum(_exact(pull / F.col("group"))).alias("g"), F.sum(_exact(surrogate_term(eps) / F.col("group"))).alias("s"),
                                            F.sum(_exact(1.0 / F.col("group"))).alias("w"), *more).collect()


def _assembled(sums: list, policy: Policy) -> tuple[np.ndarray, float]:
    grad, at = np.zeros_like(policy.theta), {c: i for i, c in enumerate(policy.classes)}
    groups = float(sum(x["w"] for x in sums)) or 1.0
    for x in sums:
        grad[at[x["family"]], policy.kinds.index(x["kind"])] += float(x["g"])
    grad -= policy.probs() * grad.sum(axis=1, keepdims=True)
    return grad / groups, float(sum(x["s"] for x in sums)) / groups


@dataclass
class Adam:
    rate: float = 0.3
    b1: float = 0.9
    b2: float = 0.95
    decay: float = 0.01
    m: np.ndarray | None = None
    v: np.ndarray | None = None
    t: int = 0

    def step(self, theta: np.ndarray, grad: np.ndarray) -> np.ndarray:
        """Ascent with decoupled decay."""
        if self.m is None:
            self.m, self.v = np.zeros_like(theta), np.zeros_like(theta)
        self.t += 1
        self.m = self.b1 * self.m + (1 - self.b1) * grad
        self.v = self.b2 * self.v + (1 - self.b2) * grad**2
        m, v = self.m / (1 - self.b1**self.t), self.v / (1 - self.b2**self.t)
        return theta * (1 - self.rate * self.decay) + self.rate * m / (np.sqrt(v) + 1e-8)


def kl_gradient(policy: Policy, reference: Policy, weights: np.ndarray) -> np.ndarray:
    """Gradient of the exact KL to the reference, averaged over classes by ``weights``."""
    p, q = policy.probs(), reference.probs()
    log = np.log(p) - np.log(q)
    return weights[:, None] * p * (log - (p * log).sum(axis=1, keepdims=True))


@dataclass
class Run:
    policy: Policy
    trace: list[tuple] = field(default_factory=list)
    snapshots: dict[int, Policy] = field(default_factory=dict)


def _traced(sums: list) -> tuple[float, float, float, int]:
    """Mean and deviation of the reward, mean length, and groups without a signal, from exact sums."""
    n, r, q, t, d = (sum(x[c] for x in sums) for c in ("n", "r", "q", "t", "d"))
    if not n:
        return 0.0, 0.0, 0.0, 0
    spread = (q - r * r / n) / (n - 1) if n > 1 else 0
    return float(r / n), math.sqrt(max(0.0, float(spread))), float(t / n), round(d)


def train(questions: DataFrame, cube: DataFrame, start: Policy, steps: int = 12, group: int = 8, inner: int = 1, eps: float = 0.2, beta: float = 0.04,
          seed: int = 1, every: int = 4, rate: float = 0.3) -> Run:
    """Samples, scores and updates for ``steps`` rounds; the trace has step, mean and deviation of reward, mean length,
    surrogate, KL and zero-signal groups. ``questions`` and ``cube`` should be written tables: each step reads them
    afresh, so no lineage grows, and is one aggregation; ``inner`` updates reuse a sample, where clipping begins to bite, and
    add one each."""
    reference, policy, adam = start, Policy(start.classes, start.kinds, start.theta.copy()), Adam(rate)
    run = Run(policy)
    sizes = {r["family"]: r["n"] for r in questions.groupBy("family").agg(F.count("*").alias("n")).collect()}  # one row a class
    weights = np.array([sizes.get(c, 0) for c in policy.classes], float)
    weights /= weights.sum() or 1.0
    whole = Window.partitionBy("question_id")
    for step in range(steps):
        old = Policy(policy.classes, policy.kinds, policy.theta.copy())
        rows = advantages(old.sample(questions.select("question_id", "family"), group, seed, step).join(cube, ["question_id", "kind"]), exact=True)
        rows = (rows.withColumn("group", F.lit(float(group))).withColumn("logp_old", old.logp()).withColumn("dead", F.min("total").over(whole) == F.max("total").over(whole))
                .withColumn("size", F.count("*").over(whole)))
        rows = rows.persist() if inner > 1 else rows
        try:
            sums = _sums(rows.withColumn("logp", F.col("logp_old")), eps, F.count("*").alias("n"), F.sum(_exact("total")).alias("r"), F.sum(_exact(F.col("total") * F.col("total"))).alias("q"),
                         F.sum("n_tok_out").alias("t"), F.sum(_exact(F.when(F.col("dead"), 1.0 / F.col("size")).otherwise(0.0))).alias("d"))
            mean, spread, length, dead = _traced(sums)
            grad, value = _assembled(sums, policy)
            policy.theta = adam.step(policy.theta, grad - beta * kl_gradient(policy, reference, weights))
            for _ in range(inner - 1):
                grad, value = gradient(rows.withColumn("logp", policy.logp()), policy, eps)
                policy.theta = adam.step(policy.theta, grad - beta * kl_gradient(policy, reference, weights))
        finally:
            if inner > 1:
                rows.unpersist()
        kl_now = float((weights * kl_exact(policy.probs(), reference.probs())).sum())
        run.trace.append((step, mean, spread, length, float(value), kl_now, dead))
        if every and (step + 1) % every == 0:
            run.snapshots[step + 1] = Policy(policy.classes, policy.kinds, policy.theta.copy())
    run.policy = policy
    return run


TRACE = "step int, mean_reward double, sd_reward double, mean_len double, surrogate double, kl double, dead long"


def fit_mle(records: DataFrame, start: Policy, strength: float = 8.0) -> Policy:
    """Maximum likelihood on kept records with ``strength`` pseudo-counts of the starting policy: one counting pass."""
    at = {c: i for i, c in enumerate(start.classes)}
    counts = start.probs() * strength
    for r in records.groupBy("family", "kind").agg(F.count("*").alias("n")).collect():
        counts[at[r["family"]], start.kinds.index(r["kind"])] += r["n"]
    return Policy(start.classes, start.kinds, np.log(counts / counts.sum(axis=1, keepdims=True)))
