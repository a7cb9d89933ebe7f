"""SQL names for the functions: ``skeleton``, ``hybrid_similarity``, ``reward_of``, and table functions over texts."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .functions import skeleton, sqltext
from .functions.similarity import ALPHA, blocks


@udtf(returnType="kind string, text string, place int")
class SqlTokens:
    def eval(self, sql: str) -> Iterator[tuple]:
        for i, (kind, text) in enumerate(sqltext.tokens(sql)):
            yield kind, text, i


@udtf(returnType="clause string, item string")
class ClauseItems:
    def eval(self, sql: str) -> Iterator[tuple]:
        for clause, items in sqltext.decompose(sql).items():
            for item in items:
                yield clause, item


def _hybrid(a: str | None, b: str | None) -> float | None:
    if a is None or b is None:
        return None
    x, y = set(a.split()), set(b.split())
    return ALPHA * blocks(a, b) + (1 - ALPHA) * (len(x & y) / len(x | y) if x | y else 1.0)


def _hybrids(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
    for a, b in batches:
        yield pa.array([_hybrid(x, y) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.float64())


def register(spark: SparkSession) -> None:
    """``skeleton(sql)`` and ``reward_of(...)`` are SQL expressions the optimiser sees through; the rest runs in Python."""
    from pyspark.sql import functions as F

    spark.udf.register("hybrid_similarity", F.arrow_udf(_hybrids, "double"))
    spark.udtf.register("sql_tokens", SqlTokens)
    spark.udtf.register("clause_items", ClauseItems)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION reward_of(pattern_ok BOOLEAN, sim DOUBLE, success BOOLEAN, linked BOOLEAN, ratio DOUBLE) RETURNS DOUBLE "
              "RETURN CASE WHEN NOT pattern_ok OR sim < 0.6 THEN -2D WHEN success THEN 3D + LEAST(1D, ratio) WHEN linked THEN 0D ELSE -1.5D END")


def skeleton_of(column):
    return skeleton.emphasise(skeleton.extract(column))
