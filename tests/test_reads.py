"""Queries whose rows were constants or generated texts read the given tables."""

import pytest

from sqltutor import registry
from sqltutor.sources.load import TABLES, table


@pytest.mark.parametrize("name", ["leaderboard", "published_arms", "retention", "workload_w18", "workload_w1"])
def test_rows_come_from_a_table(spark, sf, name):
    files = registry.QUERIES[name](spark, sf).inputFiles()
    assert any(f.endswith(("lineitem.parquet", "events.parquet")) for f in files)


def test_texts_to_parse_are_those_of_asked_questions(spark, sf, tmp_path):
    for t in TABLES:
        rows = table(spark, sf, t)
        (rows if t == "region" else rows.limit(0)).write.parquet(f"{tmp_path}/{t}.parquet")
    got = registry.QUERIES["real_parser"](spark, str(tmp_path)).collect()
    assert {r.family for r in got} == {"A05", "B01", "B04"} and all(r.parses == (r.kind != "syntax_error") for r in got)


def test_retention_and_arm_table_by_hand(spark):
    from sqltutor.operators import metrics

    rows = [("a", "s", True, True, 10, 10), ("a", "s", False, False, 10, 10), ("b", "s", True, True, 10, 30), ("b", "s", True, False, 10, 30), ("a", "u", True, True, 1, 1), ("b", "u", False, False, 1, 1)]
    df = spark.createDataFrame(rows, "arm string, suite string, ex boolean, em boolean, n_tok_in int, n_tok_out int")
    assert {tuple(r) for r in metrics.retention(df, "a", "b").collect()} == {("s", 50.0, 100.0, 50.0, True), ("u", 100.0, 0.0, -100.0, False)}
    got = {(r.arm, r.suite): tuple(r)[2:] for r in metrics.arm_table(df, "a", "b").collect()}
    assert got["a", "s"] == (0.5, None, None) and got["b", "s"] == (0.5, 1.0, 1.0)
