"""Time limits: what runs away ends, whenever its jobs start and whatever its plan, and leaves nothing behind."""

import time

import pytest

from sqltutor.operators import mutate
from sqltutor.plans import execution
from sqltutor.sources import load


def _busy(spark):
    return sum(x.numRunningTasks() for x in spark.sparkContext._jsc.sc().statusTracker().getExecutorInfos())


def test_a_limit_holds_for_jobs_that_start_after_it(spark):
    def work():
        time.sleep(1)  # planning may take longer than the limit
        return spark.range(0, 30_000_000_000, 1, 2).where("hash(id) = 7 AND hash(id + 1) = 7").count()

    began = time.perf_counter()
    with pytest.raises(execution.TimeLimit):
        execution.limited(spark, 0.2, work)
    assert time.perf_counter() - began < 10


@pytest.mark.parametrize("profile", [execution.ADAPTIVE, execution.STATIC], ids=lambda p: p.name)
def test_a_runaway_text_leaves_no_task_behind(spark, sf, profile):
    load.views(spark, sf)
    text = mutate.RUNAWAY.format(table="documents", key="doc_id")
    assert execution.run_one(spark, text, ("documents",), profile, repeats=0, limit_s=1.5)[0] == "timeout"
    until = time.perf_counter() + 10
    while _busy(spark) and time.perf_counter() < until:
        time.sleep(0.2)
    assert _busy(spark) == 0


def test_settings_of_stoppable_texts_stay_apart(spark, sf):
    load.views(spark, sf)
    before = {k: spark.conf.get(k, None) for k in execution.STOPPABLE}
    loops = "SELECT COUNT(*) AS n FROM region AS a CROSS JOIN region AS b CROSS JOIN nation AS c"
    home = execution.stoppable(spark, loops)
    assert home is not spark and home.sql(loops).first()["n"] == spark.sql(loops).first()["n"] == 625
    assert {k: spark.conf.get(k, None) for k in execution.STOPPABLE} == before
    assert execution.stoppable(spark, "SELECT COUNT(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey") is spark
