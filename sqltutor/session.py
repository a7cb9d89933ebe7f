"""Session helpers that never touch settings fixed at start."""

from __future__ import annotations

import os
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = str(Path(__file__).resolve().parent.parent)


def local(cores: str = "*", partitions: int = 8) -> SparkSession:
    """A session for tests and the bench."""
    return (SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", partitions)
            .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false")
            .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate())


def reach_workers(spark: SparkSession) -> None:
    """Lets Python workers import this package from where the driver found it, as ``--py-files`` would on a cluster."""
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "").split(os.pathsep)
    if ROOT not in have:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *filter(None, have)])
