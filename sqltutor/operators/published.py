"""Numbers that the paper prints, as constants. They are references; nothing here was measured by this library."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Benchmark, model (rivals by place), score in percent.
LEADERBOARD = (("A", "full", 79.14), ("A", "rival 2", 75.36), ("A", "rival 3", 74.90), ("A", "rival 4", 74.12), ("A", "rival 5", 73.34),
               ("B", "rival 1", 91.20), ("B", "rival 2", 86.60), ("B", "rival 3", 86.20), ("B", "rival 4", 85.30), ("B", "full", 84.04),
               ("C", "rival 1", 26.77), ("C", "skeleton_efficiency", 21.98), ("C", "vanilla", 21.00), ("C", "full", 17.58), ("C", "rival 5", 11.73))
#: Arm, suite, EM, PGR, TEP.
ARMS = (("base", "A", 0.0424, None, None), ("vanilla", "A", 0.0437, 228.9231, -5.1557), ("skeleton", "A", 0.0200, -13.2857, -1.5149), ("efficiency", "A", 0.0463, 76.3077, 12.4175),
        ("skeleton_efficiency", "A", 0.1317, 3.3326, -6.4448), ("full", "A", 0.3400, 1.0, -3.6854),
        ("base", "B", 0.2195, None, None), ("vanilla", "B", 0.2244, -12.0408, 0.2290), ("skeleton", "B", 0.2408, -2.7700, 0.3273), ("efficiency", "B", 0.2137, 10.1724, 0.1508),
        ("skeleton_efficiency", "B", 0.2785, -1.0, 0.5247), ("full", "B", 0.1605, 1.0, 0.8276),
        ("base", "C", 0.1868, None, None), ("vanilla", "C", 0.2100, -0.4741, 0.2974), ("skeleton", "C", 0.1209, 0.1669, 0.2415), ("efficiency", "C", 0.1913, -2.4444, 0.0129),
        ("skeleton_efficiency", "C", 0.2198, -0.3333, 0.3464), ("full", "C", 0.1758, 1.0, 2.0393))
#: Test, base score, full arm's score.
GENERAL = (("instruction following", 76.71, 80.04), ("science questions", 53.36, 43.37), ("mathematics", 86.2, 81.4))
#: Corpus, items, mean tokens a question, mean tokens a query.
TRAINING = (("A", 9294, 486.84, 17.50), ("B", 5149, 289.91, 15.69))


def leaderboard(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(LEADERBOARD), "suite string, model string, score double")


def arms(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(ARMS), "arm string, suite string, em double, pgr double, tep double")


def retention(spark: SparkSession) -> DataFrame:
    """Change of the general tests, all of them; not rerunnable without a language model."""
    rows = spark.createDataFrame(list(GENERAL), "test string, base double, trained double")
    return rows.withColumn("delta", F.round(F.col("trained") - F.col("base"), 6)).withColumn("kept", F.col("trained") >= F.col("base"))


def training(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(TRAINING), "suite string, items long, tokens_question double, tokens_query double")
