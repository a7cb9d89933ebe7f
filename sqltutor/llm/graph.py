"""Connected components by repeated contraction towards the smallest neighbour."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch


def components(spark: SparkSession, edges: DataFrame) -> DataFrame:
    """``edges(a long, b long)`` -> ``(node long, component long)`` for every node that has an edge.

    The component is its smallest node. Each round every node adopts its smallest neighbour if that is smaller than
    itself, pointers are doubled until all reach a root, and both ends of every link are renamed; links inside one name
    vanish. Only nodes without a smaller neighbour stay, at most half of those that have links, so rounds and doublings
    grow with the logarithm of the number of nodes, on long chains too. State lives in written tables; only the number of links left comes to the driver. Null ends are ignored.
    """
    scratch = Scratch(spark, "components")
    links = scratch.save(
        edges.where("a IS NOT NULL AND b IS NOT NULL AND a <> b")
        .select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links-0")
    names = scratch.save(
        links.select(F.explode(F.array("a", "b")).alias("node")).distinct().withColumn("component", F.col("node")), "names-0")
    step = 0
    while not links.isEmpty():
        step += 1
        both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = both.groupBy("a").agg(F.min("b").alias("p")).select(F.col("a").alias("old"), F.least("a", "p").alias("p"))
        up = scratch.save(up, f"up-{step}")
        jump = 0
        while True:
            far = up.select(F.col("old").alias("p"), F.col("p").alias("pp"))
            jump += 1
            after = scratch.save(up.select("old", "p").join(far, "p", "left").select(
                "old", F.coalesce("pp", "p").alias("p"), F.coalesce(F.col("pp") != F.col("p"), F.lit(False)).alias("moved")), f"up-{step}-{jump}")
            still = after.where("moved").isEmpty()
            scratch.drop(f"up-{step}" if jump == 1 else f"up-{step}-{jump - 1}")
            up = after
            if still:
                break
        up = up.select("old", F.col("p").alias("new"))
        a = up.select(F.col("old").alias("a"), F.col("new").alias("na"))
        b = up.select(F.col("old").alias("b"), F.col("new").alias("nb"))
        moved = links.join(a, "a", "left").join(b, "b", "left").select(
            F.coalesce("na", "a").alias("a"), F.coalesce("nb", "b").alias("b"))
        fresh = scratch.save(
            moved.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), f"links-{step}")
        named = scratch.save(
            names.join(up.withColumnRenamed("old", "component"), "component", "left")
            .select("node", F.coalesce("new", "component").alias("component")), f"names-{step}")
        for gone in (f"links-{step - 1}", f"names-{step - 1}", f"up-{step}-{jump}"):
            scratch.drop(gone)
        links, names = fresh, named
    return names
