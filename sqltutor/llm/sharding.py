"""Balanced label propagation over links between equal texts, in DataFrame joins only.

Law ``rows``: shard sizes differ by at most one document. Every document starts on a shard by a hash of its id. Linked
documents (equal texts, a star around the text's digest; never pairs) form cells of one text and one starting fibre.
Each round the cells of a text ask for the shard where most of its documents are; a shard grants requests in order
while its quota of linked documents lasts, small ones first, so none is refused that still fits. A move needs free room,
so texts that are apart after the rounds are then lifted from all their shards at once, which makes room for each other,
and set down whole, larger ones first, in passes until none fits any shard. Then every shard is filled to its exact size
with the documents that no link holds. A text larger than a shard fills several.
"""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Scratch, prefix_sums, text_of

SHARDS, FIBRES, BUCKETS = 24, 4, 64


def _described(docs: DataFrame) -> DataFrame:
    raw = F.col("text").cast("binary")
    return docs.select(
        "doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 8).alias("size"), F.crc32(text_of().cast("binary")).alias("text_crc32"),
        F.unhex(F.sha2(F.coalesce(raw, F.lit(b"")), 256)).alias("text_key"),
        F.pmod(F.xxhash64("doc_id"), F.lit(SHARDS * FIBRES)).cast("int").alias("fibre"))


def _granted(requests: DataFrame, free: dict[int, int]) -> DataFrame:
    """The requests ``(target, text_key, fibre, n)`` that fit in ``free[target]``, by ascending ``n``: one that is refused
    is no smaller than what follows, so it blocks nothing that fits.

    Running sums go in two levels, buckets of requests of a size first, so that no shard's requests meet in one task."""
    room = F.create_map(*[F.lit(x) for kv in free.items() for x in kv])
    return _summed(requests, ["target"], "n", ["text_key", "fibre"]).where(F.col("upto") <= F.element_at(room, F.col("target"))).drop("upto")


def _summed(rows: DataFrame, group: list[str], size: str, keys: list[str]) -> DataFrame:
    """``rows`` with ``upto``, the running sum of ``n`` inside ``group`` by ``size``, then hash bucket, then ``keys``."""
    at = [*group, size, "bucket"] if size in rows.columns else [*group, "rank", "bucket"]
    if size not in rows.columns:
        rows = rows.withColumn("rank", F.expr(size))
    bucketed = rows.withColumn("bucket", F.pmod(F.xxhash64(*keys), F.lit(_buckets(rows))).cast("int"))
    totals = bucketed.groupBy(*at).agg(F.sum("n").alias("asked"))
    before = Window.partitionBy(*group).orderBy(*at[len(group):]).rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(*at, F.coalesce(F.sum("asked").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy(*at).orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0)
    return (bucketed.withColumn("upto", F.sum("n").over(inside)).join(F.broadcast(totals), at)
            .withColumn("upto", F.col("base") + F.col("upto")).drop("bucket", "base", "rank"))


def _buckets(rows: DataFrame) -> int:
    """As many as the cluster shuffles into, so that a window's part shrinks as the cluster grows."""
    return max(BUCKETS, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def _load(cells: DataFrame) -> dict[int, int]:
    """Linked documents per shard: as many numbers as shards."""
    return {r["shard"]: r["n"] for r in cells.groupBy("shard").agg(F.sum("n").alias("n")).collect()}


def propagate(spark: SparkSession, cells: DataFrame, quota: dict[int, int], rounds: int | None = None) -> DataFrame:
    """``cells(text_key, fibre, n, shard)`` after the first round that moves nothing, or after ``rounds`` if given.

    A cell moves only to a shard that holds no less of its text than the one it leaves, so the sum of squares of a text's
    shares grows with each move and the rounds come to an end."""
    scratch = Scratch(spark, "labels")
    cells = scratch.save(cells, "cells-0")
    for step in itertools.count(1) if rounds is None else range(1, rounds + 1):
        load = _load(cells)
        free = {s: max(0, quota[s] - load.get(s, 0)) for s in quota}
        room = F.create_map(*[F.lit(x) for kv in free.items() for x in kv])
        at = cells.groupBy("text_key", "shard").agg(F.sum("n").alias("here"))
        best = (at.where((F.element_at(room, F.col("shard")) > 0) | (F.col("here") > 0)).groupBy("text_key")
                .agg(F.max(F.struct(F.when(F.element_at(room, F.col("shard")) > 0, F.col("here")).otherwise(F.lit(0)).alias("here"),
                                    (-F.col("shard")).alias("s"))).alias("best"))
                .where("best.here > 0").select("text_key", (-F.col("best.s")).alias("target"), F.col("best.here").alias("there")))
        asks = cells.join(best, "text_key").join(at, ["text_key", "shard"]).where(
            (F.col("shard") != F.col("target")) & (F.col("here") <= F.col("there")))
        moves = scratch.save(_granted(asks.select("target", "text_key", "fibre", "n"), free).select("text_key", "fibre", "target"), f"moves-{step}")
        if moves.isEmpty():
            break
        fresh = scratch.save(cells.join(moves, ["text_key", "fibre"], "left")
                             .select("text_key", "fibre", "n", F.coalesce("target", "shard").alias("shard")), f"cells-{step}")
        scratch.drop(f"cells-{step - 1}")
        cells = fresh
    return cells


def settle(spark: SparkSession, cells: DataFrame, quota: dict[int, int]) -> DataFrame:
    """``(text_key, fibre, shard)`` of the cells that keep or get a place.

    Texts that lie whole on a shard stay while its quota lasts; texts larger than a shard keep the cells that fit beside
    them. All others are set down whole: in each pass the shards' free rooms, largest first, lie end to end, texts
    follow each other along them, and those that cross no edge are placed. The largest text that fits a shard heads a
    pass, so each pass places one at least, and the last finds none that fits."""
    scratch = Scratch(spark, "settle")
    texts = scratch.save(cells.groupBy("text_key").agg(F.sum("n").alias("n"), F.min("shard").alias("shard"), F.max("shard").alias("last")), "texts")
    most = max(quota.values())
    whole = texts.where("shard = last").select("text_key", F.lit(0).alias("fibre"), "n", F.col("shard").alias("target"))
    placed = [scratch.save(_granted(whole.where(F.col("n") <= most), quota).select("text_key", "n", F.col("target").alias("shard")), "placed-0")]
    load = _load(placed[0])
    free = {s: quota[s] - load.get(s, 0) for s in quota}
    huge = cells.join(texts.where(F.col("n") > most).select("text_key"), "text_key", "left_semi")
    held = scratch.save(_granted(huge.withColumnRenamed("shard", "target"), free).select("text_key", "fibre", F.col("target").alias("shard"), "n"), "held")
    load = _load(held)
    free = {s: free[s] - load.get(s, 0) for s in quota}
    left = scratch.save(texts.where(F.col("n") <= most).join(placed[0].select("text_key"), "text_key", "left_anti").select("text_key", "n"), "left-0")
    while not (todo := left.where(F.col("n") <= max(free.values()))).isEmpty():
        step, order = len(placed), sorted(free, key=lambda s: (-free[s], s))
        rooms, upto = [], 0
        for s in order:
            rooms.append(F.struct(F.lit(s).alias("shard"), F.lit(upto).cast("long").alias("lo"), F.lit(upto + free[s]).cast("long").alias("hi")))
            upto += free[s]
        room = F.get(F.filter(F.array(*rooms), lambda r: (r["lo"] <= F.col("upto") - F.col("n")) & (F.col("upto") <= r["hi"])), F.lit(0))
        new = _summed(todo, [], "-n", ["text_key"]).withColumn("shard", room["shard"]).where("shard IS NOT NULL")
        placed.append(scratch.save(new.select("text_key", "n", "shard"), f"placed-{step}"))
        load = _load(placed[-1])
        free = {s: free[s] - load.get(s, 0) for s in quota}
        left = scratch.save(left.join(placed[-1].select("text_key"), "text_key", "left_anti"), f"left-{step}")
    at = placed[0]
    for more in placed[1:]:
        at = at.union(more)
    return cells.select("text_key", "fibre").join(at.select("text_key", "shard"), "text_key").union(held.select("text_key", "fibre", "shard"))


def _ranked(rows: DataFrame, group: list[str], order: list[str], out: str, by: list[str]) -> DataFrame:
    """Gapless rank from 0 inside ``group``, by hash bucket of ``by`` and then ``order``: counts per bucket, running
    sums of these few, and row numbers inside a bucket."""
    rows = rows.withColumn("__b", F.pmod(F.xxhash64(*by), F.lit(_buckets(rows))).cast("int"))
    counts = rows.groupBy(*group, "__b").agg(F.count("*").alias("__c"))
    if group:
        before = Window.partitionBy(*group).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
        counts = counts.select(*group, "__b", F.coalesce(F.sum("__c").over(before), F.lit(0)).alias("__base"))
    else:
        counts = prefix_sums(counts, "__b", "__c", "__base").drop("__c")
    number = F.row_number().over(Window.partitionBy(*group, "__b").orderBy(*order))
    return (rows.withColumn("__n", number).join(F.broadcast(counts), [*group, "__b"])
            .withColumn(out, (F.col("__base") + F.col("__n") - 1).cast("long")).drop("__b", "__n", "__base"))


def sharded(spark: SparkSession, docs: DataFrame, shards: int = SHARDS) -> DataFrame:
    """``(doc_id, size, text_crc32, law, shard, slot, grown_shard)``, one row per row of ``docs``.

    Null text: no bytes, size 8, in one group with empty texts. Repeated ids and rows each take a slot. Fewer documents
    than shards leave shards empty; an empty table gives no rows. Other columns are ignored.
    """
    scratch = Scratch(spark, "shards")
    rows = scratch.save(_described(docs), "rows")
    total = rows.count()
    quota = {s: total // shards + (s < total % shards) for s in range(shards)}
    cells = scratch.save(rows.groupBy("text_key", "fibre").agg(F.count("*").alias("n")), "all-cells")
    texts = cells.groupBy("text_key").agg(F.sum("n").alias("copies")).where("copies > 1").select("text_key")
    cells = cells.join(texts, "text_key", "left_semi").withColumn("shard", F.pmod("fibre", F.lit(shards)).cast("int"))
    cells = propagate(spark, cells, quota)
    held = scratch.save(settle(spark, cells, quota), "held")
    placed = scratch.save(rows.join(held, ["text_key", "fibre"], "left"), "placed")
    load = _load(placed.where("shard IS NOT NULL").withColumn("n", F.lit(1)))
    edges, upto = [], 0
    for s in range(shards):
        upto += quota[s] - load.get(s, 0)
        edges.append(upto)
    free = _ranked(placed.where("shard IS NULL"), [], ["text_key", "doc_id"], "__rank", ["text_key"])
    filled = free.withColumn("shard", F.size(F.filter(F.array(*[F.lit(e) for e in edges]), lambda e: e <= F.col("__rank"))).cast("int"))
    whole = scratch.save(placed.where("shard IS NOT NULL").select("doc_id", "size", "text_crc32", "text_key", "shard")
                         .union(filled.select("doc_id", "size", "text_crc32", "text_key", "shard")), "whole")
    slotted = _ranked(whole, ["shard"], ["doc_id", "text_key"], "slot", ["doc_id", "text_key"])
    return slotted.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def cut_share(result: DataFrame) -> DataFrame:
    """Share of linked documents that are away from their text's main shard."""
    at = result.groupBy("text_crc32", "size", "shard").agg(F.count("*").alias("n"))
    per = at.groupBy("text_crc32", "size").agg(F.sum("n").alias("n"), F.max("n").alias("most")).where("n > 1")
    return per.agg(F.sum(F.col("n") - F.col("most")).alias("away"), F.sum("n").alias("linked"))
