"""SimHash near-duplicates: segment-popcount embedding, grid join under Manhattan distance, exact check.

A 64-bit fingerprint is cut into 32 segments of two bits and mapped to the vector of their bit counts. The Manhattan
distance of two such vectors never exceeds the Hamming distance of the fingerprints, so it is a safe filter. Grid: the
vector is split into four blocks; vectors within distance two differ in at most two blocks, so they share the cell
(two whole blocks) of at least one of the six pairs of blocks. Cells are joined, the lower bound drops most pairs, and
the Hamming distance decides.

Cells with more than ``CELL`` different fingerprints are not expanded into pairs. Their members go another, equally
exact way: two fingerprints differ in at most two bits if and only if some 64-bit value lies within one bit of both.
Each member names the 65 values of its radius-one ball; all that name a value are linked to the smallest of them.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, text_of
from .graph import components

BITS, SEED, WORDS, DISTANCE, CELL = 64, 42, 3, 2, 48
_LOW = 0x5555555555555555
_PAIRS = list(itertools.combinations(range(4), 2))
_BLOCK = 4096


def fingerprint(text: str | None) -> int:
    """Signed 64-bit SimHash over word shingles; no words: 0."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    flat, size = b" ".join(words), len(words)
    span = min(WORDS, size)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, size) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[: size - span + 1].tolist()
    digest = xxhash.xxh64_digest
    hashes = b"".join([digest(flat[s:e], SEED) for s, e in zip(starts, ends[span - 1 :].tolist(), strict=True)])
    rows, counts = np.frombuffer(hashes, np.uint8).reshape(-1, 8), np.zeros(BITS, np.int64)
    for at in range(0, len(rows), _BLOCK):
        bits = np.unpackbits(rows[at : at + _BLOCK], axis=1)
        whole = len(bits) // 255 * 255
        counts += bits[:whole].reshape(-1, 255, BITS).sum(axis=1, dtype=np.uint8).sum(axis=0, dtype=np.int64)
        counts += bits[whole:].sum(axis=0, dtype=np.uint8)
    return int.from_bytes(np.packbits(counts * 2 > len(rows)).tobytes(), "big", signed=True)


def _column(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for texts in batches:
        yield pa.array([fingerprint(x) for x in texts.to_pylist()], pa.int64())


def fingerprint_of(text: Column) -> Column:
    return F.arrow_udf(_column, T.LongType())(text)


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _embedding(fp: Column) -> Column:
    """Bit counts of the two-bit segments, each in unary (0: 00, 1: 01, 2: 11), so that distances are popcounts of XOR."""
    high, low = F.shiftrightunsigned(fp, 1).bitwiseAND(F.lit(_LOW)), fp.bitwiseAND(F.lit(_LOW))
    return high.bitwiseOR(low).bitwiseOR(F.shiftleft(high.bitwiseAND(low), 1))


def _mask(pair: tuple[int, int]) -> int:
    value = sum(0xFFFF << (16 * block) for block in pair)
    return value - (1 << 64) if value >= 1 << 63 else value


def links(spark: SparkSession, prints: DataFrame, scratch: Scratch, cell: int = CELL) -> DataFrame:
    """``prints(fp)``, each value once -> links ``(a, b)`` that connect all that lie within two bits of each other."""
    embedded = prints.select("fp", _embedding(F.col("fp")).alias("e"))
    cells = embedded.select("fp", "e", F.explode(F.array(*[
        F.struct(F.lit(i).cast("byte").alias("grid"), F.col("e").bitwiseAND(F.lit(_mask(p))).alias("cell"))
        for i, p in enumerate(_PAIRS)])).alias("at")).select("fp", "e", "at.grid", "at.cell")
    shared = cells.groupBy("grid", "cell").agg(F.count("*").alias("n")).where("n > 1")
    members = scratch.save(cells.join(shared, ["grid", "cell"]), "members")
    light, heavy = members.where(F.col("n") <= cell), members.where(F.col("n") > cell)
    other = light.select("grid", "cell", F.col("fp").alias("b"), F.col("e").alias("eb"))
    near = (light.select("grid", "cell", F.col("fp").alias("a"), "e").join(other, ["grid", "cell"])
            .where((F.col("a") > F.col("b"))
                   & (F.bit_count(F.col("e").bitwiseXOR(F.col("eb"))) <= DISTANCE)
                   & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= DISTANCE)).select("a", "b"))
    ball = heavy.select("fp").distinct().select("fp", F.explode(F.concat(
        F.array("fp"), F.transform(F.sequence(F.lit(0), F.lit(BITS - 1)),
                                   lambda i: F.expr("fp").bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))))).alias("at"))
    least = ball.groupBy("at").agg(F.min("fp").alias("b"), F.count("*").alias("n")).where("n > 1").select("at", "b")
    return near.union(ball.join(least, "at").where("fp <> b").select(F.col("fp").alias("a"), "b").distinct())


def classes(spark: SparkSession, prints: DataFrame, cell: int = CELL) -> DataFrame:
    """``prints(doc_id, fp)`` -> ``(fp, label, component_id)``, one row per different fingerprint.

    ``label`` names the component even where all its documents lack an id; ``component_id`` is the smallest id in it.
    """
    scratch = Scratch(spark, "simhash")
    nodes = scratch.save(prints.groupBy("fp").agg(F.min("doc_id").alias("first")), "nodes")
    linked = components(spark, links(spark, nodes.select("fp"), scratch, cell))
    named = nodes.join(linked.withColumnRenamed("node", "fp"), "fp", "left").select(
        "fp", "first", F.coalesce("component", "fp").alias("label"))
    named = scratch.save(named, "named")
    smallest = named.groupBy("label").agg(F.min("first").alias("component_id"))
    return named.join(smallest, "label").select("fp", "label", "component_id")


def near_duplicates(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``, a row for each row of ``docs``.

    Null or empty text has no words: fingerprint zero, linked like any other. Repeated rows each keep their row; rows
    without an id share in the class but cannot name it. An empty table gives an empty one; other columns are ignored.
    """
    scratch = Scratch(spark, "prints")
    prints = scratch.save(docs.select("doc_id", fingerprint_of(text_of()).alias("fp")), "prints")
    return prints.join(classes(spark, prints).drop("label"), "fp").select(
        "doc_id", hex_of(F.col("fp")).alias("fingerprint"), "component_id")


def keep_one(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay: of each class one, the one with the smallest id; ties: the first row. Null and empty
    texts are one class, with all that lie within two bits of fingerprint zero. Columns stay as they were."""
    from .nearcopy import first_of_each, numbered

    scratch = Scratch(spark, "distinct")
    marked = numbered(docs, scratch)
    prints = scratch.save(marked.select("row", "doc_id", fingerprint_of(F.col("text")).alias("fp")), "prints")
    labels = classes(spark, prints.select("doc_id", "fp")).select("fp", "label")
    return first_of_each(marked, prints.join(labels, "fp").select("row", "doc_id", "label"), scratch, docs.columns)
