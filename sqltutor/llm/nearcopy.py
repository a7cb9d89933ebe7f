"""Near copies by five-word shingles: SimHash grid, content cells, Manhattan bound on popcounts, exact Jaccard similarity.

Documents link if their sets of five-word shingles have a Jaccard similarity of ``SIMILARITY`` or more (fewer words: the
whole sequence is the one shingle; no words: all such documents are one). Fingerprints are embedded as segment popcounts
and joined on a grid under Manhattan distance (``simhash.links``): those that two bits connect, and texts of one
fingerprint, are a cell. At ``SIMILARITY`` 64-bit fingerprints lie about ten bits apart and some up to twenty, too far for
a grid over the fingerprint alone to tell them from chance. So further cells, for pairs out of the grid's reach, are named
by the content: ``KEYS`` minima of hashed shingles, in ``TABLES`` independent tables. Two documents at the threshold
share a cell of one table with probability ``SIMILARITY ** KEYS``, and miss all with 0.00001 at the values here; more alike
ones miss less. Inside a cell the fingerprints' segment popcounts bound their distance from below, pairs over ``FAR`` bits
are dropped, and shingle sets decide.

No pairs are made in rows. A cell goes to one task as its members' shingle sets, and the task keeps a forest: members that
are already connected are not compared again, and only the links that joined two trees leave. Cells with equal members are
worked on once. A cell over ``CELL_BYTES`` is split by a hash of its members into blocks, and each pair of blocks is a task
of its own, so no cell has to fit one task and none is cut off.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import simhash
from .common import Scratch, packed_rows, parts_for, text_of, unpacked
from .graph import components

WORDS, SIMILARITY, TABLES, KEYS, FAR, SEED, CELL_BYTES, TASK_BYTES = 5, 0.8, 16, 3, 24, 42, 32 << 20, 16 << 20
_STEP = 4096
_TURNS = np.random.default_rng(SEED).integers(1, 1 << 63, TABLES * KEYS, dtype=np.uint64) | np.uint64(1)
SKETCH = "struct<digest:binary, fp:bigint, n:int, cells:array<bigint>>"


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().lower().split()


def shingles(words: list[bytes]) -> np.ndarray:
    """Hashes of the different shingles, ascending."""
    if not words:
        return np.zeros(0, np.uint64)
    flat, size = b" ".join(words), len(words)
    span = min(WORDS, size)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, size) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))[: size - span + 1].tolist()
    digest = xxhash.xxh64_digest
    return np.unique(np.frombuffer(b"".join([digest(flat[s:e], SEED) for s, e in zip(starts, ends[span - 1 :].tolist(), strict=True)]), ">u8").astype(np.uint64))


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def sketch(text: str | None) -> dict:
    """Digest of the words, SimHash and number of different shingles, and the names of the cells."""
    words = words_of(text)
    known = shingles(words)
    ones, least = np.zeros(64, np.int64), np.full(len(_TURNS), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(known), _STEP):
        part = known[at : at + _STEP]
        ones += np.unpackbits(part.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
        least = np.minimum(least, (part[:, None] * _TURNS).min(axis=0))
    fp = int.from_bytes(np.packbits(ones * 2 > len(known)).tobytes(), "big")
    raw, width = least.tobytes(), 8 * KEYS
    cells = [_signed(xxhash.xxh64_intdigest(raw[k * width : (k + 1) * width], k)) for k in range(TABLES)] if len(known) else []
    return {"digest": xxhash.xxh3_128_digest(b" ".join(words)), "fp": _signed(fp), "n": len(known), "cells": cells}


def _sketches(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
    kind = pa.struct([("digest", pa.binary()), ("fp", pa.int64()), ("n", pa.int32()), ("cells", pa.list_(pa.int64()))])
    for texts in batches:
        yield pa.array([sketch(x) for x in texts.to_pylist()], kind)


def sketch_of(text: Column) -> Column:
    return F.arrow_udf(_sketches, SKETCH)(text)


def _sets(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
    for texts in batches:
        yield pa.array([shingles(words_of(x)).tobytes() for x in texts.to_pylist()], pa.binary())


def _popcounts(prints: np.ndarray) -> np.ndarray:
    """Bit counts of the sixteen four-bit segments."""
    nibbles = prints.astype("<i8").view(np.uint8).reshape(-1, 8)
    return np.bitwise_count(np.concatenate([nibbles & 15, nibbles >> 4], axis=1)).astype(np.int16)


def forest(prints: np.ndarray, sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Links that connect all members as all pairs at ``SIMILARITY`` would; no pair inside one tree is compared."""
    order = np.argsort([len(s) for s in sets], kind="stable")
    sizes = np.array([len(s) for s in sets])[order]
    prints, tree, links = prints[order], np.arange(len(order)), []
    counts = _popcounts(prints)
    for i in range(len(order) - 1):
        mine = sets[order[i]]
        upto = np.searchsorted(sizes, int(len(mine) / SIMILARITY + 1e-9), "right")
        rest = np.arange(i + 1, upto)
        rest = rest[tree[rest] != tree[i]]
        rest = rest[np.abs(counts[rest] - counts[i]).sum(axis=1) <= FAR]
        rest = rest[np.bitwise_count((prints[rest] ^ prints[i]).view(np.uint64)) <= FAR]
        for j in rest.tolist():
            if tree[j] == tree[i]:
                continue
            other = sets[order[j]]
            both = int((other[np.minimum(np.searchsorted(other, mine), len(other) - 1)] == mine).sum())
            if both >= SIMILARITY * (len(mine) + len(other) - both) - 1e-9:
                links.append((int(order[i]), int(order[j])))
                tree[tree == tree[j]] = tree[i]
    return links


def _linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in order of (cell, i, j); the members of one such key are held at a time."""
    key, nodes, prints, sets = None, [], [], []

    def flush():
        found = forest(np.array(prints, np.int64), [np.frombuffer(s, np.uint64) for s in sets]) if len(nodes) > 1 else []
        return pa.RecordBatch.from_arrays([pa.array([nodes[x[k]] for x in found], pa.int64()) for k in (0, 1)], ["a", "b"])

    for batch in batches:
        for *now, node, fp, known in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if now != key:
                if len(nodes) > 1:
                    yield flush()
                key, nodes, prints, sets = now, [], [], []
            nodes.append(node)
            prints.append(fp)
            sets.append(known)
    if len(nodes) > 1:
        yield flush()


def grid(spark: SparkSession, nodes: DataFrame) -> DataFrame:
    """``(node, fp, n, cell)``: a cell of its own for each set of fingerprints that the grid join connects."""
    scratch = Scratch(spark, "grid")
    shown = nodes.where("n > 0").select("node", "fp", "n")
    joined = components(spark, simhash.links(spark, shown.select("fp").distinct(), scratch))
    placed = shown.join(joined.withColumnRenamed("node", "fp"), "fp", "left")
    out = scratch.save(placed.select("node", "fp", "n", F.xxhash64(F.lit("grid"), F.coalesce("component", "fp")).alias("cell")), "cells")
    scratch.drop("members")
    return out


def links(spark: SparkSession, marked: DataFrame, nodes: DataFrame, scratch: Scratch, cell_bytes: int = CELL_BYTES) -> DataFrame:
    """``(a, b)`` between different texts, named by a row that has each (``node``); ``marked`` has ``row`` and ``text``."""
    cells = nodes.select("node", "fp", "n", F.explode("cells").alias("cell")).unionByName(grid(spark, nodes))
    mark = F.xxhash64("node")
    shared = (cells.groupBy("cell").agg(F.count("*").alias("size"), F.sum(mark.cast("decimal(38,0)")).alias("total"), F.bit_xor(mark).alias("mixed"), F.sum("n").alias("n"))
              .where("size > 1").groupBy("size", "total", "mixed").agg(F.min("cell").alias("cell"), F.first("n").alias("n")))
    members = scratch.save(cells.drop("n").join(shared.select("cell", F.ceil(8 * F.col("n") / cell_bytes).cast("int").alias("blocks")), "cell"), "members")
    needed = scratch.save(members.select("node").distinct(), "needed")
    sets = marked.select(F.col("row").alias("node"), "text").join(needed, "node", "left_semi").select("node", F.arrow_udf(_sets, "binary")(F.col("text")).alias("known"))
    sets = scratch.save(sets, "sets")
    block = F.pmod(F.xxhash64(F.lit(1), "node"), F.col("blocks")).cast("int")
    pairs = F.explode(F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda k: F.struct(F.least(block, k).alias("i"), F.greatest(block, k).alias("j"))))
    dealt = members.select("cell", "node", "fp", pairs.alias("at")).join(sets, "node").select("cell", "at.i", "at.j", "node", "fp", "known")
    volume = members.join(sets.select("node", F.octet_length("known").alias("bytes")), "node").agg(F.coalesce(F.sum(F.col("bytes") * F.col("blocks")), F.lit(0))).first()[0]
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), parts_for(spark, int(volume), TASK_BYTES))
    return dealt.repartition(parts, "cell", "i", "j").sortWithinPartitions("cell", "i", "j").mapInArrow(_linked, "a long, b long")


def classes(spark: SparkSession, marked: DataFrame, scratch: Scratch, cell_bytes: int = CELL_BYTES) -> DataFrame:
    """``(row, doc_id, label)`` for each row of ``marked``; a class has one label."""
    sketched = scratch.save(marked.select("row", "doc_id", sketch_of(F.col("text")).alias("s")), "sketches").select("row", "doc_id", "s.*")
    nodes = sketched.groupBy("digest").agg(F.min(F.struct("row", "fp", "n", "cells")).alias("x"))
    nodes = scratch.save(nodes.select("digest", F.col("x.row").alias("node"), "x.fp", "x.n", "x.cells"), "nodes")
    named = components(spark, links(spark, marked, nodes, scratch, cell_bytes))
    named = nodes.select("digest", "node").join(named, "node", "left").select("digest", F.coalesce("component", "node").alias("label"))
    return sketched.select("row", "doc_id", "digest").join(named, "digest").select("row", "doc_id", "label")


def numbered(docs: DataFrame, scratch: Scratch) -> DataFrame:
    """``(row, doc_id, text, whole)``: written, so that row numbers hold; ``whole`` has the caller's columns."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), packed_rows(docs).alias("whole"))
    return scratch.save(rows, "rows").select("row", F.col("whole.doc_id").alias("doc_id"), F.coalesce("whole.text", F.lit("")).alias("text"), "whole")


def first_of_each(marked: DataFrame, labelled: DataFrame, scratch: Scratch, columns: list[str]) -> DataFrame:
    """The row of each label with the smallest id, rows without one last, then the first row. What goes is joined, since
    it is less than what stays, and texts move only if it is too large to be sent to all."""
    labelled = scratch.save(labelled, "labelled")
    first = labelled.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")).alias("x")).select(F.col("x.row").alias("row"))
    gone = scratch.save(labelled.select("row").join(first, "row", "left_anti"), "gone")
    return unpacked(marked.join(gone, "row", "left_anti"), "whole", columns)


def keep_one(spark: SparkSession, docs: DataFrame, cell_bytes: int = CELL_BYTES) -> DataFrame:
    """The rows of ``docs`` that stay: of each class of near copies one, the one with the smallest id; ties: the first row.

    Null and empty texts, and texts of white space, have no words and are one class. A class whose rows all lack an id
    keeps its first row. Columns stay as they were, whatever their names. Empty table: no rows."""
    scratch = Scratch(spark, "nearcopies")
    marked = numbered(docs, scratch)
    out = first_of_each(marked, classes(spark, marked, scratch, cell_bytes), scratch, docs.columns)
    for name in ("members", "needed", "sets", "sketches", "nodes"):  # the labels are written by now
        scratch.drop(name)
    return out
