"""Concatenate and cut: one endless token stream, cut into fixed windows at offsets from two passes of prefix sums.

First pass: tokenise, keep packed ids, and give each document its offset inside its partition. Partition totals (one row
per partition) give partition offsets. Second pass: every document knows its place in the whole stream, so each cuts
itself at window edges alone; a document that crosses edges leaves one boundary record per window it touches.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import slices, vocabulary
from .common import Scratch, prefix_sums, text_of
from .tokens import Library

LENGTH, END = 1024, 0
CODED = "doc_id long, part long, before long, n long, ids binary"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def tokenised(docs: DataFrame, path: str, end: int) -> DataFrame:
    """Ids of each document with ``end`` appended, and the tokens before it in its partition."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, part, before = Library(path), TaskContext.get().partitionId(), 0
        width = np.dtype(coder.v.kind).itemsize
        last = np.array([end], coder.v.kind).tobytes()
        for b in batches:
            for start, texts in slices(b.column(1)):
                ids = [x + last for x in coder.encode_batch(texts)]
                sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // width
                ends = before + np.cumsum(sizes)
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(start, len(texts)), pa.array(np.full(len(ids), part, np.int64)), pa.array(ends - sizes),
                     pa.array(sizes), pa.array(ids, pa.binary())], [f.split()[0] for f in CODED.split(", ")])
                before = int(ends[-1])

    return docs.select(F.col("doc_id").cast("long"), text_of().alias("text")).mapInArrow(run, CODED)


def _cut(path: str, length: int, with_ids: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = vocabulary(path).kind
        for b in batches:
            rows, kept = [], []
            for doc, at, n, packed in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                ids = np.frombuffer(packed.as_buffer(), kind).astype("<u4")
                start = 0
                while start < n:
                    offset = (at + start) % length
                    size = min(length - offset, n - start)
                    piece = ids[start : start + size]
                    rows.append((doc, start, size, zlib.crc32(piece), n, (at + start) // length, offset))
                    if with_ids:
                        kept.append(piece.astype(kind).tobytes())
                    start += size
            cols = [pa.array(c, pa.int64()) for c in zip(*rows, strict=True)] if rows else [pa.array([], pa.int64())] * 7
            names = [f.split()[0] for f in PIECES.split(", ")]
            if with_ids:
                cols, names = [*cols, pa.array(kept, pa.binary())], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(cols, names)

    return run


def packed(spark: SparkSession, docs: DataFrame, path: str, length: int = LENGTH, end: int = END, with_ids: bool = False) -> DataFrame:
    """One row per piece; only the last sequence is short of ``length`` tokens and needs padding.

    Null and empty texts are their end id alone. Repeated ids and rows each get their place. Empty table: no rows.
    Extra columns are ignored. ``with_ids`` adds each piece's packed ids.
    """
    coded = Scratch(spark, "packing").save(tokenised(docs, path, end), "ids")
    totals = coded.groupBy("part").agg(F.sum("n").alias("total"))
    placed = coded.join(F.broadcast(prefix_sums(totals, "part", "total", "base").select("part", "base")), "part")
    rows = placed.select("doc_id", (F.col("base") + F.col("before")).alias("at"), "n", "ids")
    return rows.mapInArrow(_cut(path, length, with_ids), PIECES + (", ids binary" if with_ids else ""))


def padding(pieces: DataFrame, length: int = LENGTH) -> DataFrame:
    """Sequences, tokens and padding of a packing."""
    per = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    return per.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(F.lit(length) - F.col("n")).alias("padding"))
