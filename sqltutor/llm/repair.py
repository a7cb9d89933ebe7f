"""Token files under Re-Pair grammars.

A file holds a run of documents in ascending order of id. Frequent pairs of neighbouring ids are replaced by
nonterminals, many pairs a round, until no pair is left at ``LEAST`` places or symbols run out. Rules, their expansion lengths and the compressed
sequence are stored; running sums of expansion lengths find any token without decoding what comes before it.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe import slices
from .common import Scratch, parts_for, prefix_sums, text_of
from .files import NewFile, open_fs
from .tokens import Library

END, LEAST, PER_ROUND, SYMBOLS, SHARD, PER_TASK = 2, 12, 4096, 1 << 16, 2_000_000, 8
_HEAD = struct.Struct("<8sIIIII")
MAGIC = b"REPAIR01"
MANIFEST = "part long, number long, file string, docs long, tokens long, bytes long"
ROWS = "doc_id long, start long, n_tokens long, ids_crc32 long"


def compress(ids: np.ndarray, base: int) -> tuple[np.ndarray, np.ndarray]:
    """``ids`` below ``base`` -> (sequence, rules); rule k stands for ``base + k`` and its two symbols come before it.

    Counts of pairs without a symbol of the last round only fall, so a later round counts pairs with such a symbol, those
    of the last round's pairs that are left, and all pairs only where the last round couldn't take every frequent one."""
    seq, rules, top, recent, live = ids.astype(np.uint32), [], base, 0, None
    while True:
        room = min(PER_ROUND, SYMBOLS - top)
        if len(seq) < 2 or room <= 0:
            break
        keys = (seq[:-1] << np.uint32(16)) | seq[1:]
        hashed = _mixed(keys)
        if live is None:
            ordered = np.sort(keys)
        else:
            new = seq >= recent
            ordered = np.sort(keys[new[:-1] | new[1:] | live.take(hashed)])
        if not len(ordered):
            break
        edge = np.flatnonzero(np.concatenate(([True], ordered[1:] != ordered[:-1])))
        counts = np.diff(np.append(edge, len(ordered)))
        often = np.flatnonzero(counts >= LEAST)
        if not len(often):
            break
        whole = len(often) <= room
        if not whole:
            often = np.sort(often[np.argpartition(-counts[often], room - 1)[:room]])
        chosen, times = ordered[edge[often]], counts[often]
        slots, shared, live = _slots(chosen)
        places = np.flatnonzero(live.take(hashed))
        at = slots.take(hashed.take(places))
        found = keys.take(places)
        odd = np.flatnonzero(shared[at])
        at[odd] = np.minimum(np.searchsorted(chosen, found[odd]), len(chosen) - 1)
        hit = chosen[at] == found
        places, at = places[hit], at[hit]
        won = _apart(places, times[at])
        places, at = places[won], at[won]
        there = np.bincount(at, minlength=len(chosen)) > 0
        rules.append(chosen[there])
        seq[places] = (top - 1 + np.cumsum(there))[at]
        keep = np.ones(len(seq), bool)
        keep[places + 1] = False
        seq, top, recent = seq[keep], top + int(there.sum()), top
        live = live if whole else None
    flat = np.concatenate(rules) if rules else np.zeros(0, np.uint32)
    return seq.astype("<u2"), np.stack([flat >> 16, flat & 0xFFFF], axis=1).astype("<u2")


def _slots(chosen: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash -> place in ``chosen``, which of ``chosen`` share their hash with another, and which hashes occur: a table of
    bytes, which all places ask and few pass."""
    at = _mixed(chosen)
    slots, live = np.zeros(1 << 20, np.int32), np.zeros(1 << 20, bool)
    live[at] = True
    slots[at] = np.arange(len(chosen), dtype=np.int32)
    lost = slots[at] != np.arange(len(chosen))
    shared = np.zeros(len(chosen), bool)
    shared[slots[at[lost]]] = True
    return slots, shared | lost, live


def _apart(places: np.ndarray, times: np.ndarray) -> np.ndarray:
    """Which places to replace where neighbours overlap: the more frequent pair's first; in a row of one frequency every
    other one. Places that beat both neighbours win and put these out, until all are decided."""
    won = np.ones(len(places), bool)
    touch = np.append(np.diff(places) == 1, False)
    rows = np.flatnonzero(touch | np.append(False, touch[:-1]))
    if not len(rows):
        return won
    won[rows] = False
    touch, times = touch[rows], times[rows].astype(np.int64)
    number = np.arange(len(rows))
    fresh = np.append(True, ~touch[:-1] | (times[1:] != times[:-1]))
    rank = 2 * times + ((number - np.maximum.accumulate(np.where(fresh, number, 0))) % 2 == 0)
    while len(rows):
        joined = touch[:-1]
        best = np.append(True, ~joined | (rank[1:] > rank[:-1])) & np.append(~joined | (rank[:-1] > rank[1:]), True)
        won[rows[best]] = True
        out = best.copy()
        out[1:] |= best[:-1] & joined
        out[:-1] |= best[1:] & joined
        left = ~out
        follows = np.append(left[1:], False)
        touch, rank, rows = (touch & follows)[left], rank[left], rows[left]
    return won


def _mixed(keys: np.ndarray) -> np.ndarray:
    return ((keys * np.uint32(2654435761)) >> np.uint32(12)).astype(np.intp)


def lengths(rules: np.ndarray, base: int) -> np.ndarray:
    """Tokens that each rule expands to."""
    out = np.ones(base + len(rules), np.uint32)
    for k, (a, b) in enumerate(rules.tolist()):
        out[base + k] = out[a] + out[b]
    return out[base:]


class Grammar:
    """A file's rules and sequence, ready for access to any range of tokens."""

    def __init__(self, rules: np.ndarray, sizes: np.ndarray, seq: np.ndarray, base: int):
        self.base, self.seq = base, seq
        self.sizes = np.concatenate([np.ones(base, np.int64), sizes.astype(np.int64)])
        self.starts = np.concatenate([np.arange(base), base + np.cumsum(sizes.astype(np.int64)) - sizes])
        table = np.empty(base + int(sizes.sum()), np.uint16)
        table[:base] = np.arange(base)
        for k, (a, b) in enumerate(rules.tolist()):
            s, n = self.starts[base + k], self.sizes[a]
            table[s : s + n] = table[self.starts[a] : self.starts[a] + n]
            table[s + n : s + n + self.sizes[b]] = table[self.starts[b] : self.starts[b] + self.sizes[b]]
        self.table, self.ends = table, np.cumsum(self.sizes[seq])

    def tokens(self, start: int, stop: int) -> np.ndarray:
        """Ids at ``start`` to ``stop`` of the expanded sequence; only symbols that touch the range are expanded."""
        if stop <= start:
            return np.zeros(0, np.uint16)
        a, b = np.searchsorted(self.ends, [start, stop - 1], "right")
        part = self.seq[a : b + 1]
        n = self.sizes[part]
        ends = np.cumsum(n)
        out = self.table[np.arange(ends[-1]) + np.repeat(self.starts[part] - (ends - n), n)]
        skip = start - (int(self.ends[a]) - int(self.sizes[self.seq[a]]))
        return out[skip : skip + stop - start]


def pack_file(docs: list[int | None], sizes: np.ndarray, ids: np.ndarray, base: int) -> bytes:
    seq, rules = compress(ids, base)
    numbers = np.array([x or 0 for x in docs], "<i8").tobytes() + np.array([x is not None for x in docs], "u1").tobytes()
    body = b"".join([numbers, sizes.astype("<u4").tobytes(), rules.tobytes(), lengths(rules, base).astype("<u4").tobytes(), seq.tobytes()])
    return _HEAD.pack(MAGIC, base, len(docs), len(rules), len(seq), zlib.crc32(body)) + body


def open_file(data: bytes) -> tuple[list[int | None], np.ndarray, Grammar]:
    magic, base, n, r, s, crc = _HEAD.unpack_from(data)
    if magic != MAGIC or zlib.crc32(memoryview(data)[_HEAD.size :]) != crc:
        raise ValueError("not a whole token file")
    at = _HEAD.size

    def take(kind: str, count: int) -> np.ndarray:
        nonlocal at
        out = np.frombuffer(data, kind, count, at)
        at += out.nbytes
        return out

    numbers, there, sizes = take("<i8", n).tolist(), take("u1", n).tolist(), take("<u4", n)
    rules, spans, seq = take("<u2", 2 * r).reshape(r, 2), take("<u4", r), take("<u2", s)
    return [x if ok else None for x, ok in zip(numbers, there, strict=True)], sizes, Grammar(rules, spans, seq, base)


def _writer(path: str, root: str, end: int, shard: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, part, number = Library(path), TaskContext.get().partitionId(), 0
        base = coder.v.size
        last = np.array([end], coder.v.kind).tobytes()
        docs, held, total = [], [], 0

        def flush():
            nonlocal docs, held, total, number
            sizes = np.fromiter(map(len, held), np.int64, len(held)) // np.dtype(coder.v.kind).itemsize
            data = pack_file(docs, sizes, np.frombuffer(b"".join(held), coder.v.kind), base)
            out = NewFile(root, ".repair")
            out.write(data)
            out.close()
            row = (part, number, out.name, len(docs), int(sizes.sum()), len(data))
            docs, held, total, number = [], [], 0, number + 1
            return pa.RecordBatch.from_arrays([pa.array([x]) for x in row], [f.split()[0] for f in MANIFEST.split(", ")])

        for b in batches:
            for start, texts in slices(b.column(1), min(4 << 20, 2 * shard)):
                docs += b.column(0).slice(start, len(texts)).to_pylist()
                held += (new := [x + last for x in coder.encode_batch(texts)])
                total += sum(map(len, new))
                if total >= shard * np.dtype(coder.v.kind).itemsize:
                    yield flush()
        if docs:
            yield flush()

    return run


def _reader(root: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, folder = open_fs(root)
        for b in batches:
            for name, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                with system.open_input_file(f"{folder}/{name}") as f:
                    docs, sizes, grammar = open_file(f.readall())
                ends = np.cumsum(sizes.astype(np.int64))
                starts = ends - sizes
                crcs = []
                for lo in range(0, len(docs), 512):
                    hi = min(lo + 512, len(docs))
                    ids = grammar.tokens(int(starts[lo]), int(ends[hi - 1])).astype("<u4")
                    crcs += [zlib.crc32(ids[s:e]) for s, e in zip((starts[lo:hi] - starts[lo]).tolist(), (ends[lo:hi] - starts[lo]).tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(starts + base), pa.array(sizes.astype(np.int64)), pa.array(crcs, pa.int64())],
                                                 [f.split()[0] for f in ROWS.split(", ")])

    return run


def write(spark: SparkSession, docs: DataFrame, path: str, end: int = END, shard: int = SHARD) -> tuple[DataFrame, str]:
    """Token files of about ``shard`` tokens in ascending order of id (rows that share an id: of text); manifest, folder."""
    scratch = Scratch(spark, "tokens")
    ordered = (docs.select(F.col("doc_id").cast("long"), text_of().alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text"))
    manifest = scratch.save(ordered.mapInArrow(_writer(path, scratch.path("files"), end, shard), MANIFEST), "manifest")
    return manifest, scratch.path("files")


def read(manifest: DataFrame, root: str) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32)`` from the files. Offsets: running sums over partitions, then over files."""
    parts = prefix_sums(manifest.groupBy("part").agg(F.sum("tokens").alias("total")), "part", "total", "base").select("part", "base")
    earlier = Window.partitionBy("part").orderBy("number").rowsBetween(Window.unboundedPreceding, -1)
    placed = manifest.withColumn("inside", F.coalesce(F.sum("tokens").over(earlier), F.lit(0))).join(F.broadcast(parts), "part")
    files = parts_for(manifest.sparkSession, manifest.count(), PER_TASK)
    return placed.select("file", (F.col("base") + F.col("inside")).alias("base")).repartition(files, "file").mapInArrow(_reader(root), ROWS)


def sizes(manifest: DataFrame, width: int = 2) -> DataFrame:
    """Documents, tokens, bytes of their ids at ``width`` bytes each, and bytes of the files that hold them."""
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    return manifest.agg(total("docs").alias("docs"), total("tokens").alias("tokens"), (width * total("tokens")).alias("raw_bytes"), total("bytes").alias("stored_bytes"))


def stored(spark: SparkSession, docs: DataFrame, path: str) -> DataFrame:
    """One row per row of ``docs``, all from the files. Null and empty texts are their end id alone; rows without an id
    come first; an empty table writes no file. Extra columns are ignored."""
    return read(*write(spark, docs, path))
