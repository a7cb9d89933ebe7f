"""Byte-level BPE: encoding by speculation and verification, and decoding.

Text is cut at single spaces between words; the pieces are cut on by the tokenizer's pattern. For each new piece a
greedy longest match over the vocabulary proposes tokens. A proposal is the tokenizer's own answer exactly if every
adjacent pair is compatible, that is, if encoding the two tokens' joined bytes gives these two tokens. Pairs of many
pieces are tested together in NumPy by undoing merges on both sides of the cut. Pieces with a failing pair are merged
exactly, pair by pair in rank order.

``Library`` gives the same ids from public engines; packing and storage use it, and tests hold one against the other.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import chain, pairwise

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_of

#: White space as Unicode defines it, spelled out because engines differ on U+001C to U+001F.
_WS = r"\t-\r\x20\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Fixed pattern of the tokenizer's pre-tokenizer, with that class.
PATTERN = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_WS}\p{{L}}\p{{N}}]+|[{_WS}]+(?![^{_WS}])|[{_WS}]+")
_ODD_ASCII = "\t\r\x0b\x0c\x1c\x1d\x1e\x1f"
_ODD_WIDE = regex.compile(r"[\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
CACHE, LARGE_CACHE, FAR = 350_000, 900_000, 1 << 40


def byte_letters() -> dict[str, int]:
    """The vocabulary file's letter for each byte: printable ones stand for themselves, the rest follow from U+0100."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Vocabulary:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        model, letters = data["model"], byte_letters()
        self.special = {t["content"]: t["id"] for t in data.get("added_tokens", [])}
        self.by_bytes = {bytes(letters[c] for c in piece): i for piece, i in model["vocab"].items() if piece not in self.special}
        size = max([*self.by_bytes.values(), *self.special.values()]) + 1
        self.pieces = [b""] * size
        for piece, i in self.by_bytes.items():
            self.pieces[i] = piece
        for piece, i in self.special.items():
            self.pieces[i] = piece.encode()
        self.kind = "<u2" if size <= 1 << 16 else "<u4"
        self.reach: dict[bytes, int] = {}
        self.rests: dict[bytes, list[int]] = {}
        for piece in self.by_bytes:
            self.reach[piece[:3]] = max(self.reach.get(piece[:3], 0), len(piece))
        raw = {c: bytes([b]) for c, b in letters.items()}
        join = lambda s: b"".join(map(raw.__getitem__, s))
        self.left, self.right = np.arange(size), np.arange(size)
        self.rank = np.full(size, -1, np.int64)
        ranks: dict[tuple[int, int], int] = {}
        self.product = []
        for at, pair in enumerate(model["merges"]):
            a, b = (self.by_bytes[join(x)] for x in (pair if isinstance(pair, list) else pair.split(" ")))
            whole = self.by_bytes[self.pieces[a] + self.pieces[b]]
            ranks[a, b] = at
            self.product.append(whole)
            if self.rank[whole] < 0:
                self.left[whole], self.right[whole], self.rank[whole] = a, b, at
        keys = np.array([a * size + b for a, b in ranks], np.int64)
        order = np.argsort(keys)
        self.pair_keys, self.pair_ranks = keys[order], np.array(list(ranks.values()), np.int64)[order]
        self.rank_of, self.single = ranks.get, [self.by_bytes[bytes([b])] for b in range(256)]
        self.size = size

    def exact(self, word: bytes) -> list[int]:
        """Merges the pair of the lowest rank, leftmost first, until no pair merges."""
        ids = [self.single[b] for b in word]
        ranks = [self.rank_of(p, FAR) for p in pairwise(ids)]
        while ranks and (best := min(ranks)) < FAR:
            i = ranks.index(best)
            ids[i] = self.product[best]
            del ids[i + 1], ranks[i]
            if i < len(ranks):
                ranks[i] = self.rank_of((ids[i], ids[i + 1]), FAR)
            if i:
                ranks[i - 1] = self.rank_of((ids[i - 1], ids[i]), FAR)
        return ids

    def greedy(self, word: bytes) -> list[int]:
        """Longest match from the left. What follows a match depends on the rest alone, so short rests are remembered."""
        out, at, n, get, reach, rests = [], 0, len(word), self.by_bytes.get, self.reach, self.rests
        while at < n:
            if at and (x := rests.get(word[at:])) is not None:
                out += x
                break
            end = min(n, at + reach.get(word[at : at + 3], 2))
            while (i := get(word[at:end])) is None:
                end -= 1
            out.append(i)
            at = end
            if len(out) == 1:
                first = end
        if len(out) > 1 and n - first <= 12:
            if len(rests) > CACHE // 4:
                rests.clear()
            rests[word[first:]] = out[1:]
        return out

    def compatible(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """For each cut between a token of ``a`` and one of ``b``: would BPE keep it?

        Undo merges of the two sides from the latest to the earliest. Between two undone merges the tokens that touch
        the cut are those that existed then; if they have a merge of a lower rank than the one undone last, BPE would
        have crossed the cut. Equal ranks on both sides: the left one came first, so a crossing merge must beat it.
        """
        ok, live = np.ones(len(a), bool), np.arange(len(a))
        x, y = a.astype(np.int64), b.astype(np.int64)
        limit, strict = np.full(len(a), np.iinfo(np.int64).max), np.ones(len(a), bool)
        while len(live):
            key = x * self.size + y
            at = np.minimum(np.searchsorted(self.pair_keys, key), len(self.pair_keys) - 1)
            cross = np.where(self.pair_keys[at] == key, self.pair_ranks[at], np.iinfo(np.int64).max)
            bad = (cross < limit) | (~strict & (cross == limit) & (cross < np.iinfo(np.int64).max))
            ok[live[bad]] = False
            rx, ry = self.rank[x], self.rank[y]
            go = ~bad & ((rx >= 0) | (ry >= 0))
            live, x, y, rx, ry = live[go], x[go], y[go], rx[go], ry[go]
            from_left = rx > ry
            limit, strict = np.where(from_left, rx, ry), from_left
            x, y = np.where(from_left, self.right[x], x), np.where(from_left, y, self.left[y])
        return ok

    def speculate(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word as packed bytes: greedy proposals, one vectorised test, exact merging where it fails."""
        guesses = [self.greedy(w) for w in words]
        sizes = np.fromiter(map(len, guesses), np.int64, len(words))
        flat = np.fromiter((i for g in guesses for i in g), np.int64, int(sizes.sum()))
        owner = np.repeat(np.arange(len(words)), sizes)
        cut = np.flatnonzero(owner[1:] == owner[:-1])
        pairs, back = np.unique(flat[cut] * self.size + flat[cut + 1], return_inverse=True)
        good = self.compatible(pairs // self.size, pairs % self.size)[back]
        for w in np.unique(owner[cut[~good]]).tolist():
            guesses[w] = self.exact(words[w])
        ends = np.cumsum(np.fromiter(map(len, guesses), np.int64, len(words))) * np.dtype(self.kind).itemsize
        packed = np.fromiter((i for g in guesses for i in g), self.kind).tobytes()
        return [packed[s:e] for s, e in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)] if words else []


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def separable(text: str) -> bool:
    """May the text be cut at each space? Yes if no space touches other white space: then a space opens a piece and
    nothing before it depends on what follows."""
    if "  " in text or " \n" in text or "\n " in text or any(c in text for c in _ODD_ASCII):
        return False
    return text.isascii() or not _ODD_WIDE.search(text)


class Memory:
    """Packed ids of pieces met before, in two generations of ``limit`` each, so that frequent pieces stay."""

    def __init__(self, limit: int = CACHE):
        self.limit, self.known, self.old = limit, {}, {}

    def missing(self, pieces: set[str]) -> list[str]:
        if len(self.known) > self.limit:
            self.known, self.old = {}, self.known
        known, old, out = self.known, self.old, []
        for p in pieces:
            if p not in known:
                if (x := old.get(p)) is not None:
                    known[p] = x
                else:
                    out.append(p)
        return out


class Speculative:
    """Texts -> packed ids. Pieces keep no leading space in memory; the space is part of what they stand for."""

    def __init__(self, path: str, limit: int = LARGE_CACHE):
        self.v, self.memory = vocabulary(path), Memory(limit)
        self.split = regex.compile("|".join(map(regex.escape, self.v.special))) if self.v.special else None

    def learn(self, pieces: list[str]) -> None:
        parts = [[(" " + p).encode()] if p.isalpha() else [w.encode() for w in PATTERN.findall(" " + p)] for p in pieces]
        words = list({w for ws in parts for w in ws})
        coded = dict(zip(words, self.v.speculate(words), strict=True))
        self.memory.known.update(zip(pieces, (coded[ws[0]] if len(ws) == 1 else b"".join([coded[w] for w in ws]) for ws in parts), strict=True))

    def whole(self, text: str) -> bytes:
        out, at = [], 0
        for m in [*(self.split.finditer(text) if self.split else ()), None]:
            words = [w.encode() for w in PATTERN.findall(text[at : m.start() if m else len(text)])]
            out += self.v.speculate(words)
            if m:
                out.append(np.array([self.v.special[m.group()]], self.v.kind).tobytes())
                at = m.end()
        return b"".join(out)

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        cut = [t.split(" ") if separable(t) and not any(s in t for s in self.v.special) else None for t in texts]
        self.learn(self.memory.missing(set(chain.from_iterable(c[1:] for c in cut if c))))
        known, out = self.memory.known, []
        for t, c in zip(texts, cut, strict=True):
            out.append(self.whole(t) if c is None else self.whole(c[0]) + b"".join([known[x] for x in c[1:]]))
        return out


@lru_cache(maxsize=1)
def speculative(path: str) -> Speculative:
    """One per worker process, so that its memory serves all tasks that the worker runs."""
    return Speculative(path)


def decode(v: Vocabulary, packed: bytes) -> str:
    """Ids -> text; bytes that are no UTF-8 become U+FFFD, special tokens their names."""
    return b"".join(map(v.pieces.__getitem__, np.frombuffer(packed, v.kind).tolist())).decode("utf-8", "replace")


def slices(texts: pa.Array, limit: int = 4 << 20) -> Iterator[tuple[int, list[str]]]:
    """A text column in runs of about ``limit`` characters: ``(first row, texts)``; nulls are empty."""
    start, held, run = 0, 0, []
    for i, t in enumerate(texts):
        s = t.as_py() or ""
        run.append(s)
        held += len(s)
        if held >= limit:
            yield start, run
            start, held, run = i + 1, 0, []
    if run:
        yield start, run


CODED = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def _round_trip(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = speculative(path)
        for b in batches:
            for start, texts in slices(b.column(1)):
                rows = [np.frombuffer(x, coder.v.kind) for x in coder.encode_batch(texts)]
                ids = [hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in rows]
                back = [hashlib.sha256(decode(coder.v, x.tobytes()).encode()).hexdigest() for x in rows]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(start, len(texts)), pa.array([len(x) for x in rows], pa.int64()), pa.array(ids), pa.array(back)],
                    [f.split()[0] for f in CODED.split(", ")])

    return run


def encoded(docs: DataFrame, path: str) -> DataFrame:
    """``(doc_id, ids binary)``: packed little-endian ids, two bytes each where the vocabulary allows."""
    def run(batches):
        coder = Speculative(path)
        for b in batches:
            for start, texts in slices(b.column(1)):
                yield pa.RecordBatch.from_arrays([b.column(0).slice(start, len(texts)), pa.array(coder.encode_batch(texts), pa.binary())], ["doc_id", "ids"])

    return docs.select(F.col("doc_id").cast("long"), text_of().alias("text")).mapInArrow(run, "doc_id long, ids binary")


def round_trip(docs: DataFrame, path: str) -> DataFrame:
    """Digests of ids and of the text decoded from them, one row per row of ``docs``. Null and empty text: no ids.
    Repeated rows give repeated rows, an empty table none; other columns are ignored."""
    return docs.select(F.col("doc_id").cast("long"), text_of().alias("text")).mapInArrow(_round_trip(path), CODED)
