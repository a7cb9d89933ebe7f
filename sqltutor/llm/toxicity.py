"""Toxicity by gradient-boosted trees over dense features, with isotonic calibration.

Features per text: densities and counts of an insult lexicon and of words learned from labels, second-person words near
insults, capitals, punctuation and obfuscation rates, length. Rows with labels fall in four folds by a checksum of their
id: words are learned on fold 0, trees on fold 1, calibration on fold 3; fold 2 is held out. Each fit sees at most
``ROWS`` labelled rows, those with the smallest hashes; this bound is the fit's only sampling. Everything is scored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import packed_rows, text_of, unpacked

HELD_OUT, THRESHOLD, ROWS, LEARNED = 2, 0.3, 12_000, 100
#: Fixed seed lexicon of insults, lower case, in the languages of the corpus.
INSULTS = frozenset(
    "idiot idiots moron morons stupid dumb loser losers scum trash garbage pathetic worthless disgusting clown fool imbecile jerk bastard "
    "freak creep filth vermin ugly hate bitch whore slut asshole shit crap dickhead wanker "
    "dumm dummkopf arschloch abschaum versager widerlich wertlos "
    "idiota imbécil estúpido estúpida basura escoria inútil asqueroso asquerosa payaso perdedor "
    "imbécile stupide crétin connard salaud ordure déchet minable dégoûtant débile".split())
#: Fixed second-person words of the same languages.
YOU = frozenset("you your yours yourself u ur du dich dir dein deine ihr euch tú tu ti usted ustedes vosotros toi te vous votre vos".split())
#: Fixed look-alikes that hide letters.
LOOKS = str.maketrans("013457@$!€", "oieastasie")
_EDGE = ".,;:!?\"'()[]{}<>«»„“”*_#~|&%-…"
_HIDDEN = re.compile(r"[^\W\d_](?:[.*_\-]|[0134578@$!])[^\W_]")
NAMES = ("seed", "seed_rate", "learned", "learned_rate", "near_you", "hidden", "capitals", "marks", "loud", "odd", "words", "mean_len")


def features(text: str, learned: frozenset[str]) -> list[float]:
    words = text.split()
    n = len(words) or 1
    bare = [w.strip(_EDGE) for w in text.lower().split()]
    hits = [i for i, w in enumerate(bare) if w in INSULTS]
    hidden = 0
    for i, w in enumerate(bare):
        if not w.isalpha() and 2 < len(w) < 24 and w not in INSULTS and _HIDDEN.search(w):
            plain = w.translate(LOOKS)
            if plain in INSULTS or plain.replace(".", "").replace("*", "").replace("-", "").replace("_", "") in INSULTS:
                hidden += 1
                hits.append(i)
    own = sum(map(learned.__contains__, bare))
    near = sum(1 for i in hits if not YOU.isdisjoint(bare[max(0, i - 5) : i + 6]))
    size = len(text) or 1
    marks = text.count("!") + text.count("?")
    return [len(hits), 1000 * len(hits) / n, own, 1000 * own / n, near, hidden, sum(map(str.isupper, words)) / n, marks / size, text.count("!!") / n,
            sum(map(text.count, "#*$%&|<>@")) / size, math.log1p(len(words)), size / n]


@dataclass(frozen=True)
class Tree:
    """A complete binary tree in level order: feature and threshold per inner node, value per leaf."""

    feature: np.ndarray
    threshold: np.ndarray
    value: np.ndarray

    def predict(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        while (inner := at < len(self.feature)).any():
            rows, node = np.flatnonzero(inner), at[inner]
            at[rows] = 2 * node + 1 + (x[rows, self.feature[node]] > self.threshold[node])
        return self.value[at - len(self.feature)]


@dataclass(frozen=True)
class Model:
    learned: frozenset[str]
    base: float
    trees: tuple[Tree, ...]
    edges: np.ndarray
    levels: np.ndarray

    def margin(self, x: np.ndarray) -> np.ndarray:
        return self.base + sum((t.predict(x) for t in self.trees), np.zeros(len(x)))

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.interp(self.margin(x), self.edges, self.levels)


def boosted(x: np.ndarray, y: np.ndarray, rounds: int = 40, depth: int = 3, rate: float = 0.2, bins: int = 32, least: float = 2.0) -> tuple[float, list[Tree]]:
    """Second-order boosting of the logistic loss on histograms of quantile bins."""
    base = float(np.log((y.sum() + 1) / (len(y) - y.sum() + 1)))
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, bins + 1)[1:-1], method="lower")) for c in x.T]
    binned = np.stack([np.searchsorted(c, v, "left") for c, v in zip(cuts, x.T, strict=True)], axis=1)
    margin, trees, inner = np.full(len(y), base), [], 2**depth - 1
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-margin))
        grad, hess = y - p, np.maximum(p * (1 - p), 1e-6)
        feature, threshold, node = np.zeros(inner, np.int64), np.full(inner, np.inf), np.zeros(len(y), np.int64)
        for k in range(inner):
            rows = np.flatnonzero(node == k)
            g, h, best = grad[rows].sum(), hess[rows].sum(), (1e-6, 0, None)
            for f, cut in enumerate(cuts):
                if not len(cut) or not len(rows):
                    continue
                gl = np.cumsum(np.bincount(binned[rows, f], grad[rows], len(cut) + 1))[:-1]
                hl = np.cumsum(np.bincount(binned[rows, f], hess[rows], len(cut) + 1))[:-1]
                gain = gl**2 / (hl + 1) + (g - gl) ** 2 / (h - hl + 1) - g**2 / (h + 1)
                gain[(hl < least) | (h - hl < least)] = 0
                if gain.max() > best[0]:
                    best = (float(gain.max()), f, int(gain.argmax()))
            if best[2] is not None:
                feature[k], threshold[k] = best[1], cuts[best[1]][best[2]]
            node[rows] = 2 * k + 1 + (x[rows, feature[k]] > threshold[k])
        leaf = node - inner
        value = rate * np.bincount(leaf, grad, 2**depth) / (np.bincount(leaf, hess, 2**depth) + 1)
        trees.append(Tree(feature, threshold, value))
        margin = margin + value[leaf]
    return base, trees


def isotonic(margin: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pool-adjacent-violators fit of y on margin, with one pseudo-count at each end; points for interpolation."""
    order = np.argsort(margin, kind="stable")
    m = np.concatenate(([margin.min(initial=0) - 1], margin[order], [margin.max(initial=0) + 1]))
    v = np.concatenate(([0.0], y[order], [1.0]))
    blocks: list[list[float]] = []
    for a, b in zip(m.tolist(), v.tolist(), strict=True):
        blocks.append([b, 1, a, a])
        while len(blocks) > 1 and blocks[-2][0] / blocks[-2][1] >= blocks[-1][0] / blocks[-1][1]:
            s, n, _, hi = blocks.pop()
            blocks[-1] = [blocks[-1][0] + s, blocks[-1][1] + n, blocks[-1][2], hi]
    edges = np.array([e for s, n, lo, hi in blocks for e in (lo, hi)])
    levels = np.array([s / n for s, n, _, _ in blocks for _ in range(2)])
    first = np.concatenate(([True], np.diff(edges) > 0))
    return edges[first], np.clip(levels[first], 0, 1)


def fold(doc_id: str | Column = "doc_id") -> Column:
    col = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.pmod(F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary")), F.lit(4))


def _sample(labels: DataFrame, folds: list[int], rows: int) -> DataFrame:
    """Up to ``rows`` labelled ids of these folds, by hash order; an id with several labels is toxic if one says so."""
    one = (labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & fold().isin(folds))
           .groupBy("doc_id").agg(F.max("toxic").alias("toxic")))
    return one.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)


def _texts(docs: DataFrame, sample: DataFrame) -> DataFrame:
    """One text per sampled id, the smallest where rows share it, so that the bound on ids bounds rows as well."""
    return (docs.select("doc_id", text_of().alias("text")).join(F.broadcast(sample), "doc_id")
            .groupBy("doc_id").agg(F.min("text").alias("text"), F.first("toxic").alias("toxic")))


def learned_words(docs: DataFrame, sample: DataFrame) -> frozenset[str]:
    """At most ``LEARNED`` words that mark toxic texts of fold 0: in 3 % or more of them and 85 % or more toxic."""
    words = F.array_distinct(F.split(F.lower(text_of()), r"[\s\p{Punct}]+"))
    seen = _texts(docs, sample).select("toxic", words.alias("ws"))
    toxic = seen.agg(F.sum("toxic")).first()[0] or 0
    if toxic < 20:
        return frozenset()
    counts = (seen.select("toxic", F.explode("ws").alias("w")).where("w <> ''").groupBy("w")
              .agg(F.sum("toxic").alias("t"), F.count("*").alias("n")))
    best = counts.where((F.col("t") >= max(5, 0.03 * toxic)) & (F.col("t") >= 0.85 * F.col("n"))).orderBy(F.desc("t"), "w").limit(LEARNED)
    return frozenset(r["w"] for r in best.collect())


def _featured(docs: DataFrame, sample: DataFrame, learned: frozenset[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    names = [f"f{i}" for i in range(len(NAMES))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = np.array([features(t, learned) for t in b.column(2).to_pylist()], float).reshape(-1, len(NAMES))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *map(pa.array, rows.T)], ["k", "toxic", *names])

    seen = _texts(docs, sample).select(fold().cast("long").alias("k"), F.col("toxic").cast("double").alias("toxic"), "text")
    got = seen.mapInArrow(run, "k long, toxic double, " + ", ".join(f"{n} double" for n in names)).toArrow()
    return got["k"].to_numpy(), got["toxic"].to_numpy(), np.stack([got[n].to_numpy() for n in names], axis=1)


def fit(docs: DataFrame, labels: DataFrame, rows: int = ROWS) -> Model:
    """A model from at most ``rows`` labelled ids for words and ``2 * rows`` for trees and calibration, one row each.

    No labels at all: the seed lexicon's rate alone decides, through the pseudo-counts of the calibration. Labels without
    a value or an id, and of documents that are not there, are left out; so are null ids. Empty table: as no labels."""
    learned = learned_words(docs, _sample(labels, [0], rows))
    k, y, x = _featured(docs, _sample(labels, [1, 3], 2 * rows), learned)
    base, trees = boosted(x[k == 1], y[k == 1]) if (k == 1).sum() >= 50 else (0.0, [])
    model = Model(learned, base, tuple(trees), np.array([-1.0, 1.0]), np.array([0.0, 1.0]))
    if not trees:
        step = Tree(np.array([1]), np.array([2.0]), np.array([-1.0, 1.0]))
        return Model(learned, 0.0, (step,), np.array([-1.0, 1.0]), np.array([0.05, 0.9]))
    return Model(learned, base, model.trees, *isotonic(model.margin(x[k == 3]), y[k == 3]))


def score_of(text: Column, model: Model) -> Column:
    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            x = np.array([features(t or "", model.learned) for t in texts.to_pylist()], float).reshape(-1, len(NAMES))
            yield pa.array(model.score(x))

    return F.arrow_udf(run, T.DoubleType())(text)


def scored(docs: DataFrame, model: Model) -> DataFrame:
    """``(doc_id, held_out, score, predicted)`` for each row of ``docs``. Null and empty texts score as texts without
    words. Equal texts score alike; labels, language, source and id are no inputs. Empty table: no rows."""
    rows = docs.select("doc_id", (fold() == HELD_OUT).alias("held_out"), score_of(text_of(), model).alias("score"))
    return rows.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def clean(docs: DataFrame, model: Model) -> DataFrame:
    """The documents that are not toxic, with the columns they had. Null and empty texts score as texts without words;
    equal texts stay or go together, repeated rows and null ids too. Empty table: no rows."""
    rows = docs.select(packed_rows(docs).alias("row"), score_of(text_of(), model).alias("score"))
    return unpacked(rows.where(F.col("score") < THRESHOLD), "row", docs.columns)
