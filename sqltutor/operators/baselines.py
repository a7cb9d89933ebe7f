"""Simple stand-ins for the ideas of rival methods; no model is behind any of them."""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.sqltext import decompose
from ..store import Shelf
from . import mutate
from .suites import BY_ID

SYNONYMS = {"cost": "price", "costs": "price", "bought": "purchase", "sell": "sold", "biggest": "largest", "mean": "average"}
BLOCK, CHUNK, PROBES = 8_192, 512, 48


def nearest_examples(queries: DataFrame, pool: DataFrame, k: int = 3) -> DataFrame:
    """``k`` nearest vectors of a pool for each query by cosine, exact at any size: tasks read the written pool block by
    block and keep the best ``k`` of each query. Vectors have unit length, so a dot product is the cosine."""
    return _searched(queries, pool.select("vec_id", "embedding", F.lit(0).alias("cell")), k, None, 1)


def nearest_by_planes(queries: DataFrame, pool: DataFrame, k: int, bits: int, seed: int, probes: int = PROBES) -> DataFrame:
    """Random hyperplanes cut space into cells. A query looks into the ``probes`` cells that it is nearest to (by the sum
    of its distances from the planes in between). Recall is below 1: a test holds it to 0.9 at the default, which looks
    at three quarters of the cells of six planes; ``2 ** bits`` probes are exact."""
    planes = np.random.default_rng(seed).normal(size=(bits, len((pool.select("embedding").first() or [[]])[0])))

    def cells(batches):
        for b in batches:
            yield b.assign(cell=_cells(_matrix(b["embedding"]), planes)) if len(b) else b.assign(cell=0)

    located = pool.select("vec_id", "embedding").mapInPandas(cells, "vec_id long, embedding array<float>, cell int")
    return _searched(queries, located, k, planes, probes)


def nearest_by_text(df: DataFrame, text: str = "question", k: int = 3, size: int = 256) -> DataFrame:
    """``(question_id, place, neighbour, cosine)``: for each question the ``k`` others whose ``text`` (question or
    skeleton) is most alike, exact by cosine of hashed counts of words and word pairs."""
    def vectors(batches):
        for b in batches:
            out = np.zeros((len(b), size), np.float32)
            for row, x in zip(out, b["text"], strict=True):
                words = re.findall(r"\w+", (x or "").lower())
                np.add.at(row, [zlib.crc32(w.encode()) % size for w in words + [" ".join(p) for p in zip(words, words[1:])]], 1)
            yield pd.DataFrame({"vec_id": b["vec_id"], "embedding": list(out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9))})

    named = df.select(F.col("question_id").alias("vec_id"), F.col(text).alias("text"))
    located = Shelf(df.sparkSession, "texts").put(named.mapInPandas(vectors, "vec_id long, embedding array<float>"), "vectors")
    return nearest_examples(located, located, k).withColumnRenamed("vec_id", "question_id")


def _matrix(vectors) -> np.ndarray:
    return np.array(vectors.tolist(), np.float64)


def _cells(vectors: np.ndarray, planes: np.ndarray) -> np.ndarray:
    return ((vectors @ planes.T > 0) * (1 << np.arange(len(planes)))).sum(axis=1)


def _probed(vectors: np.ndarray, planes: np.ndarray, probes: int) -> np.ndarray:
    """Which cells each vector looks into: own bits first, then those whose differing planes are nearest in sum."""
    bit = np.arange(1 << len(planes))[:, None] >> np.arange(len(planes)) & 1
    margins = np.abs(vectors @ planes.T)
    cost = margins @ bit.T
    order = np.argsort(cost, axis=1, kind="stable")[:, :probes] ^ _cells(vectors, planes)[:, None]
    out = np.zeros(cost.shape, bool)
    np.put_along_axis(out, order, True, axis=1)
    return out


def _searched(queries: DataFrame, pool: DataFrame, k: int, planes: np.ndarray | None, probes: int) -> DataFrame:
    scratch = Shelf(queries.sparkSession, "pool")
    scratch.put(pool.sortWithinPartitions("cell"), "blocks")
    root = scratch.path("blocks")

    def blocks():
        system, folder = fs.FileSystem.from_uri(root)
        for f in sorted(x.path for x in system.get_file_info(fs.FileSelector(folder)) if x.path.endswith(".parquet")):
            with system.open_input_file(f) as src:
                for batch in pq.ParquetFile(src).iter_batches(BLOCK, columns=["vec_id", "embedding", "cell"]):
                    cell, ids = batch.column("cell").to_numpy(), batch.column("vec_id").to_numpy()
                    mat = batch.column("embedding").flatten().to_numpy().astype(np.float64).reshape(len(ids), -1)
                    for c in np.unique(cell):
                        yield int(c), ids[cell == c], mat[cell == c]

    def run(batches):
        for b in batches:
            if not len(b):
                continue
            vectors, own = _matrix(b["embedding"]), b["vec_id"].to_numpy()
            wanted = np.ones((len(b), 1), bool) if planes is None else _probed(vectors, planes, probes)
            row, ids, cos = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
            floor = np.full(len(b), -np.inf)
            for c, names, mat in blocks():
                at = np.flatnonzero(wanted[:, c])
                found = [(row, ids, cos)]
                for part in (at[i : i + CHUNK] for i in range(0, len(at), CHUNK)):
                    s = np.round(vectors[part] @ mat.T, 6)
                    s[own[part][:, None] == names] = -np.inf
                    least = np.maximum(floor[part], np.partition(s, len(names) - k, axis=1)[:, len(names) - k] if len(names) > k else -np.inf)
                    r, j = np.nonzero((s >= least[:, None]) & (s > -np.inf))
                    found.append((part[r], names[j], s[r, j]))
                row, ids, cos = (np.concatenate(x) for x in zip(*found, strict=True))
                order = np.lexsort((ids, -cos, row))
                row, ids, cos = row[order], ids[order], cos[order]
                place = np.arange(len(row)) - np.searchsorted(row, row)
                floor[row[place == k - 1]] = cos[place == k - 1]
                row, ids, cos = row[place < k], ids[place < k], cos[place < k]
            yield pd.DataFrame({"vec_id": own[row], "place": np.arange(len(row)) - np.searchsorted(row, row) + 1, "neighbour": ids, "cosine": cos})

    return queries.select("vec_id", "embedding").mapInPandas(run, "vec_id long, place long, neighbour long, cosine double")


def skeleton_then_fill(neighbours: DataFrame, golds: DataFrame) -> DataFrame:
    """Most frequent skeleton among a question's neighbours, filled with the text of the nearest one that has it."""
    known = golds.select(F.col("question_id").alias("neighbour"), "skeleton", "gold_sql")
    votes = neighbours.select("question_id", "place", "neighbour").join(known, "neighbour")
    counts = votes.groupBy("question_id", "skeleton").agg(F.count("*").alias("n"), F.min(F.struct("place", "gold_sql")).alias("best"))
    first = F.row_number().over(Window.partitionBy("question_id").orderBy(F.desc("n"), F.col("best.place")))
    return counts.withColumn("k", first).where("k = 1").select("question_id", "skeleton", F.col("best.gold_sql").alias("sql"))


def best_of_n(df: DataFrame, scorer: str = "total", by: str = "question_id") -> DataFrame:
    """The candidate that a scorer ranks first, ties by slot."""
    w = Window.partitionBy(by).orderBy(F.desc(scorer), "slot")
    return df.withColumn("__k", F.row_number().over(w)).where("__k = 1").drop("__k")


def majority_by_result(df: DataFrame, result: str = "fp", by: str = "question_id") -> DataFrame:
    """A candidate of the largest group with one result; failed runs (null) have no vote."""
    votes = df.where(F.col(result).isNotNull()).groupBy(by, result).agg(F.count("*").alias("votes"), F.min("slot").alias("slot"))
    w = Window.partitionBy(by).orderBy(F.desc("votes"), "slot")
    return votes.withColumn("__k", F.row_number().over(w)).where("__k = 1").select(by, "slot", result, "votes")


def route(df: DataFrame, hard: list[str], weak: str, strong: str) -> DataFrame:
    """Rows of the strong arm for hard tiers and of the weak arm for the rest, as one arm ``router``."""
    return df.where(F.when(F.col("tier").isin(hard), F.col("arm") == strong).otherwise(F.col("arm") == weak)).withColumn("arm", F.lit("router"))


def normalise_question(questions: DataFrame, text: str = "question", synonyms: dict[str, str] = SYNONYMS) -> DataFrame:
    """Lower case and one word for several that mean the same, before translation."""
    table = F.create_map(*[F.lit(x) for kv in synonyms.items() for x in kv])
    return questions.withColumn(text, F.array_join(F.transform(F.split(F.lower(text), " "), lambda w: F.coalesce(table[w], w)), " "))


def link_prune(grounded: DataFrame, k: int) -> DataFrame:
    """Schema cut to the ``k`` best grounded elements of each question."""
    return grounded.where(F.col("place") <= k).groupBy("question_id").agg(F.sort_array(F.collect_set("element")).alias("schema"))


def result_overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Shared rows over all rows of two results as bags: partial credit for partial results."""
    cols = [F.col(c) for c in b.columns]
    b = b.select(*[c.alias(n) for c, n in zip(cols, a.columns, strict=True)])
    counts = a.withColumn("__a", F.lit(1)).withColumn("__b", F.lit(0)).unionByName(b.withColumn("__a", F.lit(0)).withColumn("__b", F.lit(1)))
    per = counts.groupBy(*a.columns).agg(F.sum("__a").alias("na"), F.sum("__b").alias("nb"))
    return per.agg((F.sum(F.least("na", "nb")) / F.sum(F.greatest("na", "nb"))).alias("overlap"))


def preferred(strong: DataFrame, weak: DataFrame, right: DataFrame) -> DataFrame:
    """``(question_id, family, chosen, rejected)``: the first answer of a strong generator that is right and the first of a
    weak one that is wrong, for questions that have both."""
    def first(df: DataFrame, good: bool, name: str) -> DataFrame:
        rows = df.join(right.select("question_id", "kind", F.coalesce("correct", F.lit(False)).alias("correct")), ["question_id", "kind"])
        return rows.where(F.col("correct") == good).groupBy("question_id", "family").agg(F.min_by("kind", "slot").alias(name))

    return first(strong, True, "chosen").join(first(weak, False, "rejected"), ["question_id", "family"])


#: Order in which a query's clauses are decided.
LEVELS = ("from", "join", "select", "where", "group", "having", "order", "limit")


def clause_paths(spark: SparkSession, kinds: tuple[str, ...] = mutate.KINDS) -> DataFrame:
    """``(family, kind, path)``: what each family's template of each kind has in each clause, in the order of ``LEVELS``, with
    set operations and named queries first; the last step is the kind, which tells answers with the same SQL apart."""
    def path(sql: str, kind: str) -> list[str]:
        known = decompose(sql)
        return [repr([known.get(c) for c in ("with", "set", "distinct")]), *(repr(known.get(c)) for c in LEVELS), kind]

    rows = [(fid, k, path(mutate.edit(f.gold, k), k)) for fid, f in BY_ID.items() for k in kinds]
    return spark.createDataFrame(rows, "family string, kind string, path array<string>")


def searched(kinds: list[str], paths: list[list[str]], rewards: list[float], iterations: int, c: float) -> tuple[str, float, int]:
    """Best kind, its reward and how many were tried, by upper-confidence search down a tree whose levels are clauses."""
    tries: dict[tuple, int] = {}
    sums: dict[tuple, float] = {}
    seen: dict[int, float] = {}
    for _ in range(iterations):
        at, here = (), range(len(kinds))
        while len(here) > 1 or len(at) < len(paths[here[0]]):
            options = sorted({paths[i][len(at)] for i in here})
            if len(options) > 1:
                total = sum(tries.get((*at, o), 0) for o in options) or 1
                worth = lambda o: math.inf if not tries.get((*at, o)) else sums[(*at, o)] / tries[(*at, o)] + c * math.sqrt(math.log(total) / tries[(*at, o)])  # noqa: B023, E731
                at = (*at, max(options, key=worth))
            else:
                at = (*at, options[0])
            here = [i for i in here if paths[i][len(at) - 1] == at[-1]]
        i = here[0]
        seen[i] = rewards[i]
        for k in range(1, len(at) + 1):
            tries[at[:k]] = tries.get(at[:k], 0) + 1
            sums[at[:k]] = sums.get(at[:k], 0.0) + rewards[i]
    best = max(sorted(seen), key=lambda i: (seen[i], kinds[i]))
    return kinds[best], seen[best], len(seen)


def tree_search(cube: DataFrame, paths: DataFrame, iterations: int = 24, c: float = 1.0) -> DataFrame:
    """``(question_id, kind, total, visited)``: clause-by-clause search over each question's candidates. A node is a choice of
    the first clauses, a leaf an answer, its reward the cube's; ``paths`` (families times kinds rows) say which clauses an
    answer has. A question's candidates are as many as kinds; questions go through Arrow in batches."""
    kind = pa.struct([("kind", pa.string()), ("total", pa.float64()), ("visited", pa.int64())])

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for rows in batches:
            out = []
            for one in rows.to_pylist():
                one = sorted(one, key=lambda x: x["kind"])
                out.append(dict(zip(("kind", "total", "visited"), searched([x["kind"] for x in one], [x["path"] for x in one], [x["total"] for x in one], iterations, c), strict=True)))
            yield pa.array(out, kind)

    listed = (cube.join(F.broadcast(paths), ["family", "kind"]).where("total IS NOT NULL").groupBy("question_id")
              .agg(F.collect_list(F.struct("kind", "path", F.col("total").cast("double").alias("total"))).alias("x")))
    return listed.select("question_id", F.arrow_udf(run, "struct<kind:string, total:double, visited:bigint>")("x").alias("b")).select("question_id", "b.*")
