"""Nearest vectors by cosine: exactly, block by block, or by inverted lists whose recall is measured.

Null ids and vectors that are null, hold nulls or have no finite direction are left out. Vectors are of one
dimension, ids are unique. Equal cosines go to the smaller id.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ripplegraph.plans.scratch import Scratch, bounded_broadcast

#: Vectors that centres are fitted on, and those whose recall is measured against all rows: those with the smallest hashes.
FIT_ROWS = 65_536
MEASURED_ROWS = 200
_PAIRS = "src long, dst long, w double"


def unit_vectors(vecs: DataFrame, name: str = "vec_id", column: str = "embedding") -> DataFrame:
    """(id, v): vectors of length one."""
    v = F.col(column).cast("array<double>")
    norm = F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
    sized = vecs.select(F.col(name).cast("long").alias("id"), v.alias("v"), norm.alias("norm")).where("id is not null and norm > 0 and norm < double('infinity')")
    return sized.select("id", F.transform("v", lambda x: x / F.col("norm")).alias("v"))


def _matrix(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy())


def _top(ids: np.ndarray, x: np.ndarray, others: pd.DataFrame, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of x, row of others, cosine) of the k nearest of ``others``, which rise by id; none is its own neighbour."""
    cos = x @ _matrix(others["v"]).T
    cos[ids[:, None] == others["id"].to_numpy()[None, :]] = -2
    top = np.argsort(-cos, axis=1, kind="stable")[:, :k]
    rows = np.repeat(np.arange(len(x)), top.shape[1])
    near = cos[rows, top.ravel()]
    own = near > -2
    return rows[own], top.ravel()[own], near[own]


def _nearest_of_blocks(left: DataFrame, right: DataFrame, keys: list[str], k: int) -> DataFrame:
    """(src, dst, w): the k nearest over all groups of ``keys``, each of one block of either side."""

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if a.empty or b.empty:
            return pd.DataFrame({"src": [], "dst": [], "w": []})
        b = b.sort_values("id")
        row, at, w = _top(a["id"].to_numpy(), _matrix(a["v"]), b, k)
        return pd.DataFrame({"src": a["id"].to_numpy()[row], "dst": b["id"].to_numpy()[at], "w": w})

    pairs = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(near, _PAIRS)
    order = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return pairs.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).drop("place")


def exact_nearest(vecs: DataFrame, k: int = 10, block: int = 256) -> DataFrame:
    """(src, dst, w) of all ``vecs`` (id, v) against all, block by block: exact, and quadratic in their number."""
    parts = max(1, -(-vecs.count() // block))
    numbered = vecs.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    each = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    left = numbered.withColumn("other", each).select(F.col("part").alias("p"), F.col("other").alias("q"), "id", "v")
    right = numbered.withColumn("other", each).select(F.col("other").alias("p"), F.col("part").alias("q"), "id", "v")
    return _nearest_of_blocks(left, right, ["p", "q"], k)


def _searched(ids: np.ndarray, x: np.ndarray, others: np.ndarray, y: np.ndarray, k: int, rows: int = 1_024, span: int = 16_384) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As ``_top``, some rows and spans at a time: single precision finds candidates, with a margin above its error, and double precision decides."""
    margin = 4e-7 * max(x.shape[1], 16)
    own = np.minimum(np.searchsorted(others, ids), len(others) - 1)
    own = np.where(others[own] == ids, own, -1)
    y32, out = y.astype(np.float32), []
    for i in range(0, len(x), rows):
        part, mine = x[i : i + rows], own[i : i + rows]
        part32, least = part.astype(np.float32), np.full(len(part), -np.inf, dtype=np.float32)
        row, at, w = np.zeros(0, dtype=int), np.zeros(0, dtype=int), np.zeros(0)
        for j in range(0, len(y), span):
            cos = part32 @ y32[j : j + span].T
            here = np.flatnonzero((mine >= j) & (mine < j + span))
            cos[here, mine[here] - j] = -np.inf
            if j == 0 and cos.shape[1] > k:
                least = np.partition(cos, -k, axis=1)[:, -k]
            r, c = np.nonzero((cos >= (least - margin)[:, None]) & (cos > -np.inf))
            row, at, w = np.concatenate((row, r)), np.concatenate((at, c + j)), np.concatenate((w, np.einsum("ij,ij->i", part[r], y[c + j])))
            order = np.lexsort((at, -w, row))
            row, at, w = row[order], at[order], w[order]
            place = np.arange(len(row)) - np.searchsorted(row, row)
            last = place == k - 1
            least[row[last]] = w[last]
            row, at, w = row[place < k], at[place < k], w[place < k]
        out.append((row + i, at, w))
    return tuple(np.concatenate(column) for column in zip(*out, strict=True))


def _sound(part: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(ids, rows of length one) of the vectors that have a direction, in the order of their ids."""
    part = part.sort_values("id")
    x = _matrix(part["v"]).astype(float)
    norm = np.sqrt((x * x).sum(axis=1))
    own = (norm > 0) & (norm < np.inf)
    return part["id"].to_numpy()[own], x[own] / norm[own, None]


def searched_nearest(asked: DataFrame, vecs: DataFrame, k: int = 10, block: int = 65_536, least_parts: int = 16) -> DataFrame:
    """(src, dst, w): the k nearest among all ``vecs`` (id, v) of each of ``asked``, exactly; v of any length, as it was read.

    Blocks of asked vectors meet parts of all others, a task for each pair, which gives its k best. Vectors are
    shuffled as they are, once a block of asked ones, so floats stay floats.
    """
    known = "id is not null and size(v) > 0"
    asked, vecs = asked.select("id", "v").where(known), vecs.select("id", "v").where(known)
    parts, groups = max(least_parts, -(-vecs.count() // (2 * block))), max(1, -(-asked.count() // block))
    dealt = lambda rows, count: rows.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(count)).cast("int"))
    each = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    left = dealt(asked, groups).withColumn("q", each(parts)).select(F.col("part").alias("p"), "q", "id", "v")
    right = dealt(vecs, parts).withColumn("p", each(groups)).select("p", F.col("part").alias("q"), "id", "v")

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        ids, x = _sound(a) if len(a) else ([], [])
        others, y = _sound(b) if len(b) else ([], [])
        if not len(ids) or not len(others):
            return pd.DataFrame({"src": [], "dst": [], "w": []})
        row, at, w = _searched(ids, x, others, y, k)
        return pd.DataFrame({"src": ids[row], "dst": others[at], "w": w})

    pairs = left.groupBy("p", "q").cogroup(right.groupBy("p", "q")).applyInPandas(near, _PAIRS)
    order = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return pairs.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).drop("place")


def _ranked(x: np.ndarray, centres: np.ndarray, most: int) -> np.ndarray:
    """The ``most`` nearest centres of each row of x, nearest first, some rows at a time."""
    return np.concatenate([np.argsort(-(x[i : i + 1_024] @ centres.T), axis=1, kind="stable")[:, :most] for i in range(0, len(x), 1_024)])


class VectorIndex:
    """Inverted lists: every vector is in the list of its nearest centre and is looked for in several.

    Centres (about the root of the number of vectors, ``fit_rows / 4`` at most) are fitted on ``fit_rows``
    vectors; all vectors are indexed. Within the lists that are looked at, cosines are exact, so a true
    neighbour is found exactly if its list is looked at. ``probes`` is therefore read off: for ``MEASURED_ROWS``
    vectors the exact neighbours among all rows are found, and as many lists are looked at as give ``recall`` of
    them. Vectors without geometry need nearly all lists; ``exact_nearest`` is cheaper there.
    """

    def __init__(self, spark: SparkSession, vecs: DataFrame, k: int = 10, recall: float = 0.95, fit_rows: int = FIT_ROWS, scratch: Scratch | None = None) -> None:
        self.k, self.scratch = k, scratch or Scratch(spark, "vectors")
        vecs = self.scratch.save(vecs.select("id", "v"))
        n = vecs.count()
        self.lists = max(1, min(math.isqrt(n), fit_rows // 4))
        self.probes, self.recall = 1, 1.0
        hashed = vecs.orderBy(F.xxhash64("id"), "id")
        fitted = hashed.limit(fit_rows).toPandas()  # bounded by fit_rows
        self.centres = self._fit(_matrix(fitted["v"])) if n else np.zeros((1, 1))
        self.vectors = self.scratch.save(self._placed(vecs, 1).select("id", "v", F.get("near", F.lit(0)).alias("list")))
        if n > 1:
            self._measure(fitted[:MEASURED_ROWS], recall)

    def _fit(self, x: np.ndarray, rounds: int = 8) -> np.ndarray:
        centres = x[np.linspace(0, len(x) - 1, self.lists).astype(int)]
        for _ in range(rounds):
            sums = np.zeros_like(centres)
            np.add.at(sums, _ranked(x, centres, 1)[:, 0], x)
            size = np.linalg.norm(sums, axis=1, keepdims=True)
            centres = np.where(size > 0, sums / np.maximum(size, 1e-300), centres)
        return centres

    def _placed(self, vecs: DataFrame, most: int) -> DataFrame:
        """``vecs`` with their ``most`` nearest lists."""
        centres = self.centres

        def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                if len(batch):
                    yield batch.assign(near=list(_ranked(_matrix(batch["v"]), centres, most).astype(np.int32)))

        return vecs.select("id", "v").mapInPandas(rows, "id long, v array<double>, near array<int>")

    def _measure(self, asked: pd.DataFrame, recall: float) -> None:
        ids, x, k = asked["id"].to_numpy(), _matrix(asked["v"]), self.k

        def rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                if len(batch):
                    batch = batch.sort_values("id")
                    row, at, w = _top(ids, x, batch, k)
                    yield pd.DataFrame({"q": row, "dst": batch["id"].to_numpy()[at], "w": w, "list": batch["list"].to_numpy()[at]})

        order = Window.partitionBy("q").orderBy(F.desc("w"), "dst")
        found = self.vectors.mapInPandas(rows, "q int, dst long, w double, list int").withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)
        true = found.select("q", "list").toPandas()  # k * MEASURED_ROWS rows at most
        place = np.argsort(_ranked(x, self.centres, self.lists), axis=1)
        needed = np.sort(place[true["q"].to_numpy(), true["list"].to_numpy()]) + 1
        self.probes = int(needed[math.ceil(recall * len(needed)) - 1])
        self.recall = float((needed <= self.probes).mean())

    def nearest(self, block: int = 1_000) -> DataFrame:
        """(src, dst, w) of every vector. Lists and those that ask them are dealt into blocks, so a large list is no hot key."""
        asks = self.scratch.save(self._placed(self.vectors, self.probes).select("id", "v", F.explode("near").alias("list")))
        blocks = lambda rows, name: rows.groupBy("list").agg(F.ceil(F.count("*") / block).cast("int").alias(name))
        sizes = self.scratch.save(blocks(asks, "n_p").join(blocks(self.vectors, "n_q"), "list"))
        sizes = bounded_broadcast(sizes, self.lists)
        part = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
        each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        left = asks.join(sizes, "list").select("list", part("n_p").alias("p"), each("n_q").alias("q"), "id", "v")
        right = self.vectors.join(sizes, "list").select("list", each("n_p").alias("p"), part("n_q").alias("q"), "id", "v")
        return _nearest_of_blocks(left, right, ["list", "p", "q"], self.k)
