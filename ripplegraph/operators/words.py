"""Clusters of documents by waves over the links between those that share words, whose links are never rows.

Links of documents that share ``least`` words or more grow with the square of the documents. Their weights are shared
words, so a sum over neighbours is a product with the table of words and its transpose, less what the pairs below
``least`` would add. Those are counted anew for each product, 64 documents to a machine word, from the words of two
blocks of documents. Nothing is kept for a pair of documents; a block's words are, once for each block that it meets.
Time grows with the square of the documents.

The Fourier sums of a run are polynomials of the walk applied to its start. They are read in the space of the first
powers of the walk on the start (block Lanczos, orthogonal by degree), where a run is one of small matrices. Powers are
added until the peaks and their coefficients stand still, which takes far fewer than the steps where the spectrum
has few modes outside a narrow bulk, and cannot take more.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.functions.bounds import DEFAULT_C2, check_speed
from ripplegraph.operators.cluster import LABELS, ROBUST, LocalGraph, Preset, codes, labels_of, local_modes, start_values
from ripplegraph.operators.components import components
from ripplegraph.plans.scratch import BROADCAST_BYTES, BROADCAST_ROWS, Scratch, bounded_broadcast

#: Documents of a block, those of them that are held as bits at a time, rows that meet these at a time, and columns that are multiplied at a time.
BLOCK = 32_768
SPAN = 8_192
ROWS = 64
TILE = 1_024
#: Powers are added until peaks and coefficients change by no more than this.
STILL = 1e-10
#: Directions shorter than this (a walk makes no vector longer) are rounding.
SHORT = 1e-10


def shared_words(a: pd.Series, b: pd.Series, n_words: int, rows: int = 1_024) -> Iterator[tuple[int, np.ndarray]]:
    """(first row, counts of shared words) of some rows of ``a`` at a time against all of ``b``; word numbers are below ``n_words``."""
    held = np.zeros((n_words, len(b)), dtype=np.uint8)
    held[np.concatenate(b.to_numpy()), np.repeat(np.arange(len(b)), b.map(len))] = 1
    own = a.to_numpy()
    for at in range(0, len(own), rows):
        part = own[at : at + rows]
        out = np.empty((len(part), len(b)), dtype=np.uint16)
        for i, words in enumerate(part):
            out[i] = held[words].sum(axis=0, dtype=np.uint8 if len(words) < 256 else np.uint16)
        yield at, out


def forest(keep: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For rows and for columns of a matrix of links: the first row of their component, -1 without links."""
    rows, columns = np.full(keep.shape[0], -1), np.full(keep.shape[1], -1)
    linked = keep.any(axis=1)
    for i in range(len(ids)):
        if rows[i] >= 0 or not linked[i]:
            continue
        rows[i], new = i, np.array([i])
        while len(new):
            reached = np.flatnonzero(keep[new].any(axis=0) & (columns < 0))
            columns[reached] = i
            new = np.flatnonzero(keep[:, reached].any(axis=1) & (rows < 0))
            rows[new] = i
    return rows, columns


def block_pairs(own: DataFrame, blocks: int) -> tuple[DataFrame, DataFrame]:
    """``own(doc_id, words)`` dealt into blocks, and each block once for every block that it meets: as (p, q, ..) for p <= q, from both sides."""
    numbered = own.withColumn("b", F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int"))
    up, down = F.explode(F.sequence(F.col("b"), F.lit(blocks - 1))), F.explode(F.sequence(F.lit(0), F.col("b")))
    left = numbered.withColumn("o", up).select(F.col("b").alias("p"), F.col("o").alias("q"), "doc_id", "words")
    right = numbered.withColumn("o", down).select(F.col("o").alias("p"), F.col("b").alias("q"), "doc_id", "words")
    return left, right


def links_between(a: pd.DataFrame, b: pd.DataFrame, n_words: int, least: int, same: bool) -> pd.DataFrame:
    """(doc_id, n, w, root) of the documents with a link between two blocks."""
    ids_a, ids_b = a["doc_id"].to_numpy(), b["doc_id"].to_numpy()
    keep = np.zeros((len(a), len(b)), dtype=bool)
    n_a, w_a, n_b, w_b = (np.zeros(len(x)) for x in (a, a, b, b))
    for at, shared in shared_words(a["words"], b["words"], n_words):
        own = keep[at : at + len(shared)]
        np.greater_equal(shared, least, out=own)
        if same:
            own[np.arange(len(shared)), at + np.arange(len(shared))] = False
        shared *= own
        n_a[at : at + len(shared)], w_a[at : at + len(shared)] = own.sum(axis=1), shared.sum(axis=1, dtype=np.int64)
        if not same:
            n_b += own.sum(axis=0)
            w_b += shared.sum(axis=0, dtype=np.int64)
    root_a, root_b = forest(keep, ids_a)
    side = lambda ids, n, w, root: pd.DataFrame({"doc_id": ids, "n": n.astype(np.int64), "w": w, "root": root})
    out = pd.concat([side(ids_a, n_a, w_a, root_a), side(ids_b, n_b, w_b, root_b)], ignore_index=True)
    return out[out["root"] >= 0].assign(root=lambda x: ids_a[x["root"]])


@dataclass
class WordBlock:
    """Words of documents, one after the other; no document is without words."""

    sizes: np.ndarray
    words: np.ndarray

    def spans(self) -> Iterator[tuple[slice, WordBlock]]:
        """Some documents at a time."""
        ends = np.concatenate(([0], np.cumsum(self.sizes)))
        for at in range(0, len(self.sizes), SPAN):
            own = slice(at, min(at + SPAN, len(self.sizes)))
            yield own, WordBlock(self.sizes[own], self.words[ends[own.start] : ends[own.stop]])

    def sums(self, z: np.ndarray) -> np.ndarray:
        """Sums over the words of each document."""
        return np.concatenate([np.add.reduceat(z[part.words], np.cumsum(part.sizes) - part.sizes) for _, part in self.spans()])

    def bits(self, n_words: int) -> np.ndarray:
        """A row of bits for each word, and an empty one."""
        held = np.zeros((n_words + 1, -(-len(self.sizes) // 64) * 64), dtype=np.uint8)
        held[self.words, np.repeat(np.arange(len(self.sizes)), self.sizes)] = 1
        return np.packbits(held, axis=1).view(np.uint64)

    def counted(self, held: np.ndarray, least: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(documents, bits of the words that they share with each of ``held``, where those are below ``least``, and bits of the others)."""
        starts, none = np.cumsum(self.sizes) - self.sizes, len(held) - 1
        order = np.argsort(self.sizes, kind="stable")  # documents of like size meet together
        for at in range(0, len(order), ROWS):
            own = order[at : at + ROWS]
            each, n = np.arange(self.sizes[own].max()), self.sizes[own][:, None]
            picks = np.where(each < n, self.words[starts[own][:, None] + np.minimum(each, n - 1)], none).T.copy()
            counts = np.zeros(((least - 1).bit_length(), len(own), held.shape[1]), dtype=np.uint64)
            over, carry, next_carry = (np.zeros_like(held, shape=(len(own), held.shape[1])) for _ in range(3))
            for pick in picks:
                np.take(held, pick, axis=0, out=carry, mode="clip")
                for count in counts:
                    np.bitwise_and(count, carry, out=next_carry)
                    np.bitwise_xor(count, carry, out=count)
                    carry, next_carry = next_carry, carry
                np.bitwise_or(over, carry, out=over)
            few = ~over
            if least < 1 << len(counts):
                less, equal = np.zeros_like(over), ~np.zeros_like(over)
                for place in reversed(range(len(counts))):
                    if least >> place & 1:
                        less |= equal & ~counts[place]
                        equal &= counts[place]
                    else:
                        equal &= ~counts[place]
                few &= less
            yield own, counts & few, ~few


def unpacked(counts: np.ndarray, n: int) -> np.ndarray:
    """Numbers of their bits, for the first ``n`` columns."""
    out = np.zeros((counts.shape[1], n), dtype=np.uint8 if len(counts) <= 8 else np.uint32)
    for place, bits in enumerate(counts):
        ones = np.unpackbits(bits.view(np.uint8), axis=1, count=n).astype(out.dtype, copy=False)
        out |= np.left_shift(ones, place, out=ones)
    return out


def joined(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(id, smallest id of its component)."""
    ids, flat = np.unique(np.concatenate((src, dst)), return_inverse=True)
    a, b, label = flat[: len(src)], flat[len(src) :], np.arange(len(ids))
    while True:
        low = label.copy()
        np.minimum.at(low, a, label[b])
        np.minimum.at(low, b, label[a])
        low = low[low]
        if (low == label).all():
            return ids, ids[label]
        label = low


def weights_between(ids_a: np.ndarray, a: WordBlock, ids_b: np.ndarray, b: WordBlock, n_words: int, least: int, same: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc_id, weight of its links, root) of the documents with a link between two blocks, which may be the same."""
    w_a = a.sums(np.bincount(b.words, minlength=n_words).astype(float))
    w_b = b.sums(np.bincount(a.words, minlength=n_words).astype(float))
    if same:
        w_a -= a.sizes
    src, dst = [], []
    for at_b, part_b in b.spans():
        held, n_b = part_b.bits(n_words), len(part_b.sizes)
        for at_a, part_a in a.spans():
            keep = np.zeros((len(part_a.sizes), n_b), dtype=bool)
            for own, counts, links in part_a.counted(held, least):
                keep[own] = np.unpackbits(links.view(np.uint8), axis=1, count=n_b)
                few = unpacked(counts, n_b)
                w_a[at_a.start + own] -= few.sum(axis=1)
                w_b[at_b] -= few.sum(axis=0)
            if same and at_a == at_b:
                np.fill_diagonal(keep, False)
            own_a, own_b = ids_a[at_a], ids_b[at_b]
            rows, columns = forest(keep, own_a)
            for ids, roots in ((own_a, rows), (own_b, columns)):
                src.append(ids[roots >= 0])
                dst.append(own_a[roots[roots >= 0]])
    ids, roots = joined(np.concatenate(src), np.concatenate(dst))
    weight = pd.Series(w_a, ids_a) if same else pd.concat([pd.Series(w_a, ids_a), pd.Series(w_b, ids_b)])
    return ids, weight.loc[ids].to_numpy(), roots


@dataclass
class WordGraph(LocalGraph):
    """One component in memory: nodes in id order, all weights in one matrix."""

    w: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))

    def mean_of_neighbours(self, u: np.ndarray) -> np.ndarray:
        sums = [self.w[i : i + 4 * ROWS].astype(float) @ u for i in range(0, len(u), 4 * ROWS)]
        return np.concatenate(sums) / self.deg[:, None]


def word_labels(docs: pd.DataFrame, n_words: int, least: int, k: int, c2: float, steps: int | None, preset: Preset, seed: int = 0) -> pd.DataFrame:
    """As ``local_labels`` of the links between documents with distinct ids, for all components."""
    docs = docs.sort_values("doc_id")
    ids = docs["doc_id"].to_numpy()
    w = np.concatenate([part for _, part in shared_words(docs["words"], docs["words"], n_words)])
    w[w < least] = 0
    np.fill_diagonal(w, 0)
    keep, none, found = w > 0, np.zeros(0), []
    todo = keep.any(axis=1)
    while todo.any():
        part = new = np.arange(len(ids)) == np.argmax(todo)
        while new.any():
            new = keep[new].any(axis=0) & ~part
            part = part | new
        todo &= ~part
        own = np.flatnonzero(part)
        part = w[np.ix_(own, own)]
        found.append(labels_of(WordGraph(ids[own], none, none, none, part.sum(axis=1, dtype=float), part), k, c2, steps, preset, seed))
    return pd.concat(found, ignore_index=True) if found else pd.DataFrame({"id": [], "bits": [], "cluster": [], "group_rep": [], "margin": []}, dtype=object)


def word_cluster(spark: SparkSession, own: DataFrame, n_words: int, least: int, k: int = 1, c2: float = DEFAULT_C2, steps: int = 240, preset: Preset = ROBUST, seed: int = 0, max_nodes: int = 5_000, block: int = BLOCK, scratch: Scratch | None = None) -> DataFrame:
    """The rows of ``wave_cluster`` over the links of ``own(doc_id, words)``: distinct documents with distinct word numbers below ``n_words``."""
    check_speed(c2)
    scratch = scratch or Scratch(spark, "words")
    local = lambda part: word_labels(part, n_words, least, k, c2, steps, preset, seed)
    own = scratch.save(own.where(F.size("words") >= least).select(F.col("doc_id").cast("long").alias("doc_id"), "words"))
    n_docs = own.count()
    if n_docs <= max_nodes:
        return own.groupBy(F.lit(0).alias("all")).applyInPandas(lambda part: local(part.drop(columns="all", errors="ignore")), LABELS)
    parts = WordParts(spark, own, n_docs, n_words, least, block, scratch)
    sizes = scratch.save(parts.linked.groupBy("component").agg(F.count("*").alias("n")))
    few = sizes.where(F.col("n") <= max_nodes).select("component")
    small = own.join(parts.linked.join(bounded_broadcast(few, few.count()), "component", "left_semi").select("doc_id", "component"), "doc_id")
    out = small.groupBy("component").applyInPandas(lambda part: local(part[["doc_id", "words"]]), LABELS)
    kept, found = f"large-{uuid.uuid4().hex}", False
    for row in sizes.where(F.col("n") > max_nodes).toLocalIterator():
        parts.labels(row["component"], k, c2, steps, preset, seed).write.mode("append").parquet(scratch.path(kept))
        found = True
    return out.unionByName(spark.read.schema(LABELS).parquet(scratch.path(kept))) if found else out


@dataclass
class Powers(LocalGraph):
    """A run in the space of the first powers of a walk: coordinates instead of nodes, in which products by degree are plain ones."""

    walk: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    first: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))

    def mean_of_neighbours(self, u: np.ndarray) -> np.ndarray:
        return self.walk @ u

    def start(self, preset: Preset, seed: int = 0) -> np.ndarray:
        return self.first


PAIRS = "p int, q int, sizes_p array<int>, words_p array<{0}>, sizes_q array<int>, words_q array<{0}>, doc_id array<long>, w array<double>, root array<long>"
PLACES = "p int, ids array<long>, sizes array<int>, words array<int>, deg array<double>"
BASIS = f"{PLACES}, q array<double>, last array<double>, z array<double>"
NEXT = "p int, y array<double>, h array<double>"


class WordParts:
    """Documents beyond what one batch holds, in blocks: a stage of tasks for each power of the walk.

    The driver gets matrices of as many rows as there are words or columns of the basis, never one of the documents.
    """

    def __init__(self, spark: SparkSession, own: DataFrame, n_docs: int, n_words: int, least: int, block: int, scratch: Scratch) -> None:
        self.spark, self.n_docs, self.n_words, self.least, self.scratch = spark, n_docs, n_words, least, scratch
        self.blocks = max(8, -(-n_docs // block))
        number = "smallint" if n_words <= 1 << 15 else "int"
        own = own.withColumn("words", F.sort_array("words").cast(f"array<{number}>"))
        left, right = block_pairs(own, self.blocks)
        schema = PAIRS.format(number)

        def met(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
            if a.empty or b.empty:
                return pd.DataFrame({name: [] for name in ("p", "q", "sizes_p", "words_p", "sizes_q", "words_q", "doc_id", "w", "root")}, dtype=object)
            a, b = a.sort_values("doc_id"), b.sort_values("doc_id")
            p, q = a["p"].iloc[0], a["q"].iloc[0]
            one, two = (WordBlock(x["words"].map(len).to_numpy(), np.concatenate(x["words"].to_numpy())) for x in (a, b))
            ids, w, roots = weights_between(a["doc_id"].to_numpy(), one, b["doc_id"].to_numpy(), two, n_words, least, p == q)
            return pd.DataFrame({"p": [p], "q": [q], "sizes_p": [one.sizes], "words_p": [one.words], "sizes_q": [two.sizes], "words_q": [two.words], "doc_id": [ids], "w": [w], "root": [roots]})

        pairs = self.blocks * (self.blocks + 1) // 2
        # A row holds megabytes and a file's rows are held until it is written: about a pair to a task, however many there are.
        met_pairs = left.repartition(pairs, "p", "q").groupBy("p", "q").cogroup(right.repartition(pairs, "p", "q").groupBy("p", "q")).applyInPandas(met, schema)
        met_pairs.write.mode("overwrite").option("compression", "zstd").parquet(scratch.path("pairs"))
        found = spark.read.schema(schema).parquet(scratch.path("pairs"))
        self.pairs = found.select("p", "q", "sizes_p", "words_p", "sizes_q", "words_q")
        each = found.select(F.explode(F.arrays_zip("doc_id", "w", "root")).alias("x")).select("x.*")
        whole = components(spark, scratch.save(each.select(F.col("doc_id").alias("src"), F.col("root").alias("dst")).distinct()), scratch).toDF("doc_id", "component")
        self.linked = scratch.save(each.groupBy("doc_id").agg(F.sum("w").alias("deg")).join(whole, "doc_id"))
        self.own = own.withColumn("p", F.pmod(F.xxhash64("doc_id"), F.lit(self.blocks)).cast("int"))

    def labels(self, component: int, k: int, c2: float, steps: int, preset: Preset, seed: int) -> DataFrame:
        """Labels of one component: the others have degree 0 here and no part in it."""
        if preset.parted or preset.closed or preset.frequencies != "peaks" or not steps:
            raise ValueError("so many documents run in tasks, which need given steps and read peaks")
        within = self.linked.where(F.col("component") == component).select("doc_id", "deg")
        rows = F.sort_array(F.collect_list(F.struct("doc_id", F.size("words").alias("n"), "words", F.coalesce("deg", F.lit(0.0)).alias("deg")))).alias("r")
        tasks = min(self.blocks, int(self.spark.conf.get("spark.sql.shuffle.partitions")))
        blocks = self.own.join(within, "doc_id", "left").repartition(tasks, "p").groupBy("p").agg(rows)
        places = self.scratch.save(blocks.select("p", F.col("r.doc_id").alias("ids"), F.col("r.n").alias("sizes"), F.flatten(F.col("r.words")).alias("words"), F.col("r.deg").alias("deg")))
        basis, first = self._start(places, preset, seed)
        walk, width, names, last = np.zeros((0, 0)), len(first), [], None
        cols = width
        for power in range(1, steps + 2):
            few = self.scratch.save(self._below(basis, cols), f"few-{component}")
            z = self._added(basis, "z").reshape(self.n_words, cols)
            y = self.scratch.save(self._walked(basis, few, z, width, cols), f"next-{component}")
            h = self._added(y, "h").reshape(width, cols)
            again = self._added(self._left(basis, y, h, width, cols), "h").reshape(width + cols, cols)
            h += again[:width]
            grown = np.zeros((width, width))
            grown[: len(walk), : len(walk)] = walk
            grown[:, width - cols :], grown[width - cols :, :] = h, h.T
            grown[width - cols :, width - cols :] = (h[width - cols :] + h[width - cols :].T) / 2
            walk = grown
            none = np.zeros(0)
            start = np.zeros((width, first.shape[1]))
            start[: len(first)] = first
            omegas, coef = local_modes(Powers(np.arange(width), none, none, none, np.ones(width), walk, start), k, c2, steps, preset, seed)
            if power > steps or last is not None and still(last, (omegas, coef)):
                break
            last = omegas, coef
            rest = again[width:] - again[:width].T @ again[:width]
            e, turn = np.linalg.eigh((rest + rest.T) / 2)
            kept = e > SHORT**2
            if not kept.any():  # the space holds all further powers
                break
            basis = self._grown(basis, y, h, turn[:, kept] / np.sqrt(e[kept]), width, f"basis{power}-{component}")
            names.append(f"basis{power}-{component}")
            if len(names) > 1:
                self.scratch.drop(names[-2])
            cols = int(kept.sum())
            width += cols
            self.scratch.release()
        return self._coded(basis, coef, width)

    def _near(self, df: DataFrame, cols: int) -> DataFrame:
        """A table of some columns of all documents, for joins by block."""
        return F.broadcast(df) if self.blocks <= BROADCAST_ROWS and self.n_docs * cols * 8 <= BROADCAST_BYTES else df

    def _added(self, table: DataFrame, column: str) -> np.ndarray:
        """The sum of a small array over all blocks."""
        return np.sum([r[0] for r in table.orderBy("p").select(column).collect()], axis=0)

    def _start(self, places: DataFrame, preset: Preset, seed: int) -> tuple[DataFrame, np.ndarray]:
        n = preset.seeds

        def values(ids: np.ndarray) -> np.ndarray:
            return np.column_stack([start_values(ids, seed + r) for r in range(n)])

        def moments(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                ones = [(r.p, np.column_stack((values(r.ids), np.ones(len(r.ids)))), r.deg) for r in batch.itertuples(index=False)]
                yield pd.DataFrame([(p, ((x * d[:, None]).T @ x).ravel()) for p, x, d in ones], columns=["p", "h"])

        held = places.select("p", "ids", "deg")
        gram = self._added(held.mapInPandas(moments, "p int, h array<double>"), "h").reshape(n + 1, n + 1)
        mean = gram[-1, :n] / gram[-1, -1] if preset.center else np.zeros(n)

        def products(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                own = [(r.p, values(r.ids) - mean, r.deg) for r in batch.itertuples(index=False)]
                yield pd.DataFrame([(p, ((x * d[:, None]).T @ x).ravel()) for p, x, d in own], columns=["p", "h"])

        gram = self._added(held.mapInPandas(products, "p int, h array<double>"), "h").reshape(n, n)
        e, turn = np.linalg.eigh((gram + gram.T) / 2)
        kept = e > SHORT**2 * e[-1]
        turn, e, n_words = turn[:, kept], e[kept], self.n_words

        def begin(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                new = [(values(r.ids) - mean) @ (turn / np.sqrt(e)) * (r.deg > 0)[:, None] for r in batch.itertuples(index=False)]
                z = [of_words(q, r.sizes, r.words, n_words).ravel() for q, r in zip(new, batch.itertuples(index=False), strict=True)]
                flat = [q.ravel() for q in new]
                yield batch.assign(q=flat, last=flat, z=z)

        return self.scratch.save(places.mapInPandas(begin, BASIS)), np.sqrt(e)[:, None] * turn.T

    def _below(self, basis: DataFrame, cols: int) -> DataFrame:
        """(p, c): sums of the last columns over the documents that share words, but too few for a link."""
        own = self._near(basis.select("p", "last"), cols)
        rows = self.pairs.join(own.withColumnRenamed("last", "u"), "p").join(own.toDF("q", "v"), "q")
        n_words, least = self.n_words, self.least

        def below(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total: dict[int, np.ndarray] = {}
            for batch in batches:
                for r in batch.itertuples(index=False):
                    u, v = r.u.reshape(-1, cols), r.v.reshape(-1, cols)
                    at_p, at_q = (total.setdefault(p, np.zeros_like(x)) for p, x in ((r.p, u), (r.q, v)))
                    rows = WordBlock(r.sizes_p, r.words_p)
                    for at, part in WordBlock(r.sizes_q, r.words_q).spans():
                        for own, counts, _ in rows.counted(part.bits(n_words), least):
                            few, u_own = unpacked(counts, len(part.sizes)), u[own]
                            for i in range(0, few.shape[1], TILE):
                                w, to = few[:, i : i + TILE].astype(float), slice(at.start + i, min(at.start + i + TILE, at.stop))
                                at_p[own] += w @ v[to]
                                if r.p != r.q:
                                    at_q[to] += w.T @ u_own
            yield pd.DataFrame([(p, x.ravel()) for p, x in total.items()], columns=["p", "c"])

        def total(part: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"p": part["p"].iloc[:1], "c": [np.sum(part["c"].tolist(), axis=0)]})

        sums = "p int, c array<double>"
        return rows.mapInPandas(below, sums).groupBy("p").applyInPandas(total, sums)

    def _walked(self, basis: DataFrame, few: DataFrame, z: np.ndarray, width: int, cols: int) -> DataFrame:
        """(p, y, h): the walk of the last columns, and its products by degree with the basis."""

        def walk(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                out = []
                for r in batch.itertuples(index=False):
                    y = WordBlock(r.sizes, r.words).sums(z)
                    y -= r.sizes[:, None] * r.last.reshape(-1, cols) + r.c.reshape(-1, cols)
                    y = np.where(r.deg[:, None] > 0, y / np.where(r.deg > 0, r.deg, 1.0)[:, None], 0.0)
                    out.append((r.p, y.ravel(), ((r.q.reshape(-1, width) * r.deg[:, None]).T @ y).ravel()))
                yield pd.DataFrame(out, columns=["p", "y", "h"])

        return basis.select("p", "sizes", "words", "deg", "q", "last").join(self._near(few, cols), "p").mapInPandas(walk, NEXT)

    def _left(self, basis: DataFrame, y: DataFrame, h: np.ndarray, width: int, cols: int) -> DataFrame:
        """(p, h): products by degree of what ``y`` has outside the basis, with the basis and with itself."""

        def products(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                out = []
                for r in batch.itertuples(index=False):
                    q = r.q.reshape(-1, width)
                    x = r.y.reshape(-1, cols) - q @ h
                    out.append((r.p, (np.concatenate((q, x), axis=1).T @ (x * r.deg[:, None])).ravel()))
                yield pd.DataFrame(out, columns=["p", "h"])

        rows = basis.select("p", "deg", "q").join(self._near(y.select("p", "y"), cols), "p")
        return rows.mapInPandas(products, "p int, h array<double>")

    def _grown(self, basis: DataFrame, y: DataFrame, h: np.ndarray, turn: np.ndarray, width: int, name: str) -> DataFrame:
        n_words = self.n_words

        def more(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                old = [r.q.reshape(-1, width) for r in batch.itertuples(index=False)]
                new = [(y.reshape(len(q), -1) - q @ h) @ turn for q, y in zip(old, batch["y"], strict=True)]
                z = [of_words(x, r.sizes, r.words, n_words).ravel() for x, r in zip(new, batch.itertuples(index=False), strict=True)]
                both = [np.concatenate(x, axis=1).ravel() for x in zip(old, new, strict=True)]
                yield batch.drop(columns="y").assign(q=both, last=[x.ravel() for x in new], z=z)

        rows = basis.drop("last", "z").join(self._near(y.select("p", "y"), h.shape[1]), "p")
        return self.scratch.save(rows.mapInPandas(more, BASIS), name)

    def _coded(self, basis: DataFrame, coef: np.ndarray, width: int) -> DataFrame:
        n = coef.shape[1]
        rms = np.sqrt((coef**2).sum(axis=0) / basis.select(F.explode("deg").alias("d")).agg(F.sum("d")).first()[0])
        rows = basis.select("p", "ids", "deg", "q")

        def nodes(ids: np.ndarray, q: np.ndarray, deg: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            return ids[deg > 0], (q.reshape(-1, width) @ coef)[deg > 0]

        def firsts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                seen = [(ids[0], c[0]) for ids, c in (nodes(r.ids, r.q, r.deg) for r in batch.itertuples(index=False)) if len(ids)]
                yield pd.DataFrame(seen, columns=["id", "c"])

        first = rows.mapInPandas(firsts, "id long, c array<double>").orderBy("id").first()

        def code(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for batch in batches:
                for r in batch.itertuples(index=False):
                    ids, c = nodes(r.ids, r.q, r.deg)
                    bits, cluster = codes(np.concatenate(([first["c"]], c)))  # bits are turned by the first row
                    margin = (np.abs(c) / np.maximum(rms, 1e-300)).min(axis=1) if n else np.zeros(len(ids))
                    yield pd.DataFrame({"id": ids, "bits": list(bits[1:]), "cluster": cluster[1:], "margin": margin})

        coded = self.scratch.save(rows.mapInPandas(code, "id long, bits array<int>, cluster long, margin double"))
        reps = coded.groupBy("cluster").agg(F.min("id").alias("group_rep"))
        return coded.join(F.broadcast(reps), "cluster").select("id", "bits", "cluster", "group_rep", "margin")  # 2**k groups at most


def of_words(q: np.ndarray, sizes: np.ndarray, words: np.ndarray, n_words: int) -> np.ndarray:
    """Sums over the documents of each word."""
    at = np.repeat(np.arange(len(sizes)), sizes)
    return np.column_stack([np.bincount(words, q[at, c], n_words) for c in range(q.shape[1])])


def still(last: tuple[np.ndarray, np.ndarray], now: tuple[np.ndarray, np.ndarray]) -> bool:
    """Whether one power more left all peaks where they were and changed no coefficients; a coefficient's sign as a whole is free."""
    if len(last[0]) != len(now[0]) or not np.array_equal(last[0], now[0]):
        return False
    before = np.zeros_like(now[1])
    before[: len(last[1])] = last[1]
    before *= np.where((before * now[1]).sum(axis=0) < 0, -1.0, 1.0)
    return bool((np.linalg.norm(before - now[1], axis=0) <= STILL * np.linalg.norm(now[1], axis=0)).all())
