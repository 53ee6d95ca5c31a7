"""N-gram Jaccard join: rare-first prefix filtering, each candidate pair verified once.

A document's set holds its distinct 5-word shingles (A-Z lower-cased; a shorter text is one shingle as a
whole). Documents link when 100 * intersection >= 75 * union.

1. Equal sets form a class, kept once. Copies cost one row each from here on.
2. Order. Two tables of fixed size (``RARITY_ROWS``) hold the most frequent shingles and words. Shingles that
   are in the first come last, by their count; others go by how frequent their words make them, then by
   hash. The tables shape the cost and never the result: any order that all share is exact.
3. Postings. Only the prefix of ``n - ceil(0.75 n) + 1`` rarest shingles of a set is emitted: sets that
   link share one of these. Postings are sorted over ranges of (shingle, position), which also splits hot
   shingles; shingles of one class only are dropped there.
4. Candidates by stars. In each posting list, each class is paired with the list's most central one (that
   has the shingle at the earliest position of its prefix) and with its neighbour: pairs in proportion to
   the list. The length and positional filters are applied at once; the suffix filter bounds the difference
   of whole sets from below by their parity bitmaps; survivors are verified on whole sets.
   First each class is tried with the partner that it shares most with, then the other pairs across the
   components that this leaves.
5. The rest. In lists that still hold several components, pairs across components become candidates if the
   smaller set's shingle is in its shorter prefix of ``n - ceil(6 n / 7) + 1``, in blocks of a list, and pass
   the same filters. Pairs within a component need no link any more. ``NgramJoin.links`` takes all pairs that way.

So links between classes are lost only where both ends are joined already. A null or empty text has an
empty set and links with nothing. Ids may be null (then the component is of the other ids, or null if
there are none) or repeat: rows are judged by their own text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm import kernel as K
from ripplegraph.llm.store import Scratch, bounded_broadcast, fresh, keyed, same_row, table, text_of
from ripplegraph.operators.components import components

SHINGLE = 5
PERCENT = 75
RARITY_ROWS = 65_536
#: Bits of a set's parity bitmap.
BITS = 1024
#: Sets of so many shingles also get a wide bitmap, for pairs that pass the first.
WIDE_FROM, WIDE_BITS = 1_000, 32_768
_BLOCK = 2_000_000
#: Postings of a list that look for partners in one task.
LIST_BLOCK = 1_000

_SETS = "doc_id long, th long, n long, lo long, hi long, bits array<long>, wide array<long>, prefix array<long>"
_KEPT = "shingle long, cid long, n int, pos int, head long, prev long"


def shingle_sets(words: K.Words, hashed: np.ndarray | None = None, places: list[np.ndarray] | None = None) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text of a slice; ``places`` gets the first word of each."""
    hashed = words.hashes() if hashed is None else hashed
    gram = K.grams(hashed, SHINGLE)
    start = words.start
    size = np.diff(start)
    short = np.flatnonzero((size > 0) & (size < SHINGLE))
    whole = dict(zip(short.tolist(), K.spans_hash(hashed, start[short], start[short + 1]), strict=True)) if len(short) else {}
    out = []
    for k in range(words.n_docs):
        n = size[k]
        if n < SHINGLE:
            out.append(np.array([whole[k]] if n else [], dtype=np.uint64))
            at = np.arange(len(out[-1]))
        elif places is None:
            out.append(np.unique(gram[start[k] : start[k + 1] - SHINGLE + 1]))
            continue
        else:
            own, at = np.unique(gram[start[k] : start[k + 1] - SHINGLE + 1], return_index=True)
            out.append(own)
        if places is not None:
            places.append(start[k] + at)
    return out


def _frequent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Shingles of three documents or more, and the words used most, by blocks of documents."""

    def counted(kind: str, parts: list[np.ndarray]) -> pa.RecordBatch:
        value, times = np.unique(np.concatenate(parts), return_counts=True)
        often = times > 2
        return pa.RecordBatch.from_arrays([pa.array([kind] * int(often.sum()), pa.string()), pa.array(K.signed(value[often])), pa.array(times[often].astype(np.int64))], ["kind", "value", "times"])

    sets: list[np.ndarray] = []
    words: list[np.ndarray] = []
    size = 0
    for batch in batches:
        for w in K.slices(batch.column("text"), lower=True):
            words.append(w.hashes())
            sets += shingle_sets(w, words[-1])
            size += len(words[-1])
            if size > _BLOCK:
                yield counted("shingle", sets)
                yield counted("word", words)
                sets, words, size = [], [], 0
    if words:
        yield counted("shingle", sets)
        yield counted("word", words)


Table = tuple[np.ndarray, np.ndarray]


def rarity_tables(docs: DataFrame, rows: int = RARITY_ROWS) -> tuple[Table, Table]:
    """The most frequent shingles and words and their counts, at most ``rows`` each: sorted by hash."""
    summed = docs.select("text").mapInArrow(_frequent, "kind string, value long, times long").groupBy("kind", "value").agg(F.sum("times").alias("times"))
    summed = summed.withColumn("pick", F.when(F.col("kind") == "shingle", F.struct("times", "value")))
    summed = summed.withColumn("word", F.when(F.col("kind") == "word", F.struct("times", "value")))
    out = []
    for kind in ("pick", "word"):
        top = summed.where(F.col(kind).isNotNull()).select(f"{kind}.*").orderBy(F.desc("times"), "value").limit(rows).toArrow()
        value, times = top["value"].to_numpy().view(np.uint64), top["times"].to_numpy()
        order = np.argsort(value)
        out.append((value[order], times[order]))
    return out[0], out[1]


def _times(table_: Table, values: np.ndarray) -> np.ndarray:
    value, times = table_
    if not len(value) or not len(values):
        return np.zeros(len(values), dtype=np.int64)
    at = np.minimum(np.searchsorted(value, values), len(value) - 1)
    return np.where(value[at] == values, times[at], 0)


def needed(n: np.ndarray | int, m: np.ndarray | int) -> np.ndarray | int:
    """Smallest overlap with which sets of n and m shingles link."""
    return -((-PERCENT * (n + m)) // (100 + PERCENT))


def _set_rows(shingles: Table, words: Table):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for w in K.slices(batch.column("text"), lower=True):
                hashed = w.hashes()
                places: list[np.ndarray] = []
                sets = shingle_sets(w, hashed, places)
                n = np.array([len(s) for s in sets])
                flat = np.concatenate(sets)
                often = _times(shingles, flat)
                used = np.concatenate(([0], np.cumsum((16 * np.log2(1 + _times(words, hashed))).astype(np.int64))))
                at = np.concatenate(places).astype(np.int64)
                likely = used[np.minimum(at + SHINGLE, len(hashed))] - used[at] if len(at) else at
                ends = np.cumsum(n)
                mixed = [K.mix(flat ^ np.uint64(0x5851F42D4C957F2D)), K.mix(flat + np.uint64(0x14057B7EF767814F))]
                sums = [np.concatenate((np.zeros(1, np.uint64), np.cumsum(x, dtype=np.uint64))) for x in mixed]
                lo, hi = (K.mix(s[ends] - s[ends - n] + n.astype(np.uint64)) for s in sums)
                prefixes, bitmaps, wide = [], [], []
                for k, own in enumerate(sets):
                    a, b = ends[k] - n[k], ends[k]
                    count = often[a:b]
                    keep = n[k] - -(-PERCENT * n[k] // 100) + 1 if n[k] else 0
                    prefixes.append(own[np.lexsort((own, likely[a:b], count))[:keep]])
                    odd = np.bincount((own >> np.uint64(54)).astype(np.int64), minlength=BITS) & 1
                    bitmaps.append(np.packbits(odd.astype(np.uint8)).view(np.int64))
                    fine = np.bincount((own >> np.uint64(49)).astype(np.int64), minlength=WIDE_BITS) & 1 if n[k] >= WIDE_FROM else None
                    wide.append(None if fine is None else np.packbits(fine.astype(np.uint8)).view(np.int64))
                sizes = np.array([len(p) for p in prefixes])
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32)), pa.array(K.signed(np.concatenate(prefixes))))
                words_each = BITS // 64
                bits = pa.ListArray.from_arrays(pa.array(np.arange(0, words_each * (len(n) + 1), words_each, dtype=np.int32)), pa.array(np.concatenate(bitmaps)))
                sl = slice(w.first, w.first + w.n_docs)
                ids, th = batch.column("doc_id")[sl], batch.column("th")[sl]
                yield pa.RecordBatch.from_arrays([ids, th, pa.array(n.astype(np.int64)), pa.array(K.signed(lo)), pa.array(K.signed(hi)), bits, pa.array(wide, pa.list_(pa.int64())), lists], ["doc_id", "th", "n", "lo", "hi", "bits", "wide", "prefix"])

    return rows


def _stars(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Postings of one range, sorted by (shingle, pos, cid): those of shared shingles, with up to two partners.

    The first and last list of a range may go on in another range and are kept even if of one row.
    """
    names = ["shingle", "cid", "n", "pos"]
    held: dict[str, np.ndarray] | None = None
    head: tuple[int, ...] | None = None  # shingle, cid, n, pos of the list that the held row is in
    before: tuple[int, ...] | None = None  # the row before the held one
    first_list = True

    def judged(cols: dict[str, np.ndarray], last: bool) -> pa.RecordBatch | None:
        nonlocal head, before, first_list
        s = cols["shingle"]
        n = len(s)
        new = np.ones(n, dtype=bool)
        new[1:] = s[1:] != s[:-1]
        carried = head is not None and head[0] == s[0]
        at = np.maximum.accumulate(np.where(new, np.arange(n), 0))
        heads = {c: cols[c][at] for c in names}
        prevs = {c: np.concatenate((cols[c][:1], cols[c][:-1])) for c in names}
        has_prev = ~new
        if carried:
            run = at == 0
            for i, c in enumerate(names):
                heads[c] = np.where(run, head[i], heads[c])
            if before is not None and before[0] == s[0]:
                for i, c in enumerate(names):
                    prevs[c][0] = before[i]
                has_prev[0] = True
        has_next = np.append(~new[1:], False)
        edge = np.zeros(n, dtype=bool)
        if first_list:
            edge |= at == 0
            if new[1:].any():
                first_list = False
        if last:
            edge |= s == s[-1]
        keep = np.flatnonzero((has_prev | has_next | edge)[: n if last else n - 1])

        def partner(other: dict[str, np.ndarray], ok: np.ndarray) -> pa.Array:
            a, b, pa_, pb = cols["n"].astype(np.int64), other["n"].astype(np.int64), cols["pos"], other["pos"]
            ok = ok & (other["cid"] != cols["cid"]) & (100 * np.minimum(a, b) >= PERCENT * np.maximum(a, b))
            ok &= np.minimum(a - pa_, b - pb) >= needed(a, b)
            return pa.array(other["cid"][keep], mask=~ok[keep])

        i = n - 1
        before = tuple(int(prevs[c][i]) for c in names) if has_prev[i] else None
        head = tuple(int(heads[c][i]) for c in names)
        if not len(keep):
            return None
        near = partner(prevs, has_prev & (prevs["cid"] != heads["cid"]))
        return pa.RecordBatch.from_arrays(
            [pa.array(cols["shingle"][keep]), pa.array(cols["cid"][keep]), pa.array(cols["n"][keep].astype(np.int32)), pa.array(cols["pos"][keep].astype(np.int32)), partner(heads, has_prev), near],
            [*names, "head", "prev"],
        )

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = {c: batch.column(c).to_numpy() for c in names}
        if held is not None:
            cols = {c: np.concatenate((held[c], cols[c])) for c in names}
        out = judged(cols, False)
        held = {c: cols[c][-1:] for c in names}
        if out is not None:
            yield out
    if held is not None:
        out = judged(held, True)
        if out is not None:
            yield out


def near_enough(a: str, b: str, n: Column, m: Column) -> Column:
    """Whether two parity bitmaps differ in no more bits than sets that link can differ in elements.

    An element of one set alone turns one bit of the difference, so the bits that differ are a lower bound
    of the elements that do; links allow n + m - 2 * needed(n, m) of them.
    """
    differ = sum((F.bit_count(F.get(a, F.lit(i)).bitwiseXOR(F.get(b, F.lit(i)))) for i in range(BITS // 64)), F.lit(0))
    return differ <= most_apart(n, m)


def needed_column(n: Column, m: Column) -> Column:
    return F.floor(((n + m) * PERCENT + (99 + PERCENT)) / (100 + PERCENT))


def most_apart(n: Column, m: Column) -> Column:
    return n + m - 2 * needed_column(n, m)


def _set_blobs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for w in K.slices(batch.column("text"), lower=True):
            ids = batch.column("cid")[w.first : w.first + w.n_docs]
            yield pa.RecordBatch.from_arrays([ids, pa.array([s.tobytes() for s in shingle_sets(w)], pa.binary())], ["cid", "set"])


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ok = []
        for x, y in zip(batch.column("set_a"), batch.column("set_b"), strict=True):
            a, b = np.frombuffer(x.as_buffer(), dtype=np.uint64), np.frombuffer(y.as_buffer(), dtype=np.uint64)
            both = len(np.intersect1d(a, b, assume_unique=True))
            ok.append(100 * both >= PERCENT * (len(a) + len(b) - both))
        yield batch.select(["a", "b"]).filter(pa.array(ok, pa.bool_()))


class NgramJoin:
    """The stages of one join; each reads and writes tables of ``scratch``."""

    def __init__(self, spark: SparkSession, docs: DataFrame, scratch: Scratch | None = None) -> None:
        self.spark, self.scratch = spark, scratch or Scratch(spark, "op5")
        self.rows = keyed(docs)

    def classes(self) -> None:
        sets = self.scratch.save(self.rows.mapInArrow(_set_rows(*rarity_tables(self.rows)), _SETS), "sets")
        one = sets.where("n > 0").groupBy("lo", "hi").agg(F.first("n").alias("n"), F.min("doc_id").alias("least_id"), F.min(F.struct("doc_id", "th")).alias("row"), F.first("bits").alias("bits"), F.first("wide").alias("wide"), F.first("prefix").alias("prefix"))
        self.prefixes = self.scratch.save(one.withColumn("cid", F.monotonically_increasing_id()), "prefixes")
        self.sets = self.scratch.save(sets.select("doc_id", "th", "n", "lo", "hi"), "members")
        self.scratch.drop("sets")
        self.scratch.release()

    def postings(self) -> None:
        order = ["shingle", "pos", "cid"]
        flat = self.prefixes.select("cid", F.col("n").cast("int").alias("n"), F.posexplode("prefix").alias("pos", "shingle"))
        self.kept = self.scratch.save(flat.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_stars, _KEPT), "kept")
        self.by_class = self.scratch.save(self.prefixes.drop("prefix"), "classes")
        self.scratch.drop("prefixes")
        self.scratch.release()

    def star_pairs(self) -> DataFrame:
        """(a, b, shared): distinct pairs of a class and a partner, with the number of lists that name them."""
        pair = lambda other: F.struct(F.least("cid", other).alias("a"), F.greatest("cid", other).alias("b"), F.col(other).isNotNull().alias("is"))
        near = self.kept.where("head is not null or prev is not null")
        return near.select(F.inline(F.array(pair("head"), pair("prev")))).where("is").groupBy("a", "b").agg(F.count("*").alias("shared"))

    def likely(self, pairs: DataFrame, name: str) -> DataFrame:
        """Of distinct candidate pairs, those that pass the suffix filter; fetches the sets of their ends."""
        shape = self.by_class.select("cid", "n", "bits", "wide")
        sketched = pairs.join(shape.toDF("a", "n_a", "bits_a", "wide_a"), "a").join(shape.toDF("b", "n_b", "bits_b", "wide_b"), "b")
        n, m = F.col("n_a"), F.col("n_b")
        differ = F.aggregate(F.zip_with("wide_a", "wide_b", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
        close = F.coalesce(differ <= most_apart(n, m), F.lit(True))  # null where a set has no wide bitmap
        found = self.scratch.save(sketched.where(near_enough("bits_a", "bits_b", n, m) & close).select(*pairs.columns), f"{name}-likely")
        wanted = found.select(F.explode(F.array("a", "b")).alias("cid")).distinct()
        keys = self.scratch.save(self.by_class.select("cid", "row.*").join(wanted, "cid"), f"{name}-keys")
        keys = bounded_broadcast(keys, keys.count())
        texts = self.rows.join(keys, same_row(self.rows, keys)).select("cid", "text").dropDuplicates(["cid"])
        self.blobs = self.scratch.save(texts.mapInArrow(_set_blobs, "cid long, set binary"), f"{name}-blobs")
        self.scratch.release()
        return found

    def verified(self, pairs: DataFrame, name: str) -> DataFrame:
        """Of likely pairs, those that link."""
        pairs = self.scratch.save(pairs.select("a", "b"), f"{name}-pairs")
        first = self.blobs.toDF("a", "set_a").join(bounded_broadcast(pairs, pairs.count()), "a")
        links = self.scratch.save(first.join(self.blobs.toDF("b", "set_b"), "b").mapInArrow(_verify, "a long, b long"), f"{name}-links")
        self.scratch.release()
        return links

    def labels(self, links: DataFrame) -> DataFrame:
        return components(self.spark, links.toDF("src", "dst"), self.scratch)

    def apart(self, pairs: DataFrame, labels: DataFrame) -> DataFrame:
        """Pairs whose ends are in different components so far."""
        n = labels.count()
        end = lambda c: bounded_broadcast(labels.toDF(c, f"c_{c}"), n)
        known = pairs.join(end("a"), "a", "left").join(end("b"), "b", "left")
        return known.where(F.coalesce("c_a", "a") != F.coalesce("c_b", "b")).select("a", "b")

    def across(self, labels: DataFrame, tried: DataFrame) -> DataFrame:
        """Pairs of classes of different components that share a prefix shingle and pass the filters."""
        own = self.kept.join(labels.withColumnRenamed("id", "cid"), "cid", "left").select("shingle", "cid", "n", "pos", F.coalesce("component", "cid").alias("c"))
        own = self.scratch.save(own, "labelled")
        mixed = self.scratch.save(own.groupBy("shingle").agg(F.min("c").alias("x"), F.max("c").alias("y")).where("x < y").select("shingle"), "mixed")
        own = self.scratch.save(own.join(mixed, "shingle").join(self.by_class.select("cid", "bits"), "cid"), "open")
        pairs = self.shared(own, F.col("a.c") != F.col("b.c"), "across")
        return self.scratch.save(pairs.join(tried.select("a", "b"), ["a", "b"], "left_anti"), "across")

    def shared(self, own: DataFrame, wanted: Column, name: str) -> DataFrame:
        """(a, b): distinct pairs of classes in posting lists ``own`` that pass all filters; no pair that links is missed.

        The smaller set of two that link (the one of the smaller class if equal) shares one of its
        ``n - needed(n, n) + 1`` rarest shingles with the larger one's prefix. So only such postings look for
        partners: a frequent shingle, which is late in the order of its sets, is looked up from few of them or
        none. Lists are cut into blocks of about ``LIST_BLOCK`` of those that look, each with all of the list.
        """
        n = F.col("n").cast("long")
        seeks = F.col("pos") < n - needed_column(n, n) + 1
        sizes = own.where(seeks).groupBy("shingle").agg(F.ceil(F.count("*") / LIST_BLOCK).cast("int").alias("blocks"))
        own = self.scratch.save(own.join(self.scratch.save(sizes, f"{name}-sizes"), "shingle"), f"{name}-lists")
        a = own.where(seeks).withColumn("part", F.pmod(F.xxhash64("cid"), "blocks").cast("int")).alias("a")
        b = own.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).alias("b")
        n, m = F.col("a.n").cast("long"), F.col("b.n").cast("long")
        order = (n < m) | ((n == m) & (F.col("a.cid") < F.col("b.cid")))
        sized = n * 100 >= m * PERCENT
        placed = F.least(n - F.col("a.pos"), m - F.col("b.pos")) >= needed_column(n, m)
        met = a.join(b, (F.col("a.shingle") == F.col("b.shingle")) & (F.col("a.part") == F.col("b.part")) & order & wanted & sized & placed & near_enough("a.bits", "b.bits", n, m))
        return met.select(F.least("a.cid", "b.cid").alias("a"), F.greatest("a.cid", "b.cid").alias("b")).distinct()

    def links(self) -> DataFrame:
        """(a, b): every pair of different classes that link, each verified once; the whole join, not only its components.

        Many near copies of one text have as many links as pairs; then the result itself grows with their square.
        """
        self.classes()
        self.postings()
        own = self.kept.select("shingle", "cid", "n", "pos").join(self.by_class.select("cid", "bits"), "cid")
        pairs = self.scratch.save(self.shared(self.scratch.save(own, "whole"), F.lit(True), "whole"), "whole-pairs")
        return self.verified(self.likely(pairs, "whole"), "whole")

    def link_counts(self) -> DataFrame:
        """(doc_id, th, n_links): to how many other rows each row links, equal texts included."""
        links = self.links()
        ends = self.scratch.save(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))), "ends")
        rows = self.scratch.save(self.sets.where("n > 0").groupBy("lo", "hi").agg(F.count("*").alias("rows")).join(self.by_class.select("cid", "lo", "hi"), ["lo", "hi"]).select("cid", "rows"), "class-rows")
        others = ends.join(rows.withColumnRenamed("cid", "b"), "b").groupBy("a").agg(F.sum("rows").alias("others"))
        counts = self.by_class.select("cid", "lo", "hi").join(rows, "cid").join(others.withColumnRenamed("a", "cid"), "cid", "left").select("lo", "hi", (F.col("rows") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"))
        return self.sets.join(self.scratch.save(counts, "counts"), ["lo", "hi"], "left").select("doc_id", "th", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))

    def run(self) -> DataFrame:
        """(doc_id, th, n_shingles, group, component_id) for each row; group numbers components, null for empty sets."""
        self.classes()
        self.postings()
        stars = self.likely(self.star_pairs(), "star")
        best = stars.select(F.inline(F.array(F.struct(F.col("a").alias("cid"), "a", "b", "shared"), F.struct(F.col("b").alias("cid"), "a", "b", "shared"))))
        best = best.groupBy("cid").agg(F.max(F.struct("shared", (-F.col("a")).alias("x"), "a", "b")).alias("best")).select("best.a", "best.b").distinct()
        best = self.scratch.save(best, "best")
        links = self.verified(best, "best")
        labels = self.labels(links)
        others = self.verified(self.apart(stars.join(best, ["a", "b"], "left_anti"), labels), "others")
        links = self.scratch.save(links.unionByName(others), "star-links")
        labels = self.labels(links)
        rest = self.across(labels, stars)
        if not rest.isEmpty():
            more = self.verified(self.likely(rest, "rest"), "rest")
            if not more.isEmpty():
                labels = self.labels(self.scratch.save(links.unionByName(more), "all-links"))
        of = self.scratch.save(labels.join(self.by_class.select(F.col("cid").alias("id"), "least_id"), "id"), "linked")
        least = self.scratch.save(of.groupBy("component").agg(F.min("least_id").alias("component_id")), "least")
        joined = self.scratch.save(of.join(bounded_broadcast(least, least.count()), "component").select(F.col("id").alias("cid"), "component", "component_id"), "joined")
        named = self.scratch.save(self.by_class.select("cid", "lo", "hi", "least_id").join(joined, "cid", "left").select("lo", "hi", F.coalesce("component", "cid").alias("group"), F.coalesce("component_id", "least_id").alias("component_id")), "named")
        return self.sets.join(named, ["lo", "hi"], "left").select("doc_id", "th", F.col("n").alias("n_shingles"), "group", F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def ngram_components(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """One row per input row: doc_id, th (a hash of its text), n_shingles, group, component_id."""
    return NgramJoin(spark, docs).run()


def one_of_each(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each component: that of the smallest id (null last). Texts without words all stay."""
    scratch = Scratch(spark, "op5")
    found = scratch.save(NgramJoin(spark, docs, scratch).run(), "found")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "th"))
    kept = found.where("group is not null").groupBy("group").agg(least.alias("row")).select("row.doc_id", "row.th")
    empty = found.where("group is null").select("doc_id", "th").distinct()
    own, of, text, one, copy = fresh(docs, "own_hash", "kept_id", "kept_hash", "kept_one", "kept_copy")
    kept = scratch.save(kept.withColumn("one", F.lit(True)).unionByName(empty.withColumn("one", F.lit(False))), "kept-rows").toDF(of, text, one)
    scratch.release()
    rows = docs.withColumn(own, F.xxhash64(text_of("text")))
    chosen = rows.join(kept, rows["doc_id"].cast("long").eqNullSafe(kept[of]) & (rows[own] == kept[text]))
    number = F.when(F.col(one), F.lit(0).cast("long")).otherwise(F.monotonically_increasing_id() + 1)
    return chosen.withColumn(copy, number).dropDuplicates([of, text, copy]).select(*docs.columns)


def op5_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_components(spark, table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


ORACLE = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), s AS (
  SELECT DISTINCT doc_id, md5(array_to_string(ws[i:i + 4], ' ')) AS g
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, 2))) AS i FROM w WHERE len(ws) > 0)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
e AS (SELECT x, y FROM c JOIN n p ON p.doc_id = x JOIN n q ON q.doc_id = y WHERE 100 * k >= 75 * (p.n + q.n - k)),
r AS (SELECT doc_id AS x, doc_id AS y FROM w UNION SELECT r.x, e.y FROM r JOIN e ON r.y = e.x)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, min(r.y)::BIGINT AS component_id
FROM w LEFT JOIN n USING (doc_id) JOIN r ON r.x = w.doc_id GROUP BY w.doc_id, n.n
"""
