"""Substring dedup: relative Lempel-Ziv factors against every indexed reference block.

A window is ``width`` consecutive words. A word is removed if a window covers it whose word sequence
starts at another place of the corpus too, in the same text or in another.

How the parse is laid out for a cluster:

* Reference blocks. Each text is cut at content-defined anchors: a window's anchor is the smallest-hash
  8-word gram in it, leftmost if equal. Consecutive windows with one anchor form a *segment*. The corpus
  sorted by (anchor, segment hash) is the reference; every range partition of it is one indexed block
  that holds all text around its anchors. Equal windows have equal anchors, so a window's only possible
  partners lie in the block of its anchor, and each text is factored against each block that could hold
  a factor of it.
* Long factors. A segment that occurs again as a whole is copied from the reference: all its windows are
  factors, without looking at any of them. Copies by the thousand cost one comparison of neighbours each.
* Factor boundaries. A segment that shares its anchor with a different one may hold part of a factor:
  there a factor ends or begins inside. One copy of each such segment is opened, its windows are matched
  by 128-bit hashes, and those found twice become factors too.

Groups are never gathered: neighbours in sort order decide, and a segment at the edge of a block counts
as undecided and is opened. A null text has no words. Rows with equal id and text are each other's copies.
Ids may be null or repeat; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm import kernel as K
from ripplegraph.llm.store import Scratch, table, text_of

WIDTH = 35
ANCHOR = 8

_RUNS = "doc_id long, th long, seed long, seg long, start int, n int"
_KINDS = "doc_id long, th long, start int, n int, whole boolean, opened boolean"
_WINDOWS = "doc_id long, th long, start int, a long, b long"


def segments(words: K.Words, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, first window, windows, anchor hash, segment hash) of each segment in a slice."""
    hashed = words.hashes()
    n = len(hashed)
    none = np.zeros(0, dtype=np.int64)
    if n < width:
        return none, none, none, none, none
    anchor = min(ANCHOR, width)
    gram = K.grams(hashed, anchor)
    bits = np.uint64((1 << n.bit_length()) - 1)
    low = K.window_min((gram & ~bits) | np.arange(len(gram), dtype=np.uint64), width - anchor + 1)
    windows = np.flatnonzero(words.doc[: n - width + 1] == words.doc[width - 1 :])
    if not len(windows):
        return none, none, none, none, none
    at = (low[windows] & bits).astype(np.int64)
    new = np.ones(len(windows), dtype=bool)
    new[1:] = (at[1:] != at[:-1]) | (windows[1:] != windows[:-1] + 1)
    head = np.flatnonzero(new)
    tail = np.append(head[1:], len(windows)) - 1
    first, last = windows[head], windows[tail]
    return words.doc[first], first, last - first + 1, K.signed(gram[at[head]]), K.signed(K.spans_hash(hashed, first, last + width, 2))


def _segment_rows(width: int):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, th = batch.column("doc_id"), batch.column("th")
            for w in K.slices(batch.column("text")):
                doc, first, n, seed, seg = segments(w, width)
                if len(doc):
                    take = pa.array(doc + w.first)
                    yield pa.RecordBatch.from_arrays(
                        [ids.take(take), th.take(take), pa.array(seed), pa.array(seg), pa.array((first - w.start[doc]).astype(np.int32)), pa.array(n.astype(np.int32))],
                        ["doc_id", "th", "seed", "seg", "start", "n"],
                    )

    return rows


def _decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of one block, sorted by anchor and segment: which segments recur whole, which must be opened.

    One row is held back between batches, so that each is judged with its neighbours.
    """
    held: pa.RecordBatch | None = None
    state = (False, False, True)  # of the held row: twin before it, other segment of its anchor before it, in the block's first anchor

    def judged(rows: pa.RecordBatch, last: bool) -> pa.RecordBatch:
        nonlocal state
        seed, seg = rows.column("seed").to_numpy(), rows.column("seg").to_numpy()
        n = len(seed)
        same_seed = seed[1:] == seed[:-1]
        same_seg = same_seed & (seg[1:] == seg[:-1])
        idx = np.arange(n)
        seed_at = np.maximum.accumulate(np.where(np.append(True, ~same_seed), idx, 0))
        seg_at = np.maximum.accumulate(np.where(np.append(True, ~same_seg), idx, 0))
        other = (seg_at > seed_at) | (state[1] & (seed_at == 0))
        edge = state[2] & (seed_at == 0)
        twin = np.append(state[0], same_seg)
        next_twin = np.append(same_seg, False)
        next_other = np.append(same_seed & ~same_seg, False)
        edge_now = edge | (last & (seed == seed[-1]))
        whole = twin | next_twin
        opened = ~next_twin & (other | next_other | edge_now)
        upto = n if last else n - 1
        state = (bool(twin[-1]), bool(other[-1]), bool(edge[-1]))
        keep = np.flatnonzero((whole | opened)[:upto])
        picked = rows.select(["doc_id", "th", "start", "n"]).take(pa.array(keep))
        return pa.RecordBatch.from_arrays([*picked.columns, pa.array(whole[keep]), pa.array(opened[keep])], ["doc_id", "th", "start", "n", "whole", "opened"])

    for batch in batches:
        if not batch.num_rows:
            continue
        rows = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
        out = judged(rows, False)
        held = rows.slice(rows.num_rows - 1)
        if out.num_rows:
            yield out
    if held is not None:
        out = judged(held, True)
        if out.num_rows:
            yield out


def _open(width: int):
    """Window hashes of the segments to open; ``todo`` holds (start, n) of a text's."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, th, todo = batch.column("doc_id"), batch.column("th"), batch.column("todo")
            todo_at = todo.offsets.to_numpy()
            flat = todo.values
            start, count = flat.field("start").to_numpy(), flat.field("n").to_numpy()
            for w in K.slices(batch.column("text")):
                a, b = K.grams(w.hashes(), width, 1), K.grams(w.hashes(1), width, 2)
                lo, hi = todo_at[w.first], todo_at[w.first + w.n_docs]
                if lo == hi:
                    continue
                doc = np.repeat(np.arange(w.n_docs), np.diff(todo_at[w.first : w.first + w.n_docs + 1]))
                n = count[lo:hi]
                step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                within = np.repeat(start[lo:hi], n) + step
                doc = np.repeat(doc, n)
                at = w.start[doc] + within
                take = pa.array(doc + w.first)
                yield pa.RecordBatch.from_arrays(
                    [ids.take(take), th.take(take), pa.array(within.astype(np.int32)), pa.array(K.signed(a[at])), pa.array(K.signed(b[at]))],
                    ["doc_id", "th", "start", "a", "b"],
                )

    return rows


def keyed(docs: DataFrame) -> DataFrame:
    """Rows are known by their id and a hash of their text: ids may repeat or be null."""
    return docs.select(F.col("doc_id").cast("long"), text_of("text").alias("text")).withColumn("th", F.xxhash64("text"))


def _same_row(left: DataFrame, right: DataFrame):
    return left["doc_id"].eqNullSafe(right["doc_id"]) & (left["th"] == right["th"])


def duplicate_factors(spark: SparkSession, docs: DataFrame, width: int = WIDTH, scratch: Scratch | None = None) -> DataFrame:
    """All duplicate windows as (doc_id, th, start, n): windows start .. start + n - 1 occur elsewhere too."""
    scratch = scratch or Scratch(spark, "op3")
    rows = keyed(docs)
    runs = scratch.save(rows.mapInArrow(_segment_rows(width), _RUNS), "segments")
    order = ["seed", "seg", "doc_id", "th", "start"]
    kinds = scratch.save(runs.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_decide, _KINDS), "kinds")
    scratch.drop("segments")
    todo = kinds.where("opened").groupBy("doc_id", "th").agg(F.collect_list(F.struct("start", "n")).alias("todo"))
    opened = rows.join(todo, _same_row(rows, todo)).select(rows["doc_id"], rows["th"], rows["text"], "todo")
    windows = scratch.save(opened.mapInArrow(_open(width), _WINDOWS).dropDuplicates(["doc_id", "th", "start", "a", "b"]), "windows")
    twice = scratch.save(windows.groupBy("a", "b").agg(F.count("*").alias("times")).where("times > 1").select("a", "b"), "twice")
    at_edges = windows.join(twice, ["a", "b"]).select("doc_id", "th", "start", F.lit(1).alias("n"))
    return kinds.where("whole").select("doc_id", "th", "start", "n").unionByName(at_edges)


def _parse(width: int):
    """The parse of each text: factors as word spans, and the digest of what is left."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = batch.column("found")
            at, flat = found.offsets.to_numpy(), found.values
            start, count = flat.field("start").to_numpy(), flat.field("n").to_numpy()
            texts = batch.column("text")
            out: dict[str, list] = {"n_words": [], "n_removed": [], "kept_sha256": [], "spans": []}
            for w in K.slices(texts):
                n_words = np.diff(w.start)
                for k in range(w.n_docs):
                    n = int(n_words[k])
                    lo, hi = at[w.first + k], at[w.first + k + 1]
                    gone = np.zeros(n + 1, dtype=np.int64)
                    np.add.at(gone, start[lo:hi], 1)
                    np.add.at(gone, np.minimum(start[lo:hi] + count[lo:hi] + width - 1, n), -1)
                    covered = np.cumsum(gone)[:n] > 0
                    kept = np.flatnonzero(~covered) + w.start[k]
                    data = w.data
                    digest = hashlib.sha256(b" ".join(data[b:e].tobytes() for b, e in zip(w.begin[kept].tolist(), w.end[kept].tolist(), strict=True)))
                    step = np.diff(np.concatenate(([0], covered.astype(np.int8), [0])))
                    out["n_words"].append(n)
                    out["n_removed"].append(int(covered.sum()))
                    out["kept_sha256"].append(digest.hexdigest())
                    out["spans"].append([{"begin": int(b), "end": int(e)} for b, e in zip(np.flatnonzero(step == 1), np.flatnonzero(step == -1), strict=True)])
            kinds = {"n_words": pa.int64(), "n_removed": pa.int64(), "kept_sha256": pa.string(), "spans": pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))}
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(v, kinds[c]) for c, v in out.items())], ["doc_id", *out])

    return rows


def substring_dedup(spark: SparkSession, docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """One row per input row: doc_id, n_words, n_removed, kept_sha256 and the removed word ``spans``."""
    rows = keyed(docs)
    found = duplicate_factors(spark, docs, width).groupBy("doc_id", "th").agg(F.collect_list(F.struct("start", "n")).alias("found"))
    empty = F.expr("cast(array() as array<struct<start:int,n:int>>)")
    joined = rows.join(found, _same_row(rows, found), "left").select(rows["doc_id"], rows["text"], F.coalesce("found", empty).alias("found"))
    return joined.mapInArrow(_parse(width), "doc_id long, n_words long, n_removed long, kept_sha256 string, spans array<struct<begin:long,end:long>>")


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(spark, table(spark, sf_dir, "documents")).select("doc_id", "n_words", "n_removed", "kept_sha256")


ORACLE = r"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), g AS (
  SELECT doc_id, unnest(range(1, len(ws) - 33)) AS i, ws FROM w WHERE len(ws) >= 35
), h AS (SELECT doc_id, i, md5(array_to_string(ws[i:i + 34], ' ')) AS k FROM g),
d AS (SELECT k FROM h GROUP BY k HAVING count(*) > 1),
m AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS p FROM h SEMI JOIN d USING (k)),
r AS (SELECT doc_id, list(p) AS gone FROM m GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(len(gone), 0) AS BIGINT) AS n_removed,
  sha256(array_to_string(CASE WHEN gone IS NULL THEN ws ELSE list_transform(list_filter(list_zip(ws, range(1, len(ws) + 1)), lambda z: NOT list_contains(gone, z[2])), lambda z: z[1]) END, ' ')) AS kept_sha256
FROM w LEFT JOIN r USING (doc_id)
"""
