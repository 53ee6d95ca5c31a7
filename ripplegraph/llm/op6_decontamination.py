"""Benchmark decontamination: SimHash over item-sized windows, multi-index Hamming blocks, exact check.

A text leaks an item if some window of as many words as the item has a weighted shingle similarity of
``SIMILARITY`` or more with it: five-word shingles, weighted by how often they occur, sum of minima over
sum of maxima. Words are runs of letters and digits, lower-cased; an item of fewer than five words is one
shingle as a whole, an item without words leaks nowhere. A text of fewer words than the item is one window.

1. Windows. A window can only reach that similarity if it holds a shingle of the item, so windows of an item
   length are placed wherever a shingle of any item of that length occurs, each window once. A text and an item
   length make one *run*: the shingle hashes of the region that its windows cover, kept once for all of them.
2. Fingerprints. Each window and each item gets a 64-bit SimHash of its weighted shingles: sums of bits in
   32-bit lanes, two to a number, compared with half of the shingles.
3. Multi-index. Fingerprints are cut into ``len(BLOCKS)`` blocks; items are indexed by length under every block
   value with at most one bit turned. Any two fingerprints within ``RADIUS`` = 2 * blocks - 1 bits share an
   entry, by the pigeonhole principle. Windows meet items by equality of entries and in no other way, then the
   whole distance is checked.
4. The exact similarity decides.

At similarity 0.75 the expected distance is 11 bits with a deviation of 3, so the radius of 23 loses one
window in tens of thousands at the very threshold and none in practice above it.

Memory follows runs, which are as long as the text's part that items cover. The time for an item of L words
that is quoted whole still grows with L * L, as it has about L windows of L shingles.

Benchmarks whose shingles exceed the broadcast bound are joined by shuffle. Rows are known by id and text:
ids may be null or repeat. Null and empty texts leak nothing. Native SQL throughout.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm.store import Scratch, bounded_broadcast, keyed, table, text_of

SHINGLE = 5
PERCENT = 75
#: Widths of the blocks of a fingerprint: 64 bits in 12 blocks.
BLOCKS = (6, 6, 6, 6, 5, 5, 5, 5, 5, 5, 5, 5)
RADIUS = 2 * len(BLOCKS) - 1


def normal_words(text: Column) -> Column:
    trimmed = F.regexp_replace(F.lower(text), r"^[^\p{L}\p{N}]+", "")
    return F.split(trimmed, r"[^\p{L}\p{N}]+")


def _shingles(words: str, start: Column, count: Column, size: Column) -> Column:
    """Hashes of ``count`` shingles from word ``start`` on; ``size`` words each, five or fewer."""
    word = lambda i: F.get(words, i.cast("int"))

    def one(t: Column) -> Column:
        at = start + t
        return F.when(size == SHINGLE, F.xxhash64(*(word(at + k) for k in range(SHINGLE)))).otherwise(F.xxhash64(F.array_join(F.slice(words, (at + 1).cast("int"), size), " ")))

    return F.transform(F.sequence(F.lit(0), count - 1), one)


def _lane(hashed: Column, lane: int) -> Column:
    """Bits 2 * lane and 2 * lane + 1 of a hash, each in 32 bits of its own."""
    bit = lambda k: F.shiftleft(F.shiftrightunsigned(hashed, 2 * lane + k).bitwiseAND(F.lit(1).cast("long")), 32 * k)
    return bit(0).bitwiseOR(bit(1))


def _fingerprint(lanes: list[str], total: Column) -> Column:
    """The bits set in more than half of the shingles."""
    out = F.lit(0).cast("long")
    for lane, name in enumerate(lanes):
        for k in range(2):
            held = F.shiftrightunsigned(F.col(name), 32 * k).bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
            out = out.bitwiseOR(F.when(held * 2 > total, F.shiftleft(F.lit(1).cast("long"), 2 * lane + k)).otherwise(F.lit(0).cast("long")))
    return out


def simhash(frame: DataFrame, keys: list[str], shingles: str) -> DataFrame:
    """(keys, fingerprint) of the array column ``shingles``; keys tell the rows apart."""
    lanes = [f"lane{i}" for i in range(32)]
    spread = frame.select(*keys, F.explode(shingles).alias("h"))
    summed = spread.groupBy(*keys).agg(F.count("*").alias("total"), *(F.sum(_lane(F.col("h"), i)).alias(c) for i, c in enumerate(lanes)))
    return summed.select(*keys, _fingerprint(lanes, F.col("total")).alias("fingerprint"))


def blocks_of(fingerprint: Column, turned: bool) -> Column:
    """Entries (block, value); with ``turned``, also all values one bit away."""
    entries, at = [], 0
    for block, width in enumerate(BLOCKS):
        value = F.shiftrightunsigned(fingerprint, at).bitwiseAND(F.lit((1 << width) - 1).cast("long")).cast("int")
        for flip in [0, *(1 << k for k in range(width))] if turned else [0]:
            entries.append(F.struct(F.lit(block).alias("block"), value.bitwiseXOR(F.lit(flip)).alias("value")))
        at += width
    return F.array(*entries)


def numbered(shingles: str) -> Column:
    """Shingles told apart by which occurrence they are, so that sets of them intersect like weighted ones."""
    col = F.col(shingles)
    several = F.transform(col, lambda x, i: F.xxhash64(x, F.size(F.filter(F.slice(col, F.lit(1), i), lambda y: y == x))))
    return F.when(F.size(F.array_distinct(col)) == F.size(col), F.transform(col, lambda x: F.xxhash64(x, F.lit(0)))).otherwise(several)


def item_table(benchmark: DataFrame) -> DataFrame:
    """(item_id, length, size, count, shingles) of items with words; equal ids are separate items of one name."""
    words = benchmark.select(F.col("item_id").cast("long"), normal_words(text_of("text")).alias("w")).select("item_id", F.filter("w", lambda x: x != "").alias("w"))
    sized = words.where(F.size("w") > 0).withColumn("length", F.size("w")).withColumn("size", F.least(F.lit(SHINGLE), F.size("w")))
    counted = sized.withColumn("count", F.col("length") - F.col("size") + 1)
    return counted.withColumn("shingles", _shingles("w", F.lit(0), F.col("count"), F.col("size"))).drop("w").withColumn("item", F.xxhash64("item_id", "shingles")).dropDuplicates(["item"])


RUN = ["doc_id", "th", "length"]


def runs(rows: DataFrame, anchors: DataFrame, n_anchors: int, sizes: list[int]) -> DataFrame:
    """(doc_id, th, length, size, held, lo, hashes, starts): the windows of an item length in a text.

    ``hashes`` are the shingles from word ``lo`` on, ``starts`` the windows' first words, ``held`` their shingles.
    """
    places = rows.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
    word = lambda k: F.get("words", F.col("i") + k)
    met = None
    for size in sizes:
        hashed = F.xxhash64(*(word(k) for k in range(SHINGLE))) if size == SHINGLE else F.xxhash64(F.array_join(F.slice("words", F.col("i") + 1, F.lit(size)), " "))
        here = places.where(F.col("i") + size <= F.col("n")).withColumn("h", hashed)
        one = here.join(bounded_broadcast(anchors.where(F.col("size") == size), n_anchors), "h").select(*RUN, "size", "i", "n", "words")
        met = one if met is None else met.unionByName(one)
    found = met.groupBy(*RUN, "size").agg(F.array_sort(F.collect_set("i")).alias("at"), F.first("n").alias("n"), F.first("words").alias("words"))
    count = F.col("length") - F.col("size") + 1
    lowest = lambda i: F.greatest(i - count + 1, F.lit(0))
    last = lambda i: F.when(F.col("n") < F.col("length"), F.lit(0)).otherwise(F.least(i, F.col("n") - F.col("length")))  # noqa: E731  (a shorter text is one window)
    empty = F.array().cast("array<int>")

    def new(i: Column, k: Column) -> Column:
        """Windows that hold the shingle at ``i`` and none of the places before it."""
        first = F.greatest(lowest(i), F.coalesce(F.get("at", k - 1) + 1, F.lit(0)))
        return F.when(first <= last(i), F.sequence(first, last(i))).otherwise(empty)

    region = found.withColumn("lo", lowest(F.get("at", 0))).withColumn("hi", F.least(F.col("n"), F.get("at", F.size("at") - 1) + F.col("length")))
    held = F.least(count, F.col("n") - F.col("size") + 1)
    return region.select(*RUN, "size", held.alias("held"), "lo", _shingles("words", F.col("lo"), F.col("hi") - F.col("lo") - F.col("size") + 1, F.col("size")).alias("hashes"), F.flatten(F.transform("at", new)).alias("starts")).where(F.size("starts") > 0)


def _window(begin: str = "begin") -> Column:
    return F.slice("hashes", F.col(begin) - F.col("lo") + 1, F.col("held"))


def leaks(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """One row per text and leaked item: doc_id, th, item_id, begin (word), similarity; the best window, first if equal."""
    scratch = scratch or Scratch(spark, "op6")
    items = scratch.save(item_table(benchmark), "items")
    n_items = items.count()
    if not n_items:
        return spark.createDataFrame([], "doc_id long, th long, item_id long, begin int, similarity double")
    anchors = scratch.save(items.select("length", "size", F.explode("shingles").alias("h")).distinct(), "anchors")
    sizes = sorted(r[0] for r in items.select("size").distinct().collect())  # five numbers at most

    rows = keyed(docs).withColumn("words", normal_words(F.col("text"))).drop("text")
    rows = rows.withColumn("n", F.size("words") - F.when(F.element_at("words", -1) == "", 1).otherwise(0)).where("n > 0")
    found = scratch.save(runs(rows, anchors, anchors.count(), sizes), "runs")

    keys = [*RUN, "begin"]
    spread = found.withColumn("begin", F.explode("starts")).select(*keys, _window().alias("shingles"))
    prints = scratch.save(simhash(spread, keys, "shingles"), "prints")
    entries = simhash(items, ["item", "length"], "shingles").select("item", "length", F.col("fingerprint").alias("of_item"), F.inline(blocks_of(F.col("fingerprint"), True)))
    index = scratch.save(entries, "index")
    looked = prints.select(*keys, "fingerprint", F.inline(blocks_of(F.col("fingerprint"), False)))
    near = F.bit_count(F.col("fingerprint").bitwiseXOR(F.col("of_item"))) <= RADIUS
    close = looked.join(bounded_broadcast(index, index.count()), ["length", "block", "value"]).where(near).select(*keys, "item").distinct()
    close = scratch.save(close.groupBy(*RUN).agg(F.collect_list(F.struct("begin", "item")).alias("near")), "close")
    likely = found.drop("starts").join(close.toDF("_doc", "_th", "_length", "near"), F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("th") == F.col("_th")) & (F.col("length") == F.col("_length")))
    likely = likely.withColumn("near", F.explode("near")).select("doc_id", "th", F.col("near.begin").alias("begin"), F.col("near.item").alias("item"), "hashes", "lo", "held").withColumn("shingles", _window()).withColumn("own", numbered("shingles"))
    against = scratch.save(items.select("item", "item_id", "count", numbered("shingles").alias("others")), "against")
    verified = likely.select("doc_id", "th", "begin", "item", "own").join(bounded_broadcast(against, n_items), "item").withColumn("both", F.size(F.array_intersect("own", "others")))
    union = F.size("own") + F.col("count") - F.col("both")
    verified = verified.where(F.col("both") * 100 >= union * PERCENT)
    scored = verified.select("doc_id", "th", "item_id", "begin", (F.col("both") / union).alias("similarity"))
    best = scored.groupBy("doc_id", "th", "item_id").agg(F.max(F.struct("similarity", (-F.col("begin")).alias("at"))).alias("best"))
    return best.select("doc_id", "th", "item_id", (-F.col("best.at")).alias("begin"), F.col("best.similarity").alias("similarity"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = leaks(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "item_id", F.col("begin").cast("long").alias("begin"), F.round("similarity", 6).alias("similarity"))


ORACLE = r"""
WITH it AS (
  SELECT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark
), i AS (SELECT item_id, w, len(w) AS l, least(5, len(w)) AS k FROM it WHERE len(w) > 0),
d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM documents),
ish AS (SELECT item_id, l, k, array_to_string(w[p:p + k - 1], ' ') AS g FROM (SELECT *, unnest(range(1, l - k + 2)) AS p FROM i)),
ic AS (SELECT item_id, l, k, g, count(*) AS c FROM ish GROUP BY ALL),
dsh AS (
  SELECT doc_id, p, s.k, array_to_string(w[p:p + s.k - 1], ' ') AS g
  FROM (SELECT *, unnest(range(1, len(w) + 1)) AS p FROM d), (SELECT DISTINCT k FROM i) s WHERE p + s.k - 1 <= len(w)
), hit AS (SELECT doc_id, item_id, l, ic.k, p FROM dsh JOIN ic ON dsh.g = ic.g AND dsh.k = ic.k),
win AS (
  SELECT DISTINCT doc_id, item_id, l, k, b
  FROM (SELECT doc_id, item_id, l, k, unnest(range(greatest(p - (l - k), 1), p + 1)) AS b FROM hit) JOIN d USING (doc_id) WHERE b + l - 1 <= len(w)
), wc AS (SELECT win.doc_id, win.item_id, win.l, win.k, b, g, count(*) AS c FROM win JOIN dsh ON dsh.doc_id = win.doc_id AND dsh.k = win.k AND dsh.p BETWEEN b AND b + win.l - win.k GROUP BY ALL),
sim AS (SELECT wc.doc_id, wc.item_id, wc.b, wc.l - wc.k + 1 AS m, sum(least(wc.c, ic.c)) AS shared FROM wc JOIN ic ON ic.item_id = wc.item_id AND ic.g = wc.g GROUP BY ALL),
ok AS (SELECT *, shared / (2 * m - shared) AS s FROM sim WHERE 100 * shared >= 75 * (2 * m - shared))
SELECT doc_id, item_id, (arg_max(b, (s, -b)) - 1)::BIGINT AS "begin", round(max(s), 6) AS similarity FROM ok GROUP BY doc_id, item_id
"""
