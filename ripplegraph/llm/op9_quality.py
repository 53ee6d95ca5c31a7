"""Quality rules: counts per text, then a hashed n-gram log-likelihood ratio with a threshold from held labels.

Unigrams and bigrams of words are hashed into ``BUCKETS`` buckets. The raw multinomial counts every text;
the trusted one counts every text that is labelled good. A text's score is the mean of log(trusted / raw) over its n-grams. Ratios are rounded to
2**-20 and summed as integers, so the order of rows cannot move a score, and each text gets a verdict.

The threshold is fitted too, on all labels that the trusted counts never see: those with crc32(doc_id as text)
mod 5 = 0. Of all cuts between their scores it is the middle of the
widest one that makes the fewest mistakes, each class weighing alike. Without labels of both classes it is 0.

A text is kept if no base rule fails it and its score is at least the threshold. Null and empty texts have
no words, fail the base rule and score 0. Ids may be null or repeat; rows are judged by themselves; extra
columns are ignored. Native SQL throughout. Judging shuffles nothing: the ratios reach every task as one
array of ``BUCKETS`` numbers, and a row's measures come from one expression that binds its words once.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm.store import BROADCAST_ROWS, SEPARATORS, Scratch, table, text_of
from ripplegraph.plans.ordered import ordered

BUCKETS = 1 << 16
#: Ids of one bitmap, as SQL builds them.
SPAN = 1 << 15
UNIT = 1 << 20
SYMBOLS = r"[#*$%&|<>]"
_SEPARATING = " \t\n\x0b\f\r"


def _long(value: int) -> Column:
    return F.lit(value).cast("long")


def _bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is worked out once: no rewrite of the plan can copy it into the places that read it."""
    return F.get(F.transform(F.array(value), use), 0)


def _words(text: Column) -> Column:
    """Words of a text that is not null; one empty word if it has none."""
    return F.split(F.btrim(text, F.lit(_SEPARATING)), SEPARATORS)


def _n_words(words: Column) -> Column:
    return F.when(F.get(words, 0) == "", F.lit(0)).otherwise(F.size(words))


def _covered(places: Column) -> Column:
    """Words under 3-word windows that start at ``places``, which rise."""
    start = F.struct(_long(-3).alias("last"), _long(0).alias("covered"))
    onward = lambda s, p: F.struct(p.alias("last"), (s["covered"] + F.least(_long(3), p - s["last"])).alias("covered"))
    return F.aggregate(places, start, onward, lambda s: s["covered"])


def repeated_words(words: Column, n: Column, hash_bits: int = 64) -> Column:
    """Words in 3-word windows that occur twice or more in their text; an exact count.

    Each window becomes one number, its hash above and its place below; sorted, windows with equal hashes are
    neighbours. If the words of all such neighbours are equal, the count is theirs. If a pair differs, which takes
    a collision of hashes, windows are sorted with their words instead. ``hash_bits`` is for tests of that case.
    """
    window = lambda i: (F.get(words, i), F.get(words, i + 1), F.get(words, i + 2))
    starts = F.sequence(F.lit(0), n - 3)
    hashed = lambda i: F.xxhash64(*window(i)).bitwiseAND(_long(-(1 << (64 - hash_bits))))
    shifted = lambda how, x, b: F.call_function(how, x, b)

    def by_hash(packed: Column, bits: Column) -> Column:
        place = lambda k: F.get(packed, k).bitwiseAND(shifted("shiftleft", _long(1), bits) - 1)
        start = lambda k: F.struct(*window(place(k).cast("int")))
        equal = F.filter(F.sequence(F.lit(0), n - 4), lambda k: shifted("shiftrightunsigned", F.get(packed, k).bitwiseXOR(F.get(packed, k + 1)), bits) == 0)
        return F.when(n == 3, _long(0)).otherwise(_bound(equal, lambda e: F.when(F.size(e) == 0, _long(0)).when(F.exists(e, lambda k: start(k) != start(k + 1)), by_words()).otherwise(
            _covered(F.sort_array(F.flatten(F.transform(e, lambda k: F.array(place(k), place(k + 1))))))
        )))

    def by_words() -> Column:
        entry = lambda i: F.struct(F.xxhash64(*window(i)).alias("h"), *(w.alias(f"w{j}") for j, w in enumerate(window(i))), i.alias("i"))
        key = lambda x: F.struct(*(x[c] for c in ("h", "w0", "w1", "w2")))
        place = lambda x: x["i"].cast("long")

        def places(entries: Column) -> Column:
            equal = F.filter(F.sequence(F.lit(0), n - 4), lambda k: key(F.get(entries, k)) == key(F.get(entries, k + 1)))
            return _covered(F.sort_array(F.flatten(F.transform(equal, lambda k: F.array(place(F.get(entries, k)), place(F.get(entries, k + 1)))))))

        return _bound(F.sort_array(F.transform(starts, entry)), places)

    pack = lambda b: F.sort_array(F.transform(starts, lambda i: shifted("shiftleft", hashed(i), b).bitwiseOR(i.cast("long"))))
    return F.when(n < 3, _long(0)).otherwise(_bound(F.length(F.bin(n.cast("long"))), lambda b: _bound(pack(b), lambda packed: by_hash(packed, b))))


def _bucket(*words: Column) -> Column:
    return F.pmod(F.xxhash64(*words), F.lit(BUCKETS)).cast("int")


def _ratio_sum(words: Column, n: Column, ratios: Column) -> Column:
    """Sum of the ratios of all unigrams and bigrams of a text."""
    two = lambda w, i: F.when(i + 1 < n, F.get(ratios, _bucket(w, F.get(words, i + 1)))).otherwise(_long(0))
    each = F.transform(words, lambda w, i: F.get(ratios, _bucket(w)) + two(w, i))
    return F.when(n == 0, _long(0)).otherwise(F.aggregate(each, _long(0), lambda a, x: a + x))


def _score(total: Column, n: Column) -> Column:
    return total.cast("double") / (F.greatest(n.cast("long") * 2 - 1, _long(1)) * _long(UNIT)).cast("double")


def base_counts(docs: DataFrame, by_bucket: DataFrame | None = None, *more: str) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed) of every row, the score if ratios are given, and ``more`` columns.

    The ratios are a scalar subquery, read once for all rows.
    """
    text = text_of("text")
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))

    def of_words(ws: Column, n: Column, r: Column | None) -> Column:
        counts = [n.cast("long").alias("n_words"), F.aggregate(ws, _long(0), lambda a, w: a + F.length(w)).alias("word_chars"), repeated_words(ws, n).alias("n_repeat_words")]
        return F.struct(*counts, *([_score(_ratio_sum(ws, n, r), n).alias("score")] if r is not None else []))

    measures = lambda r: _bound(_words(text), lambda ws: _bound(_n_words(ws), lambda n: of_words(ws, n, r)))
    symbols = (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).cast("long")
    duplicates = _bound(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long")
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *more)
    if by_bucket is not None:
        own = own.withColumn("ratios", by_bucket.scalar())
    rows = own.select("doc_id", *more, (measures(None) if by_bucket is None else _bound(F.col("ratios"), measures)).alias("m"), symbols.alias("n_symbols"), duplicates.alias("n_dup_lines"))
    failed = (F.col("m.n_words") < 50) | (F.col("m.n_repeat_words") * 100 > F.col("m.n_words") * 50)
    return rows.select("doc_id", "m.n_words", "m.word_chars", "n_symbols", "n_dup_lines", "m.n_repeat_words", failed.alias("base_failed"), *([] if by_bucket is None else ["m.score"]), *more)


def labelled(labels: DataFrame, scratch: Scratch) -> DataFrame:
    """(doc_id, quality): every labelled id once."""
    known = labels.where("quality is not null and doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("quality"))
    return scratch.save(known, "labelled")


def marked(docs: DataFrame, known: DataFrame, scratch: Scratch) -> DataFrame:
    """(doc_id, text, quality, fitting) of every row; quality is 1, 0 or null, ``fitting`` says that the label is for the threshold.

    Labels reach the tasks as bitmaps of ``SPAN`` ids each, so texts are not shuffled; where ids are so sparse that
    there would be too many bitmaps, rows and labels are joined by id.
    """
    doc = F.col("doc_id")
    span, place = F.floor(doc / SPAN), F.pmod(doc, F.lit(SPAN))
    own = docs.select(doc.cast("long").alias("doc_id"), "text")
    bits = [F.expr(f"bitmap_construct_agg(place) FILTER (WHERE quality = {q})").alias(f"q{q}") for q in (1, 0)]
    maps = scratch.save(known.select(span.alias("span"), place.alias("place"), "quality").groupBy("span").agg(*bits), "bitmaps")
    n = maps.count()
    if n <= BROADCAST_ROWS // 16:  # 8 kB each
        has = lambda c: F.getbit(F.conv(F.hex(F.substring(F.col(c), F.shiftright(place, 3).cast("int") + 1, F.lit(1))), 16, 10).cast("int"), place.bitwiseAND(_long(7)).cast("int")) == 1
        rows = own.withColumn("span", span).join(F.broadcast(maps), "span", "left").select("doc_id", "text", F.when(has("q1"), 1).when(has("q0"), 0).alias("quality"))
    else:
        rows = own.join(known.select("doc_id", F.expr("if(quality in (0, 1), quality, null)").alias("quality")), "doc_id", "left").select("doc_id", "text", "quality")
    return rows.withColumn("fitting", F.col("quality").isNotNull() & (F.pmod(F.crc32(doc.cast("string")), F.lit(5)) == 0))


def ratios(docs: DataFrame, scratch: Scratch) -> DataFrame:
    """(ratios): one row, the rounded log ratios of the two multinomials of ``marked`` rows by bucket, smoothed by one count a bucket."""
    trusted = F.expr("if(quality = 1 and not fitting, 1, null)").alias("trusted")
    rows = docs.select(trusted, _words(text_of("text")).alias("words")).select("trusted", "words", F.posexplode("words").alias("i", "one")).where("one <> ''")
    two = F.get("words", F.col("i") + 1)
    grams = rows.select("trusted", F.explode(F.array(_bucket(F.col("one")), F.when(two.isNotNull(), _bucket(F.col("one"), two)))).alias("bucket")).where("bucket is not null")
    counts = scratch.save(grams.groupBy("bucket").agg(F.count("*").alias("raw"), F.count("trusted").alias("good")), "counts")
    total = counts.agg(F.coalesce(F.sum("raw"), _long(0)).alias("all_raw"), F.coalesce(F.sum("good"), _long(0)).alias("all_good"))
    count = lambda c: F.coalesce(F.col(c), _long(0)) + 1
    ratio = F.log((count("good") / (F.col("all_good") + BUCKETS)) / (count("raw") / (F.col("all_raw") + BUCKETS)))
    dense = docs.sparkSession.range(BUCKETS, numPartitions=1).select(F.col("id").cast("int").alias("bucket")).join(counts, "bucket", "left")
    rows = dense.crossJoin(F.broadcast(total)).select("bucket", F.round(ratio * UNIT).cast("long").alias("ratio"))
    return scratch.save(rows.agg(F.transform(F.array_sort(F.collect_list(F.struct("bucket", "ratio"))), lambda x: x["ratio"]).alias("ratios")), "ratios")


def fitted_threshold(docs: DataFrame, by_bucket: DataFrame, scratch: Scratch) -> float:
    """The cut between scores of held labels with the fewest mistakes; 0 without labels of both classes."""
    rows = scratch.save(docs.where("fitting").select("doc_id", "text", "quality"), "held")
    judged = scratch.save(base_counts(rows, by_bucket, "quality"), "judged").where("not base_failed")
    scores = judged.groupBy("score").agg(F.sum("quality").cast("long").alias("good"), F.sum(1 - F.col("quality")).cast("long").alias("bad"))
    placed = scratch.save(ordered(scores, ["score"], scratch, {"kept": F.col("good"), "left": F.col("bad")}), "places")
    total = placed.agg(F.sum("good").alias("good"), F.sum("bad").alias("bad")).first()
    if not total["good"] or not total["bad"]:
        return 0.0
    before = placed.select((F.col("place") + 1).alias("place"), F.col("score").alias("last"), "kept", "left")
    mistakes = F.col("kept") / total["good"] + (1 - F.col("left") / total["bad"])
    cuts = placed.select("place", "score").join(before, "place").select("score", "last", mistakes.alias("mistakes"))
    best = cuts.orderBy("mistakes", (F.col("last") - F.col("score")), "score").first()
    return (best["score"] + best["last"]) / 2 if best else 0.0


def quality(spark: SparkSession, docs: DataFrame, labels: DataFrame, threshold: float | None = None) -> DataFrame:
    """One row per input row: doc_id, counts, base_failed, kept and the score; ``threshold`` None: fitted."""
    scratch = Scratch(spark, "op9")
    known = marked(docs, labelled(labels, scratch), scratch)
    by_bucket = ratios(known, scratch)
    cut = fitted_threshold(known, by_bucket, scratch) if threshold is None else threshold
    judged = base_counts(docs, by_bucket)
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & (F.col("score") >= cut)).alias("kept"), "score")


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def quality_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts alone, which SQL can check."""
    return base_counts(table(spark, sf_dir, "documents"))


BASE_ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
ws AS (SELECT r, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS words FROM d),
place AS (SELECT r, unnest(words) AS a, generate_subscripts(words, 1) AS i FROM ws),
tri AS (SELECT r, i, a, lead(a, 1) OVER o AS b, lead(a, 2) OVER o AS c FROM place WINDOW o AS (PARTITION BY r ORDER BY i)),
twice AS (SELECT r, a, b, c FROM tri WHERE c IS NOT NULL GROUP BY r, a, b, c HAVING count(*) > 1),
covered AS (SELECT r, count(DISTINCT i + k) AS n FROM (SELECT tri.r, tri.i, unnest([0, 1, 2]) AS k FROM tri JOIN twice USING (r, a, b, c)) GROUP BY r),
counted AS (
  SELECT d.doc_id, len(words)::BIGINT AS n_words, coalesce(list_sum(list_transform(words, lambda w: length(w))), 0)::BIGINT AS word_chars,
    (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines, coalesce(n, 0)::BIGINT AS n_repeat_words
  FROM d JOIN ws USING (r) LEFT JOIN covered USING (r))
SELECT doc_id, n_words, word_chars, n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, n_repeat_words,
  (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed
FROM counted
"""
