"""Graphs: generated ones with known structure, and graphs drawn from the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ripplegraph.operators.components import components
from ripplegraph.operators.graph import symmetrize
from ripplegraph.operators.neighbours import VectorIndex, exact_nearest, searched_nearest, unit_vectors
from ripplegraph.operators.words import block_pairs, links_between
from ripplegraph.plans.ordered import ordered
from ripplegraph.plans.scratch import Scratch, bounded_broadcast
from ripplegraph.sources.tables import table

#: The 78 friendships of a karate club, members 1 to 34 (public data).
KARATE = (
    "1-2 1-3 1-4 1-5 1-6 1-7 1-8 1-9 1-11 1-12 1-13 1-14 1-18 1-20 1-22 1-32 2-3 2-4 2-8 2-14 2-18 2-20 2-22 2-31 "
    "3-4 3-8 3-9 3-10 3-14 3-28 3-29 3-33 4-8 4-13 4-14 5-7 5-11 6-7 6-11 6-17 7-17 9-31 9-33 9-34 10-34 14-34 "
    "15-33 15-34 16-33 16-34 19-33 19-34 20-34 21-33 21-34 23-33 23-34 24-26 24-28 24-30 24-33 24-34 25-26 25-28 "
    "25-32 26-32 27-30 27-34 28-34 29-32 29-34 30-33 30-34 31-33 31-34 32-33 32-34 33-34"
)


def line(spark: SparkSession, n: int = 200, weak_at: int = 100, weak: float = 0.1) -> DataFrame:
    """Nodes 1..n in a row, one weak link between ``weak_at`` and the next."""
    links = spark.range(1, n).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.when(F.col("id") == weak_at, weak).otherwise(1.0).alias("w"))
    return symmetrize(links)


def row(values: DataFrame, weak_at: int = 0, weak: float = 1.0) -> DataFrame:
    """The distinct values of one column in a row, as nodes 1..n in their order; one weak link after ``weak_at``."""
    (name,) = values.columns
    scratch = Scratch(values.sparkSession, "row")
    placed = scratch.save(ordered(values.where(F.col(name).isNotNull()).distinct(), [name], scratch).select((F.col("place") + 1).cast("long").alias("src")))
    links = placed.where(F.col("src") < placed.count()).select("src", (F.col("src") + 1).alias("dst"), F.when(F.col("src") == weak_at, weak).otherwise(1.0).alias("w"))
    return symmetrize(links)


def ring(spark: SparkSession, n: int) -> DataFrame:
    return symmetrize(spark.range(n).select(F.col("id").alias("src"), F.pmod(F.col("id") + 1, F.lit(n)).alias("dst"), F.lit(1.0).alias("w")))


def karate(spark: SparkSession) -> DataFrame:
    return symmetrize(spark.createDataFrame([(*map(int, x.split("-")), 1.0) for x in KARATE.split()], "src long, dst long, w double"))


def planted(spark: SparkSession, sizes: tuple[int, int] = (680, 320), links: int = 99_084, mixed: float = 0.1, seed: int = 1) -> DataFrame:
    """Two planted groups, ids from 0; exactly ``links`` links, the share ``mixed`` of them between the groups.

    Pairs are ranked by a seeded hash within their kind, so the draw is reproducible and exact.
    """
    n = sum(sizes)
    a, b = spark.range(n).toDF("src"), F.broadcast(spark.range(n).toDF("dst"))  # n is a parameter, not data
    pairs = a.join(b, F.col("src") < F.col("dst")).withColumn("across", (F.col("src") < sizes[0]) != (F.col("dst") < sizes[0]))
    place = F.row_number().over(Window.partitionBy("across").orderBy(F.xxhash64("src", "dst", F.lit(seed)), "src", "dst"))
    between = round(links * mixed)
    kept = pairs.withColumn("place", place).where(F.col("place") <= F.when(F.col("across"), between).otherwise(links - between))
    return symmetrize(kept.select("src", "dst", F.lit(1.0).alias("w")))


def building(spark: SparkSession, walls: str = "quadrants", pitch: float = 7.0, radius: float = 10.0, vertical: float = 0.02, horizontal: float = 0.06, rooms: DataFrame | None = None) -> DataFrame:
    """Two floors of 8 x 8 rooms (all of them, or those of ``rooms(id)``), linked within ``radius``; floors meet at four stairs only; walls of the upper floor weaken links.

    ``walls='equal'`` gives both walls the vertical one's factor: then two eigenvalues coincide. Links are found
    through grid cells, not by comparing all rooms.
    """
    cell = F.col("id") % 64
    rooms = (spark.range(128) if rooms is None else rooms).select("id", F.floor(F.col("id") / 64).alias("floor"), (cell % 8).alias("gx"), F.floor(cell / 8).alias("gy"))
    around = rooms.withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(8)))).select("id", "floor", "gx", "gy", (F.col("gx") + F.col("step") % 3 - 1).alias("nx"), (F.col("gy") + F.floor(F.col("step") / 3) - 1).alias("ny"))
    other = rooms.select(F.col("id").alias("dst"), F.col("floor").alias("floor2"), F.col("gx").alias("nx"), F.col("gy").alias("ny"))
    near = around.join(other, ["nx", "ny"])
    distance = pitch * F.sqrt((F.col("gx") - F.col("nx")) ** 2 + (F.col("gy") - F.col("ny")) ** 2)
    flat = near.where((F.col("floor") == F.col("floor2")) & (F.col("id") < F.col("dst")) & (distance < radius))
    right = horizontal if walls == "quadrants" else vertical
    crosses_x = (F.col("gx") < 4) != (F.col("nx") < 4)
    crosses_y = (F.col("gy") < 4) != (F.col("ny") < 4)
    upper = F.when(F.col("floor") == 1, F.when(crosses_x, vertical).otherwise(1.0) * F.when(crosses_y, right).otherwise(1.0)).otherwise(F.lit(1.0))
    stairs = near.where((F.col("floor") == 0) & (F.col("floor2") == 1) & (F.col("gx") == F.col("nx")) & (F.col("gy") == F.col("ny")) & F.col("gx").isin(1, 6) & F.col("gy").isin(1, 6))
    return symmetrize(flat.select(F.col("id").alias("src"), "dst", upper.alias("w")).unionByName(stairs.select(F.col("id").alias("src"), "dst", F.lit(1.0).alias("w"))))


def customer_rooms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id): the rooms 0..127 that customers fall into by their keys."""
    rooms = table(spark, sf_dir, "customer").where("c_custkey is not null").select(F.pmod("c_custkey", F.lit(128)).cast("long").alias("id"))
    return rooms.distinct()


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nations by lines sold between them, both directions together."""
    t = lambda name: table(spark, sf_dir, name)
    buyers = t("orders").select("o_orderkey", "o_custkey").join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    sold = t("lineitem").select("l_orderkey", "l_suppkey").join(t("supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    pairs = sold.join(buyers, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("c_nationkey", "s_nationkey").agg(F.count("*").alias("w"))
    return symmetrize(pairs.select(F.col("c_nationkey").alias("src"), F.col("s_nationkey").alias("dst"), "w"))


def by_region(spark: SparkSession, sf_dir: str, edges: DataFrame, weighting: str = "chain") -> DataFrame:
    """Trade weakened between regions: a chain of regions, or all pairs alike (close eigenvalues)."""
    nation = table(spark, sf_dir, "nation")
    own = F.broadcast(nation.select(F.col("n_nationkey").cast("long").alias("src"), F.col("n_regionkey").alias("ra")))  # 25 nations
    other = F.broadcast(nation.select(F.col("n_nationkey").cast("long").alias("dst"), F.col("n_regionkey").alias("rb")))
    apart = F.abs(F.col("ra") - F.col("rb"))
    factor = F.when(apart == 0, 1.0).when(apart == 1, 0.05).otherwise(0.001) if weighting == "chain" else F.when(apart == 0, 1.0).otherwise(0.02)
    return edges.join(own, "src").join(other, "dst").select("src", "dst", (F.col("w") * factor).alias("w"))


def region_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return by_region(spark, sf_dir, trade(spark, sf_dir))


def region_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    return by_region(spark, sf_dir, trade(spark, sf_dir), "alike")


def copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts by the number of orders that hold both."""
    own = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = own.toDF("o", "src").join(own.toDF("o", "dst"), "o").where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("w"))
    return symmetrize(pairs)


PART_OFFSET = 1_000_000_000


def part_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts and suppliers (ids moved up) by lines: a graph of two sides."""
    pairs = table(spark, sf_dir, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.count("*").alias("w"))
    return symmetrize(pairs.select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + PART_OFFSET).alias("dst"), "w"))


def cust_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    pairs = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_partkey", "o_custkey").agg(F.count("*").alias("w"))
    return symmetrize(pairs.select(F.col("l_partkey").alias("src"), (F.col("o_custkey") + PART_OFFSET).alias("dst"), "w"))


def user_line(spark: SparkSession, sf_dir: str, weak: float = 0.001, gap_days: int = 2) -> DataFrame:
    """Consecutive events of a user; a link over a gap is weak."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    own = table(spark, sf_dir, "events").where("user_id is not null").select("event_id", "ts", F.lag("event_id").over(order).alias("last"), F.lag("ts").over(order).alias("since"))
    weight = F.when(F.col("ts") > F.col("since") + F.expr(f"interval {gap_days} days"), weak).otherwise(1.0)
    return symmetrize(own.where("last is not null").select(F.col("last").alias("src"), F.col("event_id").alias("dst"), weight.alias("w")))


def day_ring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct ship days in a ring, numbered from 0."""
    scratch = Scratch(spark, "days")
    days = table(spark, sf_dir, "lineitem").select(F.to_date("l_shipdate").alias("d")).where("d is not null").distinct()
    placed = scratch.save(ordered(days, ["d"], scratch).select(F.col("place").cast("long").alias("id")))
    n = placed.count()
    return symmetrize(placed.select(F.col("id").alias("src"), F.pmod(F.col("id") + 1, F.lit(n)).alias("dst"), F.lit(1.0).alias("w")))


def conv_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive turns of a conversation; ids conv_id * 1000 + turn."""
    node = F.col("conv_id") * 1000 + F.col("turn")
    order = Window.partitionBy("conv_id").orderBy("turn")
    own = table(spark, sf_dir, "conversations").select(node.alias("dst"), F.lag(node).over(order).alias("src"))
    return symmetrize(own.where("src is not null").select("src", "dst", F.lit(1.0).alias("w")))


def event_flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, w): transitions between the event types of a user's consecutive events, as counted; events without a user follow nothing."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id")
    own = table(spark, sf_dir, "events").where("user_id is not null").select("event_type", F.lag("event_type").over(order).alias("last"))
    return own.where("last is not null").groupBy(F.col("last").alias("a"), F.col("event_type").alias("b")).agg(F.count("*").alias("w"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(host, target, w): link targets named in pages, by host."""
    pages = table(spark, sf_dir, "pages").select(F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1)).alias("hrefs"))
    return pages.select("host", F.explode("hrefs").alias("target")).groupBy("host", "target").agg(F.count("*").alias("w"))


def _doc_words(spark: SparkSession, sf_dir: str, low: float, high: float, most: int | None = None) -> tuple[DataFrame, DataFrame]:
    """((doc_id, word), (word, df)): all words of the documents, and those in a middle share of them; with ``most``, in so many of them at most."""
    docs = table(spark, sf_dir, "documents")
    words = docs.where("doc_id is not null").select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"([\p{L}\p{N}_]{2,})"), F.lit(1)))).alias("word"))
    total = docs.agg(F.count("*").alias("n"))
    df = words.groupBy("word").agg(F.count("*").alias("df")).crossJoin(F.broadcast(total))
    middle = (F.col("df") >= low * F.col("n")) & (F.col("df") <= high * F.col("n"))
    return words, df.where(middle if most is None else middle & (F.col("df") <= most)).select("word", "df")


def doc_words(spark: SparkSession, sf_dir: str, low: float = 0.02, high: float = 0.4, least: int = 3, block: int = 1_000) -> DataFrame:
    """Documents by the number of words they share, of words in a middle share of all documents.

    Pairs grow with the square of the documents. A word's documents are dealt into blocks of about
    ``block``, and pairs of blocks meet in tasks of their own, so a frequent word is no hot key.
    """
    words, often = _doc_words(spark, sf_dir, low, high)
    often = often.select("word", F.ceil(F.col("df") / block).cast("int").alias("blocks"))
    own = words.join(often, "word").withColumn("b", F.pmod(F.xxhash64("doc_id"), "blocks").cast("int"))
    each = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    left = own.withColumn("o", each).select("word", F.col("b").alias("p"), F.col("o").alias("q"), F.col("doc_id").alias("src"))
    right = own.withColumn("o", each).select("word", F.col("o").alias("p"), F.col("b").alias("q"), F.col("doc_id").alias("dst"))
    pairs = left.join(right, ["word", "p", "q"]).where("src < dst").groupBy("src", "dst").agg(F.count("*").alias("w")).where(F.col("w") >= least)
    return symmetrize(pairs)


def doc_word_sets(spark: SparkSession, sf_dir: str, scratch: Scratch, low: float = 0.02, high: float = 0.4, least: int = 3, most: int | None = None) -> tuple[DataFrame, int]:
    """((doc_id, words), number of words): the words of ``doc_words`` by number, for documents that have ``least`` of them; with ``most``, only words in so many documents at most."""
    words, often = _doc_words(spark, sf_dir, low, high, most)
    often = scratch.save(ordered(often.select("word"), ["word"], scratch).withColumnRenamed("place", "number"))
    n_words = often.count()
    own = words.join(bounded_broadcast(often, n_words), "word").groupBy("doc_id").agg(F.collect_set(F.col("number").cast("int")).alias("words"))
    return scratch.save(own.where(F.size("words") >= least)), n_words


def doc_words_joined(spark: SparkSession, sf_dir: str, low: float = 0.02, high: float = 0.4, least: int = 3, most: int = 20_000, block: int = 8_192) -> DataFrame:
    """(doc_id, n_links, weight, component_id) of every document: the graph of ``doc_words`` by words in ``most`` documents at most, as in its SQL, without its links written out.

    Documents are dealt into blocks of about ``block``; each pair of blocks counts its shared words in one task, as a
    product of two 0/1 matrices, and gives sums and a forest of its links, so what is shuffled are the words of the documents once a block.
    """
    scratch = Scratch(spark, "doc-words")
    own, n_words = doc_word_sets(spark, sf_dir, scratch, low, high, least, most)
    left, right = block_pairs(own, max(4, -(-own.count() // block)))

    def met(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if a.empty or b.empty:
            return pd.DataFrame({"doc_id": [], "n": [], "w": [], "root": []})
        a = a.sort_values("doc_id")
        same = a["p"].iloc[0] == a["q"].iloc[0]
        return links_between(a, a if same else b, n_words, least, same)

    found = scratch.save(left.groupBy("p", "q").cogroup(right.groupBy("p", "q")).applyInPandas(met, "doc_id long, n long, w double, root long"))
    sums = found.groupBy("doc_id").agg(F.sum("n").alias("n_links"), F.sum("w").alias("weight"))
    whole = components(spark, scratch.save(found.select(F.col("doc_id").alias("src"), F.col("root").alias("dst")).distinct()), scratch).toDF("doc_id", "component_id")
    every = table(spark, sf_dir, "documents").where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id")).distinct()
    rows = every.join(sums, "doc_id", "left").join(whole, "doc_id", "left")
    return rows.select("doc_id", F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"), F.coalesce("weight", F.lit(0.0)).alias("weight"), F.coalesce("component_id", "doc_id").alias("component_id"))


def emb_knn(spark: SparkSession, sf_dir: str, k: int = 10, indexed: bool = False, every: int = 1) -> DataFrame:
    """Vectors by cosine to their k nearest: exact against all, or by inverted lists of measured recall for many vectors with geometry.

    With ``every`` only the vectors whose id it divides look for their nearest, exactly and among all.
    """
    given = table(spark, sf_dir, "embeddings")
    if every > 1:
        rows = given.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v"))
        best = searched_nearest(rows.where(F.col("id") % every == 0), rows, k)
    else:
        vecs = unit_vectors(given)
        best = VectorIndex(spark, vecs, k).nearest() if indexed else exact_nearest(vecs, k)
    return symmetrize(best.select("src", "dst", F.greatest("w", F.lit(1e-9)).alias("w")), how="max")
