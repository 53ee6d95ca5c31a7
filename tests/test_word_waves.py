"""Waves over documents that share words, without rows of links."""

import math

import numpy as np

from ripplegraph import queries
from ripplegraph.operators import cluster, words
from ripplegraph.plans.scratch import Scratch
from ripplegraph.sources import builders


def documents(spark, folder, n=90):
    """Two kinds of documents without a word in common, each of two subjects with some; copies, and documents that share too little."""
    draw = np.random.default_rng(5)
    names = [[f"{kind}{i}" for i in range(24)] for kind in "ab"]
    texts = []
    for i in range(n):
        own = names[i % 2][: 15] if i % 4 < 2 else names[i % 2][9:]
        texts.append(" ".join(draw.choice(own, 7)))
    texts += texts[:4] + [None, "", "alone in here", "a1 a2"]
    docs = spark.createDataFrame([(7 * i + 3, t) for i, t in enumerate(texts)], "doc_id long, text string")
    docs.coalesce(1).toPandas().to_parquet(f"{folder}/documents.parquet")
    return str(folder)


def same(one, other):
    a, b = ({r["id"]: r for r in x.collect()} for x in (one, other))
    assert a.keys() == b.keys() and len(a) > 0
    for i, r in a.items():
        assert (r["bits"], r["cluster"], r["group_rep"]) == (b[i]["bits"], b[i]["cluster"], b[i]["group_rep"]) and math.isclose(r["margin"], b[i]["margin"], rel_tol=1e-6, abs_tol=1e-9)


def clustered(spark, folder, least=3, **options):
    own, n_words = builders.doc_word_sets(spark, folder, Scratch(spark, "test"), least=least)
    return words.word_cluster(spark, own, n_words, least, k=2, **options)


def test_documents_in_a_batch_give_the_labels_of_the_links(spark, tmp_path):
    folder = documents(spark, tmp_path)
    same(clustered(spark, folder, steps=64), cluster.wave_cluster(spark, builders.doc_words(spark, folder), k=2, steps=64))


def test_documents_in_blocks_give_the_labels_of_the_links(spark, tmp_path):
    """Two components in blocks, where powers stand still before the steps are over, and where they do not."""
    folder = documents(spark, tmp_path)
    for steps, least in ((64, 3), (5, 4)):
        want = cluster.wave_cluster(spark, builders.doc_words(spark, folder, least=least), k=2, steps=steps)
        assert want.where("bits[0] = 0").count() > 10 and want.select("group_rep").distinct().count() > 3
        same(clustered(spark, folder, least, steps=steps, max_nodes=20, block=24), want)


def test_components_of_both_sizes(spark, tmp_path):
    folder = documents(spark, tmp_path, 61)
    want = cluster.wave_cluster(spark, builders.doc_words(spark, folder), k=2, steps=64)
    sizes = sorted(r["n"] for r in want.selectExpr("pmod(div(id - 3, 7), 2) as kind").groupBy("kind").count().toDF("kind", "n").collect())
    assert sizes[0] < sizes[-1]
    same(clustered(spark, folder, steps=64, max_nodes=sizes[0], block=10), want)


def test_the_query_writes_no_links(spark, sf, monkeypatch):
    """Links between all documents grow with their square; blocks give what the batch gives."""
    monkeypatch.setattr(builders, "doc_words", None)
    monkeypatch.setattr(builders, "symmetrize", None)
    whole = queries.doc_words_lang(spark, sf).first()["purity"]
    monkeypatch.setattr(words.word_cluster, "__defaults__", (*words.word_cluster.__defaults__[:5], 20, 60, None))
    assert queries.doc_words_lang(spark, sf).first()["purity"] == whole > 0.9
