"""Texts that are shorter than the benchmark item they hold."""

import pytest

from ripplegraph.llm import op6_decontamination as op6


def test_a_text_shorter_than_its_item_leaks_it(spark):
    words = [f"w{i}" for i in range(40)]
    texts = [(1, " ".join(words[:39])), (2, " ".join(words[4:]) + "."), (3, " ".join(words[:20])), (4, " ".join(words)), (5, "w1 w2")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    bench = spark.createDataFrame([(7, " ".join(words))], "item_id long, text string")
    got = {r.doc_id: (r.begin, r.similarity) for r in op6.leaks(spark, docs, bench).collect()}
    assert got == {1: (0, pytest.approx(35 / 36)), 2: (0, pytest.approx(32 / 36)), 4: (0, 1.0)}
