"""Notices that repeat close together."""

import pytest

from ripplegraph.llm import op1_license_scan as op1


@pytest.mark.parametrize("line, words", [("Released under the MIT License.", 5), ("Licensed under CC BY-NC 4.0.", 7)])
def test_each_repeated_notice_is_a_row(spark, line, words):
    docs = spark.createDataFrame([(1, "\n".join([line] * 9)), (2, f"x {line} y z {line}")], "doc_id long, text string")
    got = sorted((r.doc_id, r.begin_word, r.end_word) for r in op1.license_scan(docs).collect())
    assert got == [(1, words * i, words * (i + 1)) for i in range(9)] + [(2, 1, 1 + words), (2, 3 + words, 3 + 2 * words)]
