"""Cases that the operators once got wrong: repeated notices by the thousand, long items, hot shingles, clashing names, long hosts."""

import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_operators import AWKWARD, BASE, docs, edited, prose

from ripplegraph.llm import op1_license_scan as op1
from ripplegraph.llm import op2_warc as op2
from ripplegraph.llm import op4_url_filter as op4
from ripplegraph.llm import op5_ngram_join as op5
from ripplegraph.llm import op6_decontamination as op6
from ripplegraph.llm import op8_pii as op8
from ripplegraph.llm.store import fresh


def words(text):
    return re.findall(r"[a-z0-9]+", text.lower())


def test_thousands_of_notices_are_as_many_rows(spark):
    got = op1.license_scan(docs(spark, [(1, "Released under the MIT License.\n" * 20_000)]))
    assert got.count() == 20_000 and got.select("begin_word").distinct().count() == 20_000


def test_exact_notices_equal_a_search(spark):
    rng = np.random.default_rng(3)
    names = sorted(op1.TEMPLATES)
    texts = []
    for i in range(40):
        parts = [prose(100 * i + k, int(rng.integers(0, 9))) if k % 2 else op1.TEMPLATES[names[int(rng.integers(len(names)))]] for k in range(7)]
        texts.append((i, " ".join(parts)))
    expected = []
    for i, text in texts:
        w, found = words(text), []
        for name in names:
            t = words(op1.TEMPLATES[name])
            found += [(len(t), name, b, b + len(t)) for b in range(len(w) - len(t) + 1) if w[b : b + len(t)] == t]
        taken = []
        for n, name, b, e in sorted(found, key=lambda x: (-x[0], x[1], x[2])):
            if all(e <= x or b >= y for _, x, y in taken):
                taken.append((name, b, e))
        expected += [(i, *x) for x in taken]
    got = op1.license_scan(docs(spark, texts)).where("coverage = 1").collect()
    assert Counter((r.doc_id, r.license, r.begin_word, r.end_word) for r in got) == Counter(expected)


def test_the_license_that_is_named_is_found(spark):
    texts = [(1, op1.TEMPLATES["LGPL-3.0-or-later"]), (2, op1.TEMPLATES["AGPL-3.0-or-later"]), (3, "Released under the ABC License."), (4, "Licensed under CC BY 4.0.")]
    assert {(r.doc_id, r.license) for r in op1.license_scan(docs(spark, texts)).collect()} == {(1, "LGPL-3.0-or-later"), (2, "AGPL-3.0-or-later")}
    assert op1.license_scan(docs(spark, [])).count() == 0


def test_long_items_and_wide_lanes(spark):
    item = prose(7, 3_000)
    bench = spark.createDataFrame([(1, item), (2, prose(8, 40))], "item_id long, text string")
    texts = [(1, f"{prose(9, 50)} {item} {prose(10, 50)}"), (2, edited(item, 60, 1)), (3, prose(11, 3_000)), (4, None)]
    assert {(r.doc_id, r.item_id, r.begin) for r in op6.leaks(spark, docs(spark, texts), bench).collect()} == {(1, 1, 50), (2, 1, 0)}
    same = spark.range(1).select(F.lit(1).alias("k"), F.array_repeat(F.lit(-1).cast("long"), 70_000).alias("h"))
    assert op6.simhash(same, ["k"], "h").first().fingerprint == -1
    assert op6.leaks(spark, docs(spark, texts), bench.limit(0)).count() == 0


def test_all_links_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(op5, "LIST_BLOCK", 3)
    texts = AWKWARD + [(100 + i, edited(BASE, i % 12, i)) for i in range(30)] + [(200 + i, edited(prose(8, 200), 2 + i % 9, i)) for i in range(30)]
    sets = []
    for _, t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    linked = lambda a, b: bool(a and b) and 100 * len(a & b) >= 75 * len(a | b)
    expected = Counter((i, sum(linked(a, b) for k, b in enumerate(sets) if k != j)) for j, ((i, _), a) in enumerate(zip(texts, sets, strict=True)))
    got = op5.NgramJoin(spark, docs(spark, texts)).link_counts().collect()
    assert Counter((r.doc_id, r.n_links) for r in got) == expected


def test_one_passage_in_many_unlinked_texts(spark):
    """Texts that share a passage but do not link make no pairs across by its shingles."""
    passage = prose(50, 60)
    texts = [(i, f"{prose(1_000 + i, 25)} {passage}") for i in range(400)]
    join = op5.NgramJoin(spark, docs(spark, texts))
    got = join.run()
    assert got.where("component_id <> doc_id").count() == 0
    seen = spark.read.parquet(join.scratch.path("across"))
    assert seen.count() < 400


def test_clashing_names_stay(spark):
    frame = spark.createDataFrame([(1, "card 4111 1111 1111 1111", 5, 6, 7, 8)], "doc_id long, text string, n_pseudonyms int, matches_found int, own_hash int, kept_id int")
    out = op8.pseudonymise(frame, count=None)
    assert out.columns == frame.columns and out.first()[2:] == (5, 6, 7, 8) and "4111" not in out.first().text.split()[1]
    kept = op5.one_of_each(spark, frame)
    assert kept.columns == frame.columns and kept.first()[2:] == (5, 6, 7, 8)
    assert fresh(frame, "OWN_HASH", "x") == ["_OWN_HASH", "x"]


def test_the_key_comes_from_the_session(spark):
    frame = spark.createDataFrame([(1, "4111 1111 1111 1111")], "doc_id long, text string")
    known = op8.pseudonymise(frame).first().text
    spark.conf.set(op8.KEY_SETTING, "secret")
    try:
        assert op8.pseudonymise(frame).first().text == op8.pseudonymise(frame, key="secret").first().text != known
    finally:
        spark.conf.unset(op8.KEY_SETTING)


def test_hosts_of_many_labels(spark):
    urls = spark.createDataFrame([(1, "http://" + "a." * 200_000 + "org/x"), (2, "http://" + "." * 50_000), (3, "http://org./")], "page_id long, url string")
    assert [r.rule for r in op4.filter_urls(spark, urls, op4.RULES).orderBy("page_id").collect()] == ["org/", None, None]
    assert op4.filter_urls(spark, urls.limit(0), op4.RULES).count() == 0 and op4.filter_urls(spark, urls, spark.createDataFrame([], "verdict string, rule string")).count() == 3


@pytest.mark.parametrize("n, total, most", [(10, 0, 4_000), (4_000, 4_000 * 500_000, 134), (3, 3 << 30, 1), (None, None, 4_000)])
def test_files_hold_so_many_bytes(n, total, most):
    assert op2.records_per_file(n, total) == most
