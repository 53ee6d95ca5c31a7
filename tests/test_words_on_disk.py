"""Documents in blocks: what is written for their pairs follows the words of the blocks, not the pairs."""

import numpy as np
import pandas as pd

from ripplegraph.operators import words
from ripplegraph.plans.scratch import Scratch


def test_disk_does_not_grow_with_the_pairs(spark, tmp_path, monkeypatch):
    """A dozen random words of 200 for each of 10,000 documents: kept bits of their pairs took 12.7 MB."""
    scratch = Scratch(spark, "test")
    monkeypatch.setattr(scratch, "path", lambda name: f"{tmp_path}/{name}")
    n = 10_000
    own = spark.range(n).selectExpr("id AS doc_id", "array_distinct(transform(sequence(1, 12), i -> cast(pmod(xxhash64(id, i), 200) AS int))) AS words").where("size(words) >= 3")
    parts = words.WordParts(spark, own, n, 200, 3, 2_500, scratch)
    assert parts.linked.count() > 0
    written = sum(x.stat().st_size for x in tmp_path.rglob("*.parquet"))
    assert written < 4_000_000


def test_counts_below_the_bound_are_those_of_the_pairs(monkeypatch):
    """Bounds of every kind, spans and rows that do not divide the documents, and documents of one and of many words."""
    monkeypatch.setattr(words, "SPAN", 50)
    monkeypatch.setattr(words, "ROWS", 7)
    draw = np.random.default_rng(3)
    docs = [np.sort(draw.choice(40, size, replace=False)).astype(np.int16) for size in draw.integers(8, 30, 130)]
    block = words.WordBlock(np.array([len(x) for x in docs]), np.concatenate(docs))
    table = np.zeros((130, 40), dtype=int)
    for i, x in enumerate(docs):
        table[i, x] = 1
    shared, ids = table @ table.T, np.arange(130) * 3 - 20
    for least in (1, 2, 3, 4, 5, 8):
        got, over = np.zeros_like(shared), np.zeros(shared.shape, dtype=bool)
        for at, part in block.spans():
            for own, counts, links in block.counted(part.bits(40), least):
                got[own, at] = words.unpacked(counts, len(part.sizes))
                over[own, at] = np.unpackbits(links.view(np.uint8), axis=1, count=len(part.sizes))
        assert (got == np.where(shared < least, shared, 0)).all() and (over == (shared >= least)).all()
        weights = np.where(shared >= least, shared, 0)
        np.fill_diagonal(weights, 0)
        found, w, root = words.weights_between(ids, block, ids, block, 40, least, True)
        assert (found == ids[weights.any(axis=1)]).all() and (w == weights.sum(axis=1)[weights.any(axis=1)]).all() and (root == root.min()).all()
    one, two = ids[:60], ids[60:]
    halves = [words.WordBlock(np.array([len(x) for x in part]), np.concatenate(part)) for part in (docs[:60], docs[60:])]
    found, w, root = words.weights_between(one, halves[0], two, halves[1], 40, 8, False)
    across = np.where(shared >= 8, shared, 0)[:60, 60:]
    want = pd.Series(np.concatenate((across.sum(axis=1), across.sum(axis=0))), ids)
    assert (found == want.index[want > 0]).all() and (w == want[want > 0]).all()
