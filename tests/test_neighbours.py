import numpy as np
import pytest

from ripplegraph.operators.neighbours import VectorIndex, exact_nearest, unit_vectors


def brute(x, k):
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    cos = x @ x.T
    np.fill_diagonal(cos, -2)
    return np.argsort(-cos, axis=1, kind="stable")[:, :k]


def frame(spark, x):
    return spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "vec_id long, embedding array<float>")


def share_found(rows, true):
    got = {(r.src, r.dst) for r in rows}
    return np.mean([(i, int(j)) in got for i, own in enumerate(true) for j in own])


def test_index_reaches_its_recall_with_few_lists(spark):
    """Vectors around 40 directions, a third of them around one: recall over all vectors, not only the measured ones."""
    draw = np.random.default_rng(5)
    middle = draw.normal(size=(40, 16))
    own = np.where(np.arange(1_200) % 3 == 0, 0, draw.integers(0, 40, 1_200))
    x = (middle[own] + 0.3 * draw.normal(size=(1_200, 16))).astype(np.float32).astype(float)
    index = VectorIndex(spark, unit_vectors(frame(spark, x)), k=5)
    rows = index.nearest(block=100).collect()
    assert len(rows) == len({(r.src, r.dst) for r in rows}) == 1_200 * 5
    assert index.recall >= 0.95 and index.probes <= index.lists // 2
    assert share_found(rows, brute(x, 5)) >= 0.9


def test_all_lists_give_the_exact_neighbours(spark):
    x = np.random.default_rng(6).normal(size=(150, 8)).astype(np.float32).astype(float)
    vecs = unit_vectors(frame(spark, x))
    index = VectorIndex(spark, vecs, k=4, recall=1.0)
    index.probes = index.lists
    got, want = (sorted((r.src, r.dst) for r in f.collect()) for f in (index.nearest(block=20), exact_nearest(vecs, 4, 40)))
    assert got == want and share_found(exact_nearest(vecs, 4, 40).collect(), brute(x, 4)) == 1


def test_awkward_vectors(spark):
    rows = [(1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, [2.0, 0.0]), (4, None), (5, [0.0, 0.0]), (6, [1.0, None]), (7, [float("nan"), 1.0]), (None, [1.0, 1.0])]
    vecs = unit_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>"))
    assert sorted((r.src, r.dst, r.w) for r in exact_nearest(vecs, 1).collect()) == [(1, 2, 1.0), (2, 1, 1.0), (3, 1, 1.0)]
    for few in (vecs.limit(0), vecs.where("id = 1")):
        assert exact_nearest(few, 3).count() == 0 and VectorIndex(spark, few, 3).nearest().count() == 0
    assert VectorIndex(spark, vecs, 1).nearest().count() == pytest.approx(3)
