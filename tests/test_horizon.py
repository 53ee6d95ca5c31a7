"""Steps of components too large for a batch: as many as their lowest peak needs, and no component is left out."""

from unittest.mock import MagicMock

import numpy as np
import pytest

from ripplegraph.operators import cluster
from ripplegraph.operators.cluster import LABELS, ROBUST, LocalGraph, Preset, stable_series, stable_steps, wave_cluster
from ripplegraph.plans.scratch import Scratch


def line(n, weak=0):
    a = np.arange(n - 1)
    w = np.where(a == weak - 1, 0.001, 1.0)
    return LocalGraph.of(np.concatenate((a, a + 1)), np.concatenate((a + 1, a)), np.concatenate((w, w)))


def history(g, n_probes=8):
    """Steps one span after the other, as a distributed run gives them."""
    u = g.start(ROBUST)
    state = [u, u]

    def go(steps):
        out = np.empty((n_probes, u.shape[1], steps))
        for t in range(steps):
            before, now = state
            state[:] = now, 2 * now - before - 1.99 * (now - g.mean_of_neighbours(now))
            out[:, :, t] = state[1][:n_probes]
        return out

    return go


def test_probes_run_until_their_lowest_peak_is_settled():
    for g in (line(100), line(20, weak=10)):
        series = stable_series(history(g), ROBUST)
        assert series.shape[2] >= max(1024, stable_steps(g, 1.99, ROBUST) // 2)
        assert np.allclose(series, history(g)(series.shape[2]))


def test_a_horizon_that_is_too_short_is_an_error():
    with pytest.raises(RuntimeError, match="not settled after 512"):
        stable_series(history(line(400)), ROBUST, t_max=512)
    with pytest.warns(UserWarning, match="not settled before 128"):
        stable_steps(line(400), 1.99, ROBUST, t_max=128)


def edges(spark, g):
    w = g.p * g.deg[g.src]
    return spark.createDataFrame([(int(g.ids[a]), int(g.ids[b]), float(x)) for a, b, x in zip(g.src, g.dst, w, strict=True)], "src long, dst long, w double")


def test_distributed_steps_are_not_fixed(spark, monkeypatch):
    """Without given steps the probes decide, and their spans are one run."""
    seen = []

    def two_spans(go, preset, deg=None):
        seen.append(np.concatenate((go(8), go(8)), axis=2))
        return seen[0]

    monkeypatch.setattr("ripplegraph.operators.cluster.stable_series", two_spans)
    g = line(4)
    preset = Preset(seeds=2)
    got = wave_cluster(spark, edges(spark, g), preset=preset, max_nodes=1, connected=True)
    whole = g.evolve(g.start(preset), 16, 1.99)
    assert got.count() == 4 and seen[0].shape == whole.shape and np.allclose(seen[0], whole)


def test_no_large_component_is_left_out(spark, monkeypatch):
    """More than a thousand of them, whose runs are left out here but for the first."""
    n = 1_003
    links = spark.range(n).selectExpr("id * 2 AS a", "id * 2 + 1 AS b")
    both = links.selectExpr("a AS src", "b AS dst", "1.0D AS w").unionByName(links.selectExpr("b AS src", "a AS dst", "1.0D AS w"))
    first = spark.createDataFrame([(0, [1], 1, 0, 1.0)], LABELS)
    seen = []

    def labels(*_):
        seen.append(1)
        return first if len(seen) == 1 else MagicMock()

    save = Scratch.save
    monkeypatch.setattr(cluster, "distributed_labels", labels)
    monkeypatch.setattr(cluster, "components", lambda *_: spark.range(2 * n).selectExpr("id", "id div 2 * 2 AS component"))
    monkeypatch.setattr(Scratch, "save", lambda self, df, name=None: df if seen else save(self, df, name))
    wave_cluster(spark, both, steps=8, max_nodes=1)
    assert len(seen) == n
