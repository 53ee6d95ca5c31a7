"""The method on graphs in memory, against exact eigenvectors."""

import numpy as np
import pytest

from ripplegraph.functions import bounds
from ripplegraph.operators import baselines
from ripplegraph.operators.cluster import LITERAL, ROBUST, LocalGraph, codes, find_peaks, local_modes, stable_steps
from ripplegraph.operators.spectrum import music
from ripplegraph.sources.builders import KARATE


def both(links):
    a, b, w = (np.array(x) for x in zip(*links, strict=True))
    return LocalGraph.of(np.concatenate((a, b)), np.concatenate((b, a)), np.concatenate((w, w)).astype(float))


def karate():
    return both([(*map(int, x.split("-")), 1.0) for x in KARATE.split()])


def line(n=200, weak=100):
    return both([(i, i + 1, 0.1 if i == weak else 1.0) for i in range(1, n)])


def ring(n):
    return both([(i, (i + 1) % n, 1.0) for i in range(n)])


def exact_signs(g):
    _, v = baselines.exact_pairs(g)
    return codes(v[:, 1:2])[1]


def test_karate_has_78_links_and_the_known_low_eigenvalue():
    g = karate()
    values, _ = baselines.exact_pairs(g)
    assert len(g.ids) == 34 and len(g.src) == 156
    assert values[1] == pytest.approx(0.1323, abs=1e-4)


@pytest.mark.parametrize("seed", [11, 23, 57])
@pytest.mark.parametrize("make, steps", [(karate, 122), (line, 4171)])
def test_signs_equal_spectral_clustering_for_fresh_seeds(make, steps, seed):
    g = make()
    _, coef = local_modes(g, 1, 1.99, steps, ROBUST, seed)
    assert (codes(coef)[1] == exact_signs(g)).all()


def test_line_is_cut_at_its_weak_link():
    g = line()
    _, coef = local_modes(g, 1, 1.99, 4171, ROBUST)
    assert (codes(coef)[0][:, 0] == (g.ids <= 100)).all()


def test_literal_preset_reads_signs_worse():
    g = karate()
    exact = exact_signs(g)

    def share(preset):
        out = []
        for seed in range(8):
            _, coef = local_modes(g, 1, 1.99, 79, preset, seed)
            if coef.shape[1]:
                same = (codes(coef[:, :1])[1] == exact).mean()
                out.append(max(same, 1 - same))
            else:
                out.append(0.5)
        return np.mean(out)

    assert share(ROBUST) > share(LITERAL)


def test_closed_form_of_the_iteration():
    g = karate()
    u0 = np.random.default_rng(3).random((34, 1))
    history = g.evolve(u0, 300, 1.99)[:, 0, :]
    lam, v = baselines.exact_pairs(g)
    a = (v * g.deg[:, None]).T @ u0[:, 0]
    omega = np.arccos((2 - 1.99 * lam) / 2)
    t = np.arange(1, 301)
    shape = np.cos(omega[:, None] * (t + 0.5)) / np.cos(omega[:, None] / 2)
    assert np.abs(history - (v * a) @ shape).max() < 1e-8


def test_bounded_below_the_limit_and_growing_above():
    g = ring(20)
    u0 = np.random.default_rng(1).random((20, 1))
    assert np.abs(g.evolve(u0, 800, 1.99)).max() < 10
    assert np.abs(g.evolve(u0, 800, 2.01)).max() > 1e6


def test_speed_check():
    assert bounds.check_speed(1.99) == 1.99
    with pytest.raises(ValueError):
        bounds.check_speed(2.0)
    assert bounds.check_speed(2.2, lambda_max=1.7) == 2.2


def test_start_orthogonal_to_a_mode_hides_its_peak():
    g = karate()
    lam, v = baselines.exact_pairs(g)
    z = np.fft.rfft(g.evolve(v[:, 2:3], 512, 1.99)[:, 0, :] * np.hanning(512), axis=1)
    power = (g.deg[:, None] * np.abs(z) ** 2).sum(axis=0)
    omega = np.arccos((2 - 1.99 * lam) / 2)
    assert abs(2 * np.pi * power.argmax() / 512 - omega[2]) < 2 * np.pi / 512


def test_peaks_are_local():
    power = np.array([0, 1, 30, 2, 1, 1, 20, 500, 900, 1000, 900, 100, 1.0])
    assert find_peaks(power, 2, 3.0).tolist() == [2, 9]


def test_adaptive_steps_grow_with_the_mixing_time():
    assert stable_steps(ring(64), 1.99, ROBUST) > stable_steps(ring(16), 1.99, ROBUST)


def test_music_finds_two_frequencies():
    t = np.arange(200)
    x = np.array([np.cos(0.31 * t + p) + 0.8 * np.cos(0.5 * t + 2 * p) for p in np.linspace(0, 3, 8)])
    assert music(x, 40, 2) == pytest.approx([0.31, 0.5], abs=5e-3)


def test_repeated_eigenvalue_gives_the_eigenspace():
    g = ring(12)
    _, coef = local_modes(g, 1, 1.99, 512, ROBUST)
    _, v = baselines.exact_pairs(g)
    basis = v[:, 1:3] * np.sqrt(g.deg)[:, None]
    x = coef[:, 0] * np.sqrt(g.deg)
    assert np.linalg.norm(basis @ (basis.T @ x)) == pytest.approx(np.linalg.norm(x), rel=1e-3)


def test_tiny_graphs():
    g = both([(5, 9, 2.0)])
    _, coef = local_modes(g, 1, 1.99, 64, ROBUST)
    assert coef.shape[0] == 2


def test_pair_swap_repairs_a_bad_split():
    import pandas as pd

    g = line(10, 5)
    frame = pd.DataFrame({"src": g.ids[g.src], "dst": g.ids[g.dst], "w": g.p * g.deg[g.src]})
    assert baselines.swap_pairs(frame, {1, 2, 3, 4, 6}) in ({1, 2, 3, 4, 5}, {6, 7, 8, 9, 10})
