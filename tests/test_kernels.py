"""Fixtures with exact answers for the local kernels."""

import math

import numpy as np
import pytest

from cyclefold.functions import kernels as k
from cyclefold.operators import homology, spectral


def dist(points):
    return np.sqrt(k.squared_distances(np.asarray(points, float)))


def circle(n):
    a = 2 * np.pi * np.arange(n) / n
    return np.c_[np.cos(a), np.sin(a)]


@pytest.mark.parametrize("n", [4, 6, 12, 15, 20])
def test_polygon_barcodes(n):
    bars = k.rips_h1(dist(circle(n)))
    assert len(bars) == 1
    assert np.allclose(bars[0], [2 * math.sin(math.pi / n), 2 * math.sin(math.pi * math.ceil(n / 3) / n)])


def two_harmonics(ratio):
    a = 2 * np.pi * np.arange(60) / 60
    return np.c_[np.cos(a), np.sin(a), ratio * np.cos(2 * a), ratio * np.sin(2 * a)]


def test_loop_with_strong_second_harmonic_splits_over_two_elements_only():
    d = dist(two_harmonics(2.0))
    for p in (3, 7, 49):
        assert np.allclose(k.rips_h1(d, p)[0], [0.4310, 3.8131], atol=1e-4)
    two = k.rips_h1(d, 2)
    assert np.allclose(two[0], [2.0, 3.8131], atol=1e-4) and np.allclose(two[1], [0.4310, 2.0406], atol=1e-4)
    weak = dist(two_harmonics(0.3))
    assert all(np.allclose(k.rips_h1(weak, p)[0], [0.1220, 1.8083], atol=1e-4) for p in (2, 3, 7))


def brute_h1(d, p):
    """Column reduction of the whole boundary matrix over the integers mod p."""
    n = len(d)
    limit = d.max(axis=1).min()
    edges = sorted((d[i, j], i, j) for i in range(n) for j in range(i + 1, n) if d[i, j] <= limit)
    rank = {(i, j): r for r, (_, i, j) in enumerate(edges)}
    triangles = []
    for i in range(n):
        for j in range(i + 1, n):
            for m in range(j + 1, n):
                if {(i, j), (i, m), (j, m)} <= rank.keys():
                    triangles.append((max(rank[i, j], rank[i, m], rank[j, m]), i, j, m))
    bars, pivots = [], {}
    for top, i, j, m in sorted(triangles):
        column = {rank[j, m]: 1, rank[i, m]: p - 1, rank[i, j]: 1}
        while column:
            low = max(column)
            if low not in pivots:
                pivots[low] = column
                if edges[top][0] > edges[low][0]:
                    bars.append((edges[low][0], edges[top][0]))
                break
            other = pivots[low]
            f = column[low] * pow(other[low], -1, p)
            for r, v in other.items():
                column[r] = (column.get(r, 0) - f * v) % p
            column = {r: v for r, v in column.items() if v}
    return sorted(bars)


@pytest.mark.parametrize("p", [2, 3, 7])
def test_barcodes_against_matrix_reduction(p):
    draw = np.random.default_rng(p)
    for trial in range(12):
        n = int(draw.integers(3, 16))
        points = draw.normal(size=(n, 3)) if trial % 3 else draw.integers(0, 3, (n, 3)).astype(float)
        d = dist(points)
        got, want = sorted(map(tuple, k.rips_h1(d, p))), brute_h1(d, p)
        assert len(got) == len(want) and np.allclose(got, want)


def test_fields():
    assert k.field_characteristic(49) == 7 and k.field_characteristic(13) == 13
    for bad in (0, 1, 4, 15, 9):
        with pytest.raises(ValueError):
            k.field_characteristic(bad)


def test_landmark_bars_are_within_the_bound():
    d2 = k.squared_distances(np.r_[circle(80), 1.01 * circle(80)])
    exact, _, _ = homology.bars(d2, 7, 200)
    rough, radius, _ = homology.bars(d2, 7, 200, landmarks=40)
    assert radius > 0 and np.abs(exact[0] - rough[0]).max() <= 2 * radius


def test_scale_is_birth_or_death_at_the_ends_and_falls_back_without_a_loop():
    bars = np.array([[0.5, 2.0], [0.1, 1.0]])
    assert k.auto_scale(bars, 1.0) == (0.5, False) and k.auto_scale(bars, 0.0) == (2.0, False)
    sigma, fallback = k.auto_scale(np.zeros((0, 2)), 0.5, dist(np.arange(5.0)[:, None]))
    assert fallback and sigma == 0.5 * 1 + 0.5 * 2


def test_window_distances_equal_stacked_windows():
    x = np.random.default_rng(0).normal(size=(40, 3))
    for d in (1, 2, 7, 40):
        stacked = np.stack([x[i : i + d].ravel() for i in range(len(x) - d + 1)])
        assert np.allclose(k.window_distances(k.squared_distances(x), d), k.squared_distances(stacked), atol=1e-9)
    assert np.array_equal(k.window_distances(k.squared_distances(x), 1), k.squared_distances(x))


def test_projection_keeps_distances():
    x = np.random.default_rng(1).normal(size=(30, 500))
    z = k.isometric_projection(x)
    assert z.shape[1] <= 29 and np.allclose(k.squared_distances(z), k.squared_distances(x), rtol=1e-6)


@pytest.mark.parametrize("cycles,T", [(6, 14), (3, 5), (4, 9)])
def test_ideal_model(cycles, T):
    lap = spectral.ideal_matrix(cycles, T)
    assert (np.diag(lap) == 3 * cycles - 1).all() and np.allclose(lap.sum(axis=1), 0)
    m = np.arange(1, cycles * T)
    closed = np.where(m % cycles == 0, 3 * cycles - cycles * (1 + 2 * np.cos(2 * np.pi * m / (cycles * T))), 3 * cycles)
    assert np.allclose(np.sort(np.linalg.eigvalsh(lap))[1:], np.sort(closed))
    values, vectors, zero = k.low_modes(lap)
    assert zero == 1 and np.allclose(values[:2], 2 * cycles * (1 - np.cos(2 * np.pi / T)))
    crossings = [k.zero_crossings(v) for v in vectors.T[:2]]
    assert all(abs(c - 2 * cycles) <= 1 for c in crossings)
    truth = 2 * np.pi * np.arange(cycles * T) / T
    assert k.angular_error(k.phase(vectors, (0, 1)), truth) < 1e-5


def test_periods():
    t = np.arange(300)
    assert abs(k.period(np.sin(2 * np.pi * t / 12))[0] - 12) < 0.02
    for method in ("acf", "nsdf", "yin"):
        assert abs(k.period(np.sin(2 * np.pi * t / 6.13), method)[0] - 6.13) < 0.1
    assert math.isnan(k.period(np.zeros(50))[0]) and math.isnan(k.period(np.arange(4.0))[0])
    x = np.random.default_rng(2).normal(size=60)
    x -= x.mean()
    direct = [np.mean(x[: 60 - g] * x[g:]) / np.mean(x * x) for g in range(20)]
    assert np.allclose(k.autocorrelation(x, 19), direct)


def test_exact_repeats_leave_the_neighbour_graph_connected():
    x = np.tile(circle(20), (5, 1))
    graph = k.knn_graph(k.squared_distances(x), 4)
    assert np.isfinite(k.geodesics(graph)).all()
    y = k.isomap1d(k.squared_distances(x), 4)
    assert abs(k.period(y)[0] - 20) < 0.5
    assert abs(k.period(k.isomap1d(k.squared_distances(x + 1e-3 * np.random.default_rng(0).normal(size=x.shape)), 8, landmarks=30))[0] - 20) < 0.5


def test_pair_rule():
    assert k.mode_pair([30, 56, 28, 29]) == (2, 3, False)
    assert k.mode_pair([10, 20, 40]) == (0, 1, True)
    assert k.zero_crossings(np.array([1, 0, -1, 0, 0, 2, -3])) == 3


def test_phases_and_counts():
    phi = 2 * np.pi * np.arange(280) / 20 % (2 * np.pi)
    for sign in (1, -1):
        turned, unwrapped = k.unwrap(sign * phi % (2 * np.pi))
        assert np.allclose(unwrapped, 2 * np.pi * np.arange(280) / 20)
        assert np.allclose(k.wrap(turned - phi), 0)
    assert abs(k.cycle_count(unwrapped, 300, 21) - 14.946) < 1e-3
    assert abs(k.cycle_count(unwrapped, 300, 21, "slope") - 15) < 1e-9
    draw = np.random.default_rng(0).uniform(0, 2 * np.pi, 20000)
    assert k.angular_error(phi + 1, phi) < 1e-9 and k.angular_error(-phi, phi) < 1e-9
    assert 85 < k.angular_error(draw, np.random.default_rng(1).uniform(0, 2 * np.pi, 20000)) < 91


def test_votes_on_exact_linear_phase_agree():
    n, d, T = 300, 21, 20
    t = np.arange(n)
    px = np.c_[np.sin(2 * np.pi * t / T), np.arange(T)[t % T] ** 2.0]
    phi = 2 * np.pi * np.arange(n - d + 1) / T % (2 * np.pi)
    angles = 2 * np.pi * (np.arange(10) + 0.5) / 10
    ballots = k.votes(phi, angles, n / T, n, d)
    j, i, a, b, frac, s = ballots
    assert (b <= i + d - 1).all() and (a >= i).all() and (s <= d - 1).all()
    values = (1 - frac)[:, None] * px[a] + frac[:, None] * px[b]
    out, count = k.median_template(px, ballots, 10)
    for m in range(10):
        assert np.allclose(values[j == m], out[m], atol=1e-9) and count[m] >= n - 2 * d
    spoiled = px.copy()
    spoiled[100:120] += 50  # one bad cycle of fifteen
    assert np.allclose(k.median_template(spoiled, ballots, 10)[0], out)
    near = k.votes(phi, angles, n / T, n, d, near=0.6)
    assert 0 < len(near[0]) < len(j) and (near[5] <= 0.6).all()
    far = k.votes(phi, angles, n / T, n, d, near=0.6, anchor="center")
    assert (np.abs(far[5] - 10) <= 0.6).all()
    assert np.isnan(k.median_template(px, tuple(x[:0] for x in ballots), 10)[0]).all()


def test_geodesics_against_single_source_paths():
    x = np.random.default_rng(5).normal(size=(50, 3))
    graph = k.knn_graph(k.squared_distances(x), 4)
    far = k.geodesics(graph)
    assert all(np.allclose(far[s], k._dijkstra(graph, s)) for s in range(50))
    assert np.allclose(far, far.T) and (far >= np.sqrt(k.squared_distances(x)) - 1e-9).all()
