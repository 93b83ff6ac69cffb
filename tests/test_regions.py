import itertools

import numpy as np
import pytest

from gridmatch.region import solvers as S

FIG6 = np.array([[-1, -1, 10, -1, -1, 10, 1, 35, -1, -1, 40, -90]], float)


def test_worked_sweeps():
    assert [S.sweep(FIG6, 3, 4, k)[0][0] for k in S.CORNERS] == [61, 95, 95, 95]
    assert S.corner_dp(FIG6, 3, 4)[0][0] == 95
    assert S.exact_region(FIG6, 3, 4)[0][0] == 96
    cells = S.region_cells(S.sweep(FIG6, 3, 4, "BL")[1][0], 4)
    assert [(r + 1, c + 1) for r, c in cells] == [(1, 3), (2, 2), (2, 3), (3, 3)]


def test_sweeps_are_not_monotone():
    low, high = np.array([[5, -6, 5, -1, 0, 0]], float), np.array([[5, -4, 5, -1, 0, 0]], float)
    assert (S.corner_dp(low, 2, 3)[0][0], S.corner_dp(high, 2, 3)[0][0]) == (9, 6)
    assert (S.exact_region(low, 2, 3)[0][0], S.exact_region(high, 2, 3)[0][0]) == (9, 9)


@pytest.mark.parametrize(("h", "w", "n"), [(2, 2, 13), (2, 3, 40), (3, 3, 218), (3, 4, 1126), (1, 4, 10)])
def test_connected_masks(h, w, n):
    masks = S.connected_masks(h, w)
    assert len(masks) == n and all(S.is_connected(m, h, w) for m in masks)


@pytest.mark.parametrize(("h", "w"), [(2, 2), (2, 3), (3, 3), (1, 5)])
def test_solvers_on_random_matrices(h, w):
    rng = np.random.default_rng(h * 10 + w)
    m = rng.integers(-10, 11, (300, h * w)).astype(float)
    m[rng.random(m.shape) < 0.1] = np.nan
    m = m[~np.isnan(m).all(1)]
    dp, mask, _ = S.corner_dp(m, h, w)
    exact, emask = S.exact_region(m, h, w)
    bound = S.positive_sum(m)
    assert (dp <= exact).all() and (exact <= bound).all() and (dp >= np.nanmax(m, 1)).all()
    for row, s, k in itertools.chain(zip(m, dp, mask), zip(m, exact, emask)):
        assert S.is_connected(int(k), h, w)
        assert s == sum(row[i] for i in range(h * w) if int(k) >> i & 1)
    assert all(S.sink_class(int(k), h, w) for k in mask)
    if h == 1 or (h, w) == (2, 2):
        assert (dp == exact).all()
    for row, s in list(zip(m, exact))[:60]:
        assert S.exact_branch(row, h, w)[0] == s


def test_all_negative_and_holes():
    assert S.corner_dp(np.array([[-1.0, -2, -3, -4]]), 2, 2)[0][0] == -1
    ring = np.array([[1.0, 1, 1, 1, np.nan, 1, 1, 1, 1]])
    assert S.exact_region(ring, 3, 3)[0][0] == 8


def test_shapes():
    mask = lambda rows: sum(1 << (r * 3 + c) for r, x in enumerate(rows) for c, y in enumerate(x) if y == "#")
    assert S.sink_class(mask(["###", "#.#", "###"]), 3, 3)
    assert not S.sink_class(mask([".#.", "###", ".#."]), 3, 3)


@pytest.mark.parametrize(("points", "length"), [({(0, 0), (2, 2)}, 4), ({(0, 0), (0, 2), (2, 1)}, 4), ({(0, 0), (0, 2), (2, 0), (2, 2)}, 6), ({(1, 0), (0, 1), (1, 2), (2, 1)}, 4)])
def test_tree_reduction(points, length):
    assert S.steiner_length(points, 3) == length
    for off, yes in ((0, True), (-1, False)):
        s, side, weight = S.steiner_instance(points, 3, length + off)
        got, _ = S.exact_branch(s.ravel(), side, side)
        assert bool(got >= weight) is yes


def test_empty_borders_and_sure_regions():
    """Matrices that overhang are swept without their empty rows and columns, and sure ones not at all: as if swept whole."""
    rng = np.random.default_rng(5)
    m = (rng.integers(-6, 7, (3000, 5, 8)) + rng.integers(-4, 5, (3000, 1, 1))).astype(float)
    for i, (r, c) in enumerate(rng.integers(0, 5, (3000, 2))):
        m[i, :r] = m[i, :, : c * (i % 3)] = np.nan
    m = m.reshape(3000, 40)
    m = m[~np.isnan(m).all(1)]
    swept = []
    inner = S._sweeps
    S._sweeps = lambda x, h, w, k: swept.append(x.size) or inner(x, h, w, k)
    try:
        score, mask, corner = S.corner_dp(m, 5, 8)
    finally:
        S._sweeps = inner
    assert sum(swept) < 0.8 * m.size
    s, k = S._sweeps(m, 5, 8, S.CORNERS)
    for i in range(len(m)):
        best = max(range(4), key=lambda j: (s[j, i], -int(k[j, i]).bit_count(), -int(k[j, i]), -j))
        assert (score[i], mask[i], S.CORNERS[corner[i]]) == (s[best, i], k[best, i], S.CORNERS[best])


@pytest.mark.parametrize(("h", "w"), [(1, 7), (2, 5), (4, 5), (5, 6), (5, 8), (7, 8)])
@pytest.mark.parametrize("most", [3, 2_000, 10**7])
def test_whole_scores_as_one_number(h, w, most):
    """Sweeps of whole scores as numbers and of any scores agree, ties and missing cells included."""
    rng = np.random.default_rng(h * w + most)
    m = rng.integers(-most, most + 1, (300, h * w)).astype(float)
    m[rng.random(m.shape) < 0.1] = np.nan
    m = m[(m > 0).any(1)]
    got, want = S._corner_dp(m, h, w, S.CORNERS, 0, h, 0, w), S._best_corner(m, h, w, S.CORNERS)
    assert all(np.array_equal(x, y) for x, y in zip(got, want))
    here = ~np.isnan(m)
    if h * w * most < 2 ** (54 - h * w):
        key = S._key_sweeps(np.where(here, m, 0).astype(np.int64), here, h, w, S.CORNERS).max(0)
        assert np.array_equal(key >> h * w + 6, want[0])
