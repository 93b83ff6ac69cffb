"""Best connected region of a score matrix, for many matrices at once.

A matrix is a row of n = h*w scores (row 0 at the bottom, row-major), NaN where there is no
tile.  A region is a set of 4-connected cells, kept as a bit mask (bit r*w + c).  Ties go to
the higher score, then fewer cells, then the smaller mask, then corner order BL, BR, TL, TR.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

CORNERS = ("BL", "BR", "TL", "TR")


def sweep_order(h: int, w: int, corner: str) -> list[tuple[int, int, int]]:
    """(cell, the cell behind it in its row, the cell behind it in its column), -1 for none."""
    rows = range(h) if corner[0] == "B" else range(h - 1, -1, -1)
    cols = range(w) if corner[1] == "L" else range(w - 1, -1, -1)
    dr, dc = (-1 if corner[0] == "B" else 1), (-1 if corner[1] == "L" else 1)
    at = lambda r, c: r * w + c if 0 <= r < h and 0 <= c < w else -1
    return [(at(r, c), at(r, c + dc), at(r + dr, c)) for r in rows for c in cols]


def _better(s1, n1, m1, s2, n2, m2):
    """Where (s1, n1, m1) beats (s2, n2, m2)."""
    return (s1 > s2) | ((s1 == s2) & ((n1 < n2) | ((n1 == n2) & (m1 < m2))))


def _sweeps(scores: np.ndarray, h: int, w: int, corners: tuple[str, ...]) -> tuple[np.ndarray, np.ndarray]:
    """Each cell takes the best of itself, itself with the region behind it in its row, in its
    column, or with both (their common cells counted once).  Best end cell: scores and masks,
    corners x matrices.  All corners go together: a step handles each one's next cell."""
    b, n = scores.shape
    if n > 62:
        raise ValueError("masks hold 62 cells at most")
    orders = [sweep_order(h, w, c) for c in corners]
    place = {cell: p for p, (cell, _, _) in enumerate(orders[0])}
    cells = np.array([[cell for cell, _, _ in o] for o in orders])
    bits = np.repeat(np.left_shift(np.int64(1), cells.T.astype(np.int64)), b, axis=1)
    here = ~np.isnan(scores)
    full = here.all()
    value = np.where(here, scores, 0.0)
    owns = np.concatenate([value.T[o] for o in cells], axis=1)  # step x (corner, matrix)
    here = np.concatenate([here.T[o] for o in cells], axis=1)
    sums = _Sums(value, len(corners)) if h > 1 and w > 1 else None
    total, mask = np.empty((n, owns.shape[1])), np.zeros((n, owns.shape[1]), np.int64)
    for p, (_, row, col) in enumerate(orders[0]):
        own, bit = owns[p], bits[p]
        options = [(own, bit)]
        behind = [place[j] for j in (row, col) if j >= 0]
        for j in behind:  # no region behind holds this cell
            options.append((own + total[j], mask[j] | bit))
        if len(behind) == 2:
            x, y = behind
            options.append((options[1][0] + total[y] - sums.of(mask[x] & mask[y]), options[1][1] | mask[y]))
        s, m = _best_of(options)
        total[p], mask[p] = (s, m) if full else (np.where(here[p], s, -np.inf), np.where(here[p], m, 0))
    s, m = _best_of(list(zip(total, mask)))
    return s.reshape(len(corners), b), m.reshape(len(corners), b)


def _best_of(options: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Scores and masks of the best of several regions of each matrix."""
    (s, m), n = options[0], np.ones(len(options[0][0]), np.int8)
    for x, _ in options[1:]:
        s = np.maximum(s, x)
    if len(options) > 1:
        n = (options[0][0] == s).view(np.int8)
        for x, y in options[1:]:
            same = x == s
            m, n = np.where(same, y, m), n + same.view(np.int8)
    tie = np.flatnonzero(n > 1)
    if len(tie):
        at, best, size = s[tie], np.zeros(len(tie), np.int64), np.full(len(tie), 99, np.uint8)
        for x, y in options:
            y = y[tie]
            k = np.bitwise_count(y)
            win = (x[tie] == at) & ((k < size) | ((k == size) & (y < best)))
            best, size = np.where(win, y, best), np.where(win, k, size)
        m = m.copy()
        m[tie] = best
    return s, m


class _Sums:
    """Sums over the cells of masks: a table of the sums of every six cells' subsets for each matrix."""

    def __init__(self, value: np.ndarray, corners: int):
        b, n = value.shape
        self.tables = []
        for a in range(0, n, 6):
            part = np.zeros((b, 1), value.dtype)
            for i in range(a, min(a + 6, n)):
                part = np.concatenate([part, part + value[:, i : i + 1]], axis=1)
            self.tables.append((part.ravel(), np.tile(np.arange(b) * part.shape[1], corners)))

    def of(self, mask: np.ndarray) -> np.ndarray:
        out = None
        for i, (table, first) in enumerate(self.tables):
            at = mask >> 6 * i if i else mask & 63
            if i:
                at &= 63
            at += first
            part = table.take(at)
            out = part if out is None else np.add(out, part, out=out)
        return out


def _key_sweeps(value: np.ndarray, here: np.ndarray, h: int, w: int, corners: tuple[str, ...]) -> np.ndarray:
    """The sweeps of whole scores with one number for a region: its score, then 63 less its cells, then its
    mask's complement, so that the larger number is the better region.  A cell adds the same to any region,
    and two regions' union is their sum less their common cells.  Best end cell: corners x matrices."""
    b, n = value.shape
    orders = [sweep_order(h, w, c) for c in corners]
    place = {cell: p for p, (cell, _, _) in enumerate(orders[0])}
    cells = np.array([[cell for cell, _, _ in o] for o in orders])
    every = np.int64((1 << n) - 1)
    empty = np.int64(63 << n) + every
    adds = (value << n + 6) - np.int64(1 << n) - np.left_shift(np.int64(1), np.arange(n, dtype=np.int64))
    full, sums = here.all(), _Sums(adds, len(corners)) if h > 1 and w > 1 else None
    adds = np.concatenate([adds.T[o] for o in cells], axis=1)  # step x (corner, matrix)
    none = None if full else ~np.concatenate([here.T[o] for o in cells], axis=1)
    key = np.empty(adds.shape, np.int64)
    for p, (_, row, col) in enumerate(orders[0]):
        behind, own = [key[place[j]] for j in (row, col) if j >= 0], key[p]
        if not behind:
            own[:] = adds[p] + empty
        else:
            np.maximum(behind[0], empty, out=own)
            if len(behind) == 2:
                x, y = behind
                np.maximum(own, y, out=own)
                common = x | y
                np.invert(common, out=common)
                common &= every
                both = x + y
                both -= sums.of(common)
                both -= empty
                np.maximum(own, both, out=own)
            own += adds[p]
        if not full:
            own[none[p]] = empty  # nothing to go on from
    if not full:
        key[none] = np.iinfo(np.int64).min
    return key.max(0).reshape(len(corners), b)


def sweep(scores: np.ndarray, h: int, w: int, corner: str) -> tuple[np.ndarray, np.ndarray]:
    """The sweep from one corner: scores and masks."""
    s, m = _sweeps(scores, h, w, (corner,))
    return s[0], m[0]


def corner_dp(scores: np.ndarray, h: int, w: int, corners: tuple[str, ...] = CORNERS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best of the corners' sweeps: scores (-inf without cells), masks, corner numbers.

    What every sweep surely gives is not swept: the largest cell where one or none is positive, and
    all cells of a rectangle where all are.  The others are swept without their empty border rows
    and columns, those with the same border together."""
    b, first = len(scores), CORNERS.index(corners[0])
    parts = [_outline(scores[a : a + 4096], h, w) for a in range(0, max(b, 1), 4096)]
    positive, cells, r0, r1, c0, c1 = (np.concatenate(x) for x in zip(*parts))
    score, mask, which = np.full(b, -np.inf), np.zeros(b, np.int64), np.full(b, first)
    few = np.flatnonzero((positive <= 1) & (cells > 0))
    value = scores[few]
    value[np.isnan(value)] = -np.inf
    at = value.argmax(1) if len(few) else np.zeros(0, np.int64)
    score[few], mask[few] = value[np.arange(len(few)), at], np.left_shift(np.int64(1), at.astype(np.int64))
    every = np.flatnonzero((positive > 1) & (positive == cells) & (cells == (r1 - r0) * (c1 - c0)))
    value = scores[every]
    score[every] = np.where(np.isnan(value), 0.0, value).sum(1)
    line = np.left_shift(np.int64(1), c1[every]) - np.left_shift(np.int64(1), c0[every])
    for r in range(h):
        mask[every] |= np.where((r0[every] <= r) & (r < r1[every]), line << r * w, 0)
    rest = (positive > 1) & (positive < cells) | (positive > 1) & (cells < (r1 - r0) * (c1 - c0))
    rest = np.flatnonzero(rest)
    border = ((r0[rest] * h + r1[rest] - 1) * w + c0[rest]) * w + c1[rest] - 1
    kinds, kind, n = np.unique(border, return_inverse=True, return_counts=True)
    if len(kinds) > 1:
        kind[n[kind] < 48] = len(kinds)  # few of a border: swept whole, together
    order = np.argsort(kind, kind="stable")
    for part in np.split(order, np.flatnonzero(np.diff(kind[order])) + 1) if len(order) else ():
        i, whole = rest[part], kind[part[0]] == len(kinds)
        box = (0, h, 0, w) if whole else tuple(int(x[i[0]]) for x in (r0, r1, c0, c1))
        for a in range(0, len(i), 1024):  # what a step handles stays in the processor's cache
            j = i[a : a + 1024]
            score[j], mask[j], which[j] = _corner_dp(scores[j], h, w, corners, *box)
    return score, mask, which


def _outline(scores: np.ndarray, h: int, w: int) -> tuple[np.ndarray, ...]:
    """Positive cells, cells, and first and past the last row and column that have any."""
    by_cell = np.ascontiguousarray(scores.T)
    here = ~np.isnan(by_cell)
    grid, out = here.reshape(h, w, -1), [(by_cell > 0).sum(0), here.sum(0)]
    for any_, n in ((grid.any(1), h), (grid.any(0), w)):
        before = ~np.logical_or.accumulate(any_, 0)
        after = ~np.logical_or.accumulate(any_[::-1], 0)
        low, high = before.sum(0), n - after.sum(0)
        none = low == n
        low[none], high[none] = 0, n
        out += [low, high]
    return tuple(out)


def _corner_dp(scores: np.ndarray, h: int, w: int, corners: tuple[str, ...], r0: int, r1: int, c0: int, c1: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best of the sweeps over the rows r0 to r1 and columns c0 to c1."""
    high, wide = r1 - r0, c1 - c0
    inner = np.ascontiguousarray(scores.reshape(-1, h, w)[:, r0:r1, c0:c1]).reshape(-1, high * wide)
    n, here = high * wide, ~np.isnan(inner)
    value = np.where(here, inner, 0.0)
    # whole scores, and no region's or union's out of a number's range
    fits = (value == np.rint(value)).all(1) & (3 * np.abs(value).max(1) + np.maximum(value, 0).sum(1) < 2.0 ** max(0, 57 - n))
    score, mask, which = np.empty(len(inner)), np.empty(len(inner), np.int64), np.empty(len(inner), np.int64)
    if fits.any():
        i = slice(None) if fits.all() else np.flatnonzero(fits)
        key = _key_sweeps(value[i].astype(np.int64), here[i], high, wide, corners)
        best, numbers = key.max(0), np.array([CORNERS.index(c) for c in corners])
        score[i], mask[i], which[i] = best >> n + 6, ~best & (1 << n) - 1, numbers[key.argmax(0)]
    if not fits.all():
        i = np.flatnonzero(~fits)
        score[i], mask[i], which[i] = _best_corner(inner[i], high, wide, corners)
    return score, sum((mask >> r * wide & (1 << wide) - 1) << (r0 + r) * w + c0 for r in range(high)), which


def _best_corner(inner: np.ndarray, high: int, wide: int, corners: tuple[str, ...]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    best = None
    for corner, s, m in zip(corners, *_sweeps(inner, high, wide, corners)):
        n = np.bitwise_count(m).astype(np.int64)
        k = np.full(len(s), CORNERS.index(corner))
        if best is None:
            best = (s, n, m, k)
            continue
        win = _better(s, n, m, *best[:3])
        best = tuple(np.where(win, x, y) for x, y in zip((s, n, m, k), best))
    return best[0], best[2], best[3]


def neighbours(i: int, h: int, w: int) -> list[int]:
    r, c = divmod(i, w)
    return [a * w + b for a, b in ((r - 1, c), (r + 1, c), (r, c - 1), (r, c + 1)) if 0 <= a < h and 0 <= b < w]


def is_connected(mask: int, h: int, w: int) -> bool:
    if not mask:
        return False
    seen = mask & -mask
    while True:
        grown = seen
        for i in range(h * w):
            if seen >> i & 1:
                for j in neighbours(i, h, w):
                    grown |= mask & (1 << j)
        if grown == seen:
            return seen == mask
        seen = grown


@lru_cache(maxsize=None)
def connected_masks(h: int, w: int) -> tuple[int, ...]:
    """All connected regions of a small grid, grown cell by cell."""
    layer = {1 << i for i in range(h * w)}
    found = set(layer)
    while layer:
        layer = {m | 1 << j for m in layer for i in range(h * w) if m >> i & 1 for j in neighbours(i, h, w) if not m >> j & 1}
        found |= layer
    return tuple(sorted(found))


def exact_enumerated(scores: np.ndarray, h: int, w: int) -> tuple[np.ndarray, np.ndarray]:
    masks = np.array(connected_masks(h, w), np.int64)
    member = (masks[:, None] >> np.arange(h * w) & 1).astype(float)
    total = np.where(np.isnan(scores), -np.inf, scores)
    sums = np.stack([np.where(member[i] > 0, total, 0).sum(1) for i in range(len(masks))], 1)
    order = np.lexsort((masks, np.bitwise_count(masks)))
    k = order[sums[:, order].argmax(1)]
    return sums[np.arange(len(scores)), k], masks[k]


def exact_branch(scores: np.ndarray, h: int, w: int) -> tuple[float, int]:
    """Branch and bound for one matrix: grow from each root over larger cells only, deciding one
    border cell at a time; a branch ends when all positive cells left cannot beat the best."""
    s = np.asarray(scores, float)
    usable = [i for i in range(h * w) if not np.isnan(s[i])]
    best: tuple[float, int, int] = (-np.inf, 0, 0)
    rank = lambda v, m: (v, -int(m).bit_count(), -m)

    def grow(mask: int, banned: int, value: float) -> None:
        nonlocal best
        if rank(value, mask) > best:
            best = rank(value, mask)
        free = [i for i in usable if not (mask | banned) >> i & 1]
        if value + sum(s[i] for i in free if s[i] > 0) < best[0]:
            return
        border = [j for j in free if any(mask >> k & 1 for k in neighbours(j, h, w))]
        if not border:
            return
        j = max(border, key=lambda x: s[x])
        grow(mask | 1 << j, banned, value + s[j])
        grow(mask, banned | 1 << j, value)

    before = 0
    for i in usable:
        grow(1 << i, before, s[i])
        before |= 1 << i
    return best[0], -best[2]


def exact_region(scores: np.ndarray, h: int, w: int) -> tuple[np.ndarray, np.ndarray]:
    if h * w <= 12:
        return exact_enumerated(scores, h, w)
    got = [exact_branch(x, h, w) for x in scores]
    return np.array([g[0] for g in got]), np.array([g[1] for g in got], np.int64)


def best_run(scores: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One-row matrices: the best run of neighbouring cells, exactly."""
    return corner_dp(scores, 1, scores.shape[1], ("BL",))[:2]


def positive_component(scores: np.ndarray, h: int, w: int) -> tuple[np.ndarray, np.ndarray]:
    """The best 4-connected component of the positive cells (best single cell if none is)."""
    out_s, out_m = [], []
    for x in scores:
        left = sum(1 << i for i in range(h * w) if x[i] > 0)
        best = max(((x[i], -1, -(1 << i)) for i in range(h * w) if not np.isnan(x[i])), default=(-np.inf, 0, 0))
        while left:
            part = left & -left
            while True:
                grown = part
                for i in range(h * w):
                    if part >> i & 1:
                        for j in neighbours(i, h, w):
                            grown |= left & 1 << j
                if grown == part:
                    break
                part = grown
            left &= ~part
            best = max(best, (sum(x[i] for i in range(h * w) if part >> i & 1), -part.bit_count(), -part))
        out_s.append(best[0]), out_m.append(-best[2])
    return np.array(out_s), np.array(out_m, np.int64)


def positive_sum(scores: np.ndarray) -> np.ndarray:
    """No region scores more: the positive cells' sum, or the largest cell if none is positive."""
    live = np.where(np.isnan(scores), -np.inf, scores)
    most = live.max(axis=-1, initial=-np.inf)
    return np.where(most > 0, np.where(live > 0, live, 0).sum(-1), most)


def solve(scores: np.ndarray, h: int, w: int, solver: str = "corner_dp", corners: tuple[str, ...] = CORNERS) -> tuple[np.ndarray, np.ndarray]:
    """The named heuristic: corner_dp, exact, best_run or positive_component."""
    if solver == "corner_dp":
        return corner_dp(scores, h, w, corners)[:2]
    if solver == "exact":
        return exact_region(scores, h, w)
    if solver == "best_run":
        if h != 1:
            raise ValueError("best_run is for matrices of one row")
        return best_run(scores)
    if solver == "positive_component":
        return positive_component(scores, h, w)
    raise ValueError(f"unknown solver {solver}")


def has_region(scores: np.ndarray, h: int, w: int, at_least: float) -> np.ndarray:
    """Is there a connected region of weight `at_least`?"""
    return exact_region(scores, h, w)[0] >= at_least


def region_cells(mask: int, w: int) -> list[tuple[int, int]]:
    return [divmod(i, w) for i in range(int(mask).bit_length()) if int(mask) >> i & 1]


def sinks(mask: int, h: int, w: int, corner: str) -> set[int]:
    """Cells of the region that every cell of it reaches by the corner's two moves inside it."""
    dr, dc = (1 if corner[0] == "B" else -1), (1 if corner[1] == "L" else -1)
    inside = [i for i in range(h * w) if mask >> i & 1]
    reach: dict[int, set[int]] = {}
    order = [i for i, _, _ in sweep_order(h, w, corner)][::-1]
    for i in order:
        if i not in inside:
            continue
        r, c = divmod(i, w)
        reach[i] = {i}
        for a, b in ((r + dr, c), (r, c + dc)):
            if 0 <= a < h and 0 <= b < w and a * w + b in reach:
                reach[i] |= reach[a * w + b]
    return set.intersection(*reach.values()) if reach else set()


def sink_class(mask: int, h: int, w: int) -> set[str]:
    """Corners from which a sweep can give the region: those with a sink."""
    return {k for k in CORNERS if sinks(mask, h, w, k)}


def steiner_instance(points: set[tuple[int, int]], m: int, length: int) -> tuple[np.ndarray, int, int]:
    """A score matrix on a (2m-1)^2 grid and a weight W: terminals weigh more than any tree costs,
    other crossings 0, the steps between crossings -1, and there is no cell between the lines.
    A rectilinear tree of `length` joins the points if and only if a region weighs W."""
    side, big = 2 * m - 1, 2 * m * m + 1
    s = np.full((side, side), np.nan)
    for r in range(side):
        for c in range(side):
            if r % 2 == 0 and c % 2 == 0:
                s[r, c] = big if (r // 2, c // 2) in points else 0
            elif r % 2 == 0 or c % 2 == 0:
                s[r, c] = -1
    return s, side, len(points) * big - length


def steiner_length(points: set[tuple[int, int]], m: int) -> int:
    """Least edges of a tree on the m x m grid that joins the points (small grids): the smallest
    connected set of crossings that holds them, less one."""
    need = sum(1 << (r * m + c) for r, c in points)
    return min(x.bit_count() for x in connected_masks(m, m) if x & need == need) - 1
