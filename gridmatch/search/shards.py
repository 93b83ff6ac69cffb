"""Searches beside the data: a store of shards, each with its images and its own packed index.

A shard is one row: whole images (a bounded number of tiles), their features as flat arrays, and
the order in which a sort-tile-recursive packing puts its tiles into leaves.  A search is one narrow
job over the shards; each task walks its shard's tree best-first (or by sorted access) with the
distances it needs and gives k results at most.  With more shards than can run at once, a
sixteenth of them goes first and the k-th score found there ends the others' searches early.
Nothing is exchanged but results, and a lost executor costs the shards it was at.
"""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..carriers.grids import feature_columns
from ..durable import saved, shared_dir
from ..overlap.placements import Query
from ..region import solvers
from ..score.functions import ScoreSpec

TILES, LEAF, FANOUT = 65_536, 64, 16
STORED = "shard int, ids array<bigint>, sizes array<int>, r array<int>, c array<int>, f array<double>, place array<int>"
COUNTERS = ("overlaps", "solved", "rounds", "accesses", "distances", "popped", "max_queue")
CLOCKS = ("nn_seconds", "solve_seconds")
FOUND = "query_id long, image_id long, dr int, dc int, score double, n_cells int, mask long, " + ", ".join([*(f"{x} long" for x in COUNTERS), *(f"{x} double" for x in CLOCKS)])


def packed_order(f: np.ndarray, leaf: int = LEAF) -> np.ndarray:
    """Row numbers so that every `leaf` consecutive rows are close in all features: slabs of equal
    size by the first feature, each cut again by the next."""

    def part(rows: np.ndarray, dim: int) -> list[np.ndarray]:
        leaves = -(-len(rows) // leaf)
        if leaves <= 1 or dim == f.shape[1]:
            return [rows]
        rows = rows[np.argsort(f[rows, dim], kind="stable")]
        slabs = int(np.ceil(leaves ** (1 / (f.shape[1] - dim))))
        step = leaf * -(-leaves // slabs)
        return [x for a in range(0, len(rows), step) for x in part(rows[a : a + step], dim + 1)]

    return np.concatenate(part(np.arange(len(f)), 0)) if len(f) else np.zeros(0, np.int64)


class Space:
    """One shard's images, alignments and tree as arrays."""

    def __init__(self, ids, sizes, r, c, f, place):
        self.ids, self.r, self.c = (np.asarray(x, np.int64) for x in (ids, r, c))
        self.f = np.asarray(f, float).reshape(len(self.r), -1)
        self.image = np.repeat(np.arange(len(self.ids)), sizes)
        first = np.concatenate([[0], np.cumsum(sizes)])[:-1].astype(np.int64)
        self.rows, self.cols = np.maximum.reduceat(self.r, first) + 1, np.maximum.reduceat(self.c, first) + 1
        self.cell0 = np.concatenate([[0], np.cumsum(self.rows * self.cols)])
        self.tile = np.full(self.cell0[-1], -1)
        self.tile[self.cell0[self.image] + self.r * self.cols[self.image] + self.c] = np.arange(len(self.r))
        self.place = np.asarray(place, np.int64)
        at, g = np.arange(0, len(self.place), LEAF), self.f[self.place]
        lo, hi = np.minimum.reduceat(g, at), np.maximum.reduceat(g, at)
        self.levels = [(lo, hi)]
        while len(lo) > 1:
            up = np.arange(0, len(lo), FANOUT)
            lo, hi = np.minimum.reduceat(lo, up), np.maximum.reduceat(hi, up)
            self.levels.append((lo, hi))

        #: One feature at a time gives the same sums where they are whole or few.
        whole = self.f.shape[1] < 8 or bool((self.f == np.rint(self.f)).all())
        #: A tile past the last has no features: its distances are NaN.
        self.f = np.concatenate([self.f, np.full((1, self.f.shape[1]), np.nan)])
        self.by_feature = np.ascontiguousarray(self.f.T) if whole else None

    def leaf(self, i: int) -> np.ndarray:
        return self.place[i * LEAF : (i + 1) * LEAF]

    def distance(self, spec: ScoreSpec, tiles: np.ndarray | slice, q: np.ndarray, cell) -> np.ndarray:
        """Distances of tiles to query cells (a cell for each, or one for all)."""
        if spec.metric != "l1" or self.by_feature is None or not len(self.by_feature):
            return spec.distance(self.f[tiles], q[cell])
        out = None
        for f, x in zip(self.by_feature, q.T):
            gap = f[tiles] - x[cell]
            np.abs(gap, out=gap)
            out = gap if out is None else np.add(out, gap, out=out)
        return out


class Task:
    """One query on one shard: alignments are numbered, matrices solved in batches, the best k kept."""

    def __init__(self, space: Space, query: Query, spec: ScoreSpec, k: int, solver: str, corners, floor: float, per_image: bool = False):
        self.s, self.q, self.spec, self.k, self.solver, self.corners, self.floor, self.per_image = space, query, spec, k, solver, corners, floor, per_image
        self.high, self.wide = space.rows + query.h - 1, space.cols + query.w - 1
        self.first = np.concatenate([[0], np.cumsum(self.high * self.wide)])
        self.explored, self.every, self.scores, self.frame = np.zeros(self.first[-1], bool), None, None, None
        self.qr, self.qc = np.divmod(np.arange(query.n), query.w)
        self.score, self.mask, self.at = np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.count = dict.fromkeys(COUNTERS, 0)
        self.clock = dict.fromkeys(CLOCKS, 0.0)
        self.count["overlaps"] = int(self.first[-1])

    def alignment(self, tiles: np.ndarray, cell) -> np.ndarray:
        """Numbers of the alignments that put query cells on tiles."""
        i = self.s.image[tiles]
        return self.first[i] + (self.s.r[tiles] - self.qr[cell] + self.q.h - 1) * self.wide[i] + self.s.c[tiles] - self.qc[cell] + self.q.w - 1

    def offsets(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        i = np.searchsorted(self.first, at, side="right") - 1
        dr, dc = np.divmod(at - self.first[i], self.wide[i])
        return i, dr - self.q.h + 1, dc - self.q.w + 1

    def framed(self) -> tuple[np.ndarray, ...]:
        """Tiles by place in their images' grids, with a frame that every alignment stays in (the number
        past the last tile where there is none), the grids' first places and their width."""
        h, w = self.q.h - 1, self.q.w - 1
        wide = self.s.cols + 2 * w
        first = np.concatenate([[0], np.cumsum((self.s.rows + 2 * h) * wide)])
        tile, i = np.full(first[-1], len(self.s.r)), self.s.image
        tile[first[i] + (self.s.r + h) * wide[i] + self.s.c + w] = np.arange(len(self.s.r))
        return tile, first, wide

    def matrices(self, at: np.ndarray) -> np.ndarray:
        if self.frame is None:
            self.frame = self.framed()
        grid, first, across = self.frame
        i = np.searchsorted(self.first, at, side="right") - 1
        r, c = np.divmod(at - self.first[i], self.wide[i])
        tile = grid.take((first[i] + r * across[i] + c)[:, None] + across[i][:, None] * self.qr + self.qc)
        if self.every is None:
            self.count["distances"] += int(np.count_nonzero(tile < len(self.s.r)))
            return self.spec.numpy(self.q.bg, self.s.distance(self.spec, tile, self.q.features, np.arange(self.q.n)))
        if self.scores is None:  # and none beside the tiles
            d = self.spec.numpy(self.q.bg[:, None], self.every)
            self.scores = np.concatenate([d, np.full((self.q.n, 1), np.nan)], axis=1).ravel()
        tile += np.arange(self.q.n) * (len(self.s.r) + 1)
        return self.scores.take(tile)

    def measure(self) -> None:
        """Every distance at once, for walks that need them all (each belongs to one alignment)."""
        self.every = np.stack([self.s.distance(self.spec, slice(len(self.s.r)), self.q.features, i) for i in range(self.q.n)])

    def bounds(self) -> np.ndarray:
        """Every alignment's safe bound, as `solvers.positive_sum` gives it (-inf without tiles), from the
        distances of `measure`: a query cell's scores go to their alignments at once."""
        most, total = np.full(self.first[-1], -np.inf), np.zeros(self.first[-1])
        first, wide = self.alignment(np.arange(len(self.s.r)), 0), self.wide[self.s.image]
        for i in range(self.q.n):
            at, score = first - self.qr[i] * wide - self.qc[i], self.spec.numpy(self.q.bg[i], self.every[i])
            most[at] = np.maximum(most[at], score)
            total[at] += np.maximum(score, 0)
        return np.where(most > 0, total * (1 + 1e-12), most)  # the solver may add in another order

    @property
    def kth(self) -> float:
        return max(self.floor, self.score[-1]) if len(self.score) == self.k else self.floor

    def solve(self, at: np.ndarray, bounds: np.ndarray | None = None) -> None:
        """Solve alignments (numbers, each once); with `bounds` only those whose bound reaches the k-th score."""
        began = time.perf_counter()
        step = 65536 if bounds is None else 2048
        for a in range(0, len(at), step):
            part = at[a : a + step]
            if bounds is not None:
                part = part[(bounds[part] >= self.kth) & (bounds[part] > -np.inf)]
            if not len(part):
                continue
            m = np.concatenate([self.matrices(part[x : x + 2048]) for x in range(0, len(part), 2048)])
            if bounds is None:
                live = ~np.isnan(m).all(axis=1)
                if not live.all():
                    part, m = part[live], m[live]
            if not len(part):
                continue
            self.count["solved"] += len(part)
            s, mask = solvers.solve(m, self.q.h, self.q.w, self.solver, self.corners)
            least = self.kth
            if len(s) > self.k and not self.per_image:
                least = max(least, np.partition(s, -self.k)[-self.k])
            keep = s >= least
            s, mask, part = (np.concatenate(x) for x in ((self.score, s[keep]), (self.mask, mask[keep]), (self.at, part[keep])))
            i, dr, dc = self.offsets(part)
            best = np.lexsort((dc, dr, self.s.ids[i], -s))
            if self.per_image:  # each image's best alone
                best = best[np.sort(np.unique(i[best], return_index=True)[1])]
            best = best[: self.k]
            self.score, self.mask, self.at = s[best], mask[best], part[best]
        self.clock["solve_seconds"] += time.perf_counter() - began

    def fresh(self, at: np.ndarray) -> np.ndarray:
        at = np.unique(at)
        at = at[~self.explored[at]]
        self.explored[at] = True
        return at

    def bound(self, d: float) -> float:
        """No alignment whose aligned tiles are all `d` or more apart scores more."""
        return float(solvers.positive_sum(self.spec.numpy(self.q.bg, np.full(self.q.n, d))[None, :])[0])

    def reach(self, most: float, score: float) -> tuple[float, float]:
        """Distances at which `bound` still reaches the score, and at which it is below (`most` at most)."""
        lo, hi = 0.0, min(most, 1.0)
        while self.bound(hi) >= score:
            if hi >= min(most, 1e30):
                return hi, most
            lo, hi = hi, min(most, hi * 2)
        for _ in range(16):
            mid = (lo + hi) / 2
            lo, hi = (lo, mid) if self.bound(mid) < score else (mid, hi)
        return lo, hi


def scan(t: Task, prune: bool = False) -> None:
    """Every alignment in turn; `prune` bounds each before it is solved."""
    t.measure()
    if prune:
        began = time.perf_counter()
        bounds = t.bounds()
        t.clock["solve_seconds"] += time.perf_counter() - began
        t.solve(np.arange(t.first[-1]), bounds)
    else:
        t.solve(np.arange(t.first[-1]))
    t.count["distances"], t.count["rounds"] = t.every.size, 1


class Cursor:
    """A query tile's neighbours in order of distance: leaves open as the order needs them."""

    def __init__(self, t: Task, cell: int):
        self.t, self.cell = t, cell
        lo, hi = t.s.levels[0]
        near = t.spec.mindist(t.q.features[cell], lo, hi)
        self.order = np.argsort(near, kind="stable")
        self.near, self.opened = near[self.order], 0
        self.d, self.tiles = np.zeros(0), np.zeros(0, np.int64)

    def take(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """The next n (distances, tiles) in order; fewer at the end."""
        step = max(1, -(-(n - len(self.d)) // LEAF))
        while self.opened < len(self.order):
            reach = np.partition(self.d, n - 1)[n - 1] if len(self.d) >= n else np.inf
            needed = int(np.searchsorted(self.near, reach, side="right")) - self.opened  # leaves that may hold nearer ones
            if needed <= 0:
                break
            more = self.order[self.opened : self.opened + min(needed, step)]
            self.opened += len(more)
            step *= 2
            tiles = np.concatenate([self.t.s.leaf(i) for i in more])
            d = self.t.s.distance(self.t.spec, tiles, self.t.q.features, self.cell)
            self.t.count["distances"] += len(d)
            self.d, self.tiles = np.concatenate([self.d, d]), np.concatenate([self.tiles, tiles])
        if n < len(self.d):
            reach = np.partition(self.d, n - 1)[n - 1]
            first = np.flatnonzero(self.d < reach)
            first = np.concatenate([first, np.flatnonzero(self.d == reach)[: n - len(first)]])
        else:
            first = np.arange(len(self.d))
        first = first[np.argsort(self.d[first], kind="stable")]
        out = self.d[first], self.tiles[first]
        rest = np.ones(len(self.d), bool)
        rest[first] = False
        self.d, self.tiles = self.d[rest], self.tiles[rest]
        return out


def threshold(t: Task, batch: int = 64, doubling: bool = True, bound: str = "positive_sum") -> None:
    """Rounds of sorted access to every query tile's neighbours; a round's new alignments are solved,
    and the unseen ones are bounded by the matrix of the distances reached."""
    began = time.perf_counter()
    cursors = [Cursor(t, i) for i in range(t.q.n)]
    last = np.zeros(t.q.n)
    while True:
        at = []
        for i, cursor in enumerate(cursors):
            d, tiles = cursor.take(batch)
            t.count["accesses"] += len(d)
            at.append(t.alignment(tiles, i))
            if len(d):
                last[i] = d[-1]
        at = np.concatenate(at)
        t.clock["nn_seconds"] += time.perf_counter() - began
        if not len(at):
            return
        t.count["rounds"] += 1
        t.solve(t.fresh(at))
        began = time.perf_counter()
        virtual = t.spec.numpy(t.q.bg, last)[None, :]
        top = solvers.positive_sum(virtual)[0] if bound == "positive_sum" else solvers.solve(virtual, t.q.h, t.q.w, "exact" if bound == "exact" else t.solver, t.corners)[0][0]
        if top < t.kth:
            return
        batch *= 2 if doubling else 1


class Pool:
    """(distance, alignment) pairs of opened leaves: a sorted part, and new ones not merged yet.  Pairs
    beyond `limit`, which are not likely to be taken, wait aside until nothing nearer is left."""

    def __init__(self):
        self.far, self.at = np.zeros(0), np.zeros(0, np.int64)
        self.new: list[tuple[np.ndarray, np.ndarray]] = []
        self.aside: list[tuple] = []
        self.n_new = self.n_aside = 0
        self.limit = np.inf

    def add(self, far: np.ndarray, alignments) -> None:
        """Pairs' distances, and a function that gives the alignments of some of them."""
        near = np.flatnonzero(far <= self.limit)
        if len(near):
            self.new.append((far[near], alignments(near)))
            self.n_new += len(near)
        if len(near) < len(far):
            self.aside.append((far, self.limit, alignments))
            self.n_aside += len(far) - len(near)

    def lower(self, limit: float) -> None:
        """From now on pairs beyond `limit` wait aside."""
        if limit < self.limit:
            self.limit = limit
            n = np.searchsorted(self.far, limit, side="right")
            new = [(self.far[n:], self.at[n:]), *((far[far > limit], at[far > limit]) for far, at in self.new)]
            self.far, self.at, self.new = self.far[:n], self.at[:n], [(far[far <= limit], at[far <= limit]) for far, at in self.new]
            moved = self.n_new - (kept := sum(len(far) for far, _ in self.new)) + len(new[0][0])
            self.aside += [(far, -np.inf, at.take) for far, at in new if len(far)]
            self.n_new, self.n_aside = kept, self.n_aside + moved

    def take(self, upto: float, most: int) -> tuple[np.ndarray, float]:
        """Alignments of the nearest pairs, up to a distance and about `most` of them, and the distance reached."""
        if self.n_aside and upto > self.limit and len(self.far) + self.n_new <= most:
            for far, limit, alignments in self.aside:
                i = np.flatnonzero(far > limit)
                self.new.append((far[i], alignments(i)))
            self.n_new, self.n_aside, self.aside, self.limit = self.n_new + self.n_aside, 0, [], np.inf
        if self.n_new > max(4096, len(self.far) // 4):
            far, at = (np.concatenate(x) for x in zip((self.far, self.at), *self.new))
            order = np.argsort(far)
            self.far, self.at, self.new, self.n_new = far[order], at[order], [], 0
        far, at = (np.concatenate(x) for x in zip((np.zeros(0), np.zeros(0, np.int64)), *self.new))
        head = self.far[: most + 1]
        near = np.concatenate([head, far[far <= upto]])
        if len(near) > most:
            upto = min(upto, float(np.partition(near, most - 1)[most - 1]))
        n = np.searchsorted(self.far, upto, side="right")
        now = far <= upto
        out = np.concatenate([self.at[:n], at[now]])
        self.far, self.at = self.far[n:], self.at[n:]
        if now.any():
            far, at = far[~now], at[~now]
        self.new, self.n_new = [(far, at)], len(far)
        return out, upto

    def __len__(self) -> int:
        return len(self.far) + self.n_new + self.n_aside


def frontier(t: Task, wave: int = 256, growing: bool = True, defer: bool = True) -> None:
    """One pass over the tree in order of distance to any query tile.  A leaf's (tile, query tile)
    pairs wait under their own distances (`defer`), or all of a tile's under the nearest one's;
    new alignments are solved when `wave` pairs are due, and the pass ends where nothing farther
    can reach the k-th score."""
    began = time.perf_counter()
    boxes = t.s.levels
    queue: list[tuple[float, int, int]] = [(0.0, len(boxes) - 1, 0)]
    pool, due, n_due, safe, known = Pool(), [], 0, -1.0, -np.inf
    # a guess, until the k-th score is known: half of the best there can be
    pool.limit = t.reach(np.inf, max(t.kth, t.bound(0.0) / 2))[1]

    def settle() -> None:
        nonlocal due, n_due, wave, began, safe, known
        if n_due:
            t.clock["nn_seconds"] += time.perf_counter() - began
            t.solve(np.concatenate(due))
            began = time.perf_counter()
            due, n_due, wave = [], 0, wave * 2 if growing else wave
            if t.kth > known:
                known = t.kth
                safe, limit = t.reach(np.inf, known)
                pool.lower(limit)
        t.count["rounds"] += 1

    while queue or len(pool):
        ahead = queue[0][0] if queue else np.inf
        at, reached = pool.take(ahead, wave) if len(pool) else (np.zeros(0, np.int64), ahead)
        if len(at):
            new = t.fresh(at)
            due.append(new)
            n_due += len(new)
        if n_due >= wave or reached > safe and t.bound(reached) < t.kth:
            settle()
            if reached > safe and t.bound(reached) < t.kth:
                break
        if reached < ahead or not queue:
            continue
        _, level, i = heapq.heappop(queue)
        t.count["popped"] += 1
        if level:
            a, b = i * FANOUT, min((i + 1) * FANOUT, len(boxes[level - 1][0]))
            lo, hi = boxes[level - 1][0][a:b], boxes[level - 1][1][a:b]
            near = t.spec.mindist(t.q.features[:, None, :], lo, hi).min(axis=0)
            for j, x in enumerate(near.tolist()):
                heapq.heappush(queue, (x, level - 1, a + j))
        else:
            tiles = t.s.leaf(i)
            far = t.s.distance(t.spec, tiles[:, None], t.q.features, np.arange(t.q.n))
            t.count["distances"] += far.size
            t.count["accesses"] += len(tiles)
            pool.add((far if defer else np.repeat(far.min(axis=1), t.q.n)).ravel(), lambda i, tiles=tiles: t.alignment(tiles[i // t.q.n], i % t.q.n))
        t.count["max_queue"] = max(t.count["max_queue"], len(queue) + len(pool))
    t.clock["nn_seconds"] += time.perf_counter() - began
    settle()


WALKS = {"scan": scan, "scan_pruned": lambda t: scan(t, True), "threshold": threshold, "frontier": frontier}


@dataclass
class Shards:
    """The store: `rows` has one row for each shard."""

    rows: DataFrame
    n: int
    features: int

    @classmethod
    def build(cls, tiles: DataFrame, path: str | None = None, tiles_per_shard: int = TILES, mode: str = "error") -> Shards:
        """Images are dealt to shards by a hash of their id; an image must fit in memory.
        `mode` says what to do about a store that `path` already holds, as for a write."""
        f = feature_columns(tiles)
        n = max(1, -(-tiles.count() // tiles_per_shard))
        dealt = tiles.select(F.pmod(F.xxhash64("image_id"), F.lit(n)).cast("int").alias("shard"), F.col("image_id").cast("long").alias("image_id"), F.col("r").cast("int").alias("r"), F.col("c").cast("int").alias("c"), *[F.col(x).cast("double").alias(x) for x in f])

        def pack(t: pa.Table) -> pa.Table:
            t = t.combine_chunks().sort_by([("image_id", "ascending"), ("r", "ascending"), ("c", "ascending")])
            ids, sizes = np.unique(t["image_id"].to_numpy(), return_counts=True)
            x = np.stack([t[j].to_numpy() for j in f], 1)
            lists = {"ids": ids, "sizes": sizes.astype(np.int32), "r": t["r"].to_numpy(), "c": t["c"].to_numpy(), "f": x.ravel(), "place": packed_order(x).astype(np.int32)}
            return pa.table({"shard": t["shard"][:1]} | {j: pa.array([v]) for j, v in lists.items()})

        rows = dealt.groupBy("shard").applyInArrow(pack, STORED)
        few = max(1, 4 * TILES // tiles_per_shard)
        if path is None:
            return cls(saved(rows, few), n, len(f))
        rows.write.mode(mode).option("maxRecordsPerFile", few).parquet(path)
        return cls.open(tiles.sparkSession, path)

    @classmethod
    def open(cls, spark: SparkSession, path: str) -> Shards:
        return cls.of(spark.read.schema(STORED).parquet(path))

    @classmethod
    def of(cls, rows: DataFrame) -> Shards:
        one = rows.select((F.size("f") / F.size("r")).cast("int").alias("d")).first()
        return cls(rows, rows.count(), one["d"] if one else 0)

    def append(self, tiles: DataFrame, path: str | None = None) -> Shards:
        """The store with further images in shards of their own; nothing stored is rewritten."""
        more = Shards.build(tiles, path)
        if self.n and more.features and self.features and more.features != self.features:
            raise ValueError("stores differ in dimension")
        return Shards(self.rows.unionByName(more.rows.withColumn("shard", F.col("shard") + F.lit(self.n))), self.n + more.n, self.features or more.features)

    def compact(self, tiles_per_shard: int = TILES) -> Shards:
        """Small shards of appends joined: the store is dealt anew."""
        return Shards.build(self.tiles(), tiles_per_shard=tiles_per_shard)

    def tiles(self) -> DataFrame:
        """The stored tiles as rows."""
        d = self.features

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for ids, sizes, r, c, f in zip(*(b.column(x) for x in ("ids", "sizes", "r", "c", "f"))):
                    image = np.repeat(ids.values.to_numpy(), sizes.values.to_numpy())
                    yield pa.RecordBatch.from_arrays([pa.array(image), r.values, c.values, *map(pa.array, f.values.to_numpy().reshape(-1, d).T.copy())], ["image_id", "r", "c", *(f"f{j}" for j in range(d))])

        return self.rows.select("ids", "sizes", "r", "c", "f").mapInArrow(run, "image_id long, r int, c int, " + ", ".join(f"f{j} double" for j in range(d)))

    def walk(self, rows: DataFrame, queries: list[Query], k: int, spec: ScoreSpec, algorithm: str, solver: str, corners, floors: dict[int, float], per_image: bool, how: dict, shards: int | None = None) -> DataFrame:
        """k results of each shard and query, and a row of counters (image_id is null) for each.  `shards`
        says how many rows there are about; a few go out in copies, each with a share of the queries."""
        visit, shards = WALKS[algorithm], max(1, shards or self.n)
        tasks = 4 * rows.sparkSession.sparkContext.defaultParallelism
        shares = max(1, min(len(queries), -(-tasks // shards)))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for share, *row in zip(*(b.column(x) for x in ("share", "ids", "sizes", "r", "c", "f", "place"))):
                    space = Space(*(x.values.to_numpy() for x in row))
                    out: list[tuple] = []
                    for q in queries[share.as_py() :: shares]:
                        t = Task(space, q, spec, k, solver, corners, floors.get(q.query_id, -np.inf), per_image)
                        visit(t, **how)
                        i, dr, dc = t.offsets(t.at)
                        none = (None,) * (len(COUNTERS) + len(CLOCKS))
                        out += [(q.query_id, *x, int(m).bit_count(), m, *none) for *x, m in zip(space.ids[i].tolist(), dr.tolist(), dc.tolist(), t.score.tolist(), t.mask.tolist())]
                        out.append((q.query_id, *(None,) * 6, *t.count.values(), *t.clock.values()))
                    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.float64(), pa.int32(), pa.int64(), *(pa.int64() for _ in COUNTERS), *(pa.float64() for _ in CLOCKS)]
                    names = [x.split()[0] for x in FOUND.split(", ")]
                    yield pa.RecordBatch.from_arrays([pa.array(list(x), y) for x, y in zip(zip(*out), kinds)], names)

        rows = rows.select(F.explode(F.sequence(F.lit(0), F.lit(shares - 1))).alias("share"), "ids", "sizes", "r", "c", "f", "place")
        # what is read in about as many parts as there are cores keeps some of them waiting for two parts' walks
        if rows.rdd.getNumPartitions() < min(shards * shares, tasks):
            rows = rows.repartition(min(shards * shares, tasks))
        return rows.mapInArrow(run, FOUND)

    def search(self, queries: list[Query], k: int, spec: ScoreSpec, algorithm: str = "frontier", solver: str = "corner_dp", corners=solvers.CORNERS, per_image: bool = False, early: bool | None = None, **how) -> DataFrame:
        """Saved rows of `walk` over all shards (`per_image`: an image's best alignment alone counts);
        `counters` sums them up.  `early`: a sixteenth of many shards goes first (not for scans, if not said)."""
        if any(self.features and q.features.shape[1] != self.features for q in queries):
            raise ValueError("query and tiles differ in dimension")
        spark = self.rows.sparkSession
        if early is None:
            early = not algorithm.startswith("scan")
        if not early or self.n <= 2 * spark.sparkContext.defaultParallelism:
            return saved(self.walk(self.rows, queries, k, spec, algorithm, solver, corners, {}, per_image, how))
        first = F.col("shard") % 16 == 0  # shards are dealt by hash; the first is among them
        seed = saved(self.walk(self.rows.filter(first), queries, k, spec, algorithm, solver, corners, {}, per_image, how, -(-self.n // 16)))
        # one number for each query: the k-th score among the first shards' results
        place = F.row_number().over(_by_score())
        tops = seed.filter("image_id IS NOT NULL").withColumn("place", place).filter(F.col("place") == k).select("query_id", "score").collect()
        rest = self.walk(self.rows.filter(~first), queries, k, spec, algorithm, solver, corners, {r[0]: r[1] for r in tops}, per_image, how)
        return saved(rest).union(seed)


def _by_score():
    from pyspark.sql import Window

    return Window.partitionBy("query_id").orderBy(F.desc("score"), "image_id", "dr", "dc")


def hits_of(found: DataFrame) -> DataFrame:
    return found.filter("image_id IS NOT NULL").select("query_id", "image_id", "dr", "dc", "score", "n_cells", "mask")


def counters(found: DataFrame) -> DataFrame:
    """query_id and the sums of its shards' counters (the longest queue for max_queue)."""
    own = found.filter("image_id IS NULL")
    return own.groupBy("query_id").agg(*[(F.max(x) if x == "max_queue" else F.sum(x)).alias(x) for x in (*COUNTERS, *CLOCKS)])


def store_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark).rstrip('/')}/{name}"
