"""The searches.  All return the same rows under a safe bound.

scan: every alignment of every image, next to the image.
scan_sql: the same in DataFrame expressions only.
bound_verify: one hash aggregation bounds every alignment, few are solved.
range_search: every region of a score or more.
whole_overlap: ranks alignments by total distance, no regions (a baseline).
threshold: rounds of sorted access for each query tile, until nothing unseen can win (in shards).
frontier: best-first over each shard's tree, with deferred pairs.
radius: a first wave's k-th score becomes a radius; one filtered job follows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..carriers.grids import feature_columns
from ..durable import saved
from ..index.packed import PackedIndex
from ..overlap.placements import Query, cells, matrices, pairs, query_tiles
from ..region import expressions, solvers
from ..score.functions import ScoreSpec
from .core import SearchResult, SearchStats, canvas, kth, ranked, solve_canvases, with_alignments
from .shards import Shards, counters, hits_of


def _check(k: int, query: Query, spec: ScoreSpec, tiles: DataFrame) -> None:
    if k < 1:
        raise ValueError("k must be at least 1")
    if query.features.shape[1] != len(feature_columns(tiles)):
        raise ValueError("query and tiles differ in dimension")


def scan(tiles: DataFrame, queries: Query | list[Query], k: int, spec: ScoreSpec, solver: str = "corner_dp", per_image: bool = False, canvases: DataFrame | None = None, **how) -> SearchResult:
    qs = queries if isinstance(queries, list) else [queries]
    for q in qs:
        _check(k, q, spec, tiles)
    hits = solve_canvases(canvases if canvases is not None else canvas(tiles), qs, spec, k, solver, **how)
    return SearchResult(ranked(hits, k, per_image, len(qs) == 1), SearchStats("scan", rounds=1))


def scan_sql(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, solver: str = "corner_dp", corners=solvers.CORNERS) -> SearchResult:
    """No Python worker: broadcast query tiles, one aggregation to wide rows, unrolled sweeps."""
    _check(k, query, spec, tiles)
    wide = matrices(cells(tiles, query_tiles(tiles.sparkSession, query), spec), query.n)
    solve = expressions.exact if solver == "exact" else lambda d, h, w: expressions.corner_dp(d, h, w, corners)
    hits = solve(wide, query.h, query.w).select("query_id", "image_id", "dr", "dc", "score", "n_cells", "mask")
    return SearchResult(ranked(hits, k), SearchStats("scan_sql", rounds=1))


def overlap_bounds(tiles: DataFrame, query: Query, spec: ScoreSpec) -> DataFrame:
    """query_id, image_id, dr, dc, bound: no region of the alignment scores more."""
    c = cells(tiles, query_tiles(tiles.sparkSession, query), spec)
    g = c.groupBy("query_id", "image_id", "dr", "dc").agg(F.sum(F.greatest("score", F.lit(0))).alias("p"), F.max("score").alias("m"))
    return g.select("query_id", "image_id", "dr", "dc", F.when(F.col("m") > 0, F.col("p")).otherwise(F.col("m")).alias("bound"))


def bound_verify(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, solver: str = "corner_dp", floor: float = -np.inf, first: int | None = None, per_image: bool = False) -> SearchResult:
    """Solve the `first` best bounds for a k-th score; then only alignments whose bound reaches it."""
    _check(k, query, spec, tiles)
    bounds, canvases = saved(overlap_bounds(tiles, query, spec)), canvas(tiles)
    stats = SearchStats("bound_verify", rounds=2)
    head = bounds.orderBy(F.desc("bound"), "image_id", "dr", "dc").limit(first or 4 * k)
    tau = max(floor, kth(_solve(canvases, head, query, spec, solver), k)) if not per_image else floor
    rest = bounds.filter(F.col("bound") >= F.lit(float(tau))) if tau > -np.inf else bounds
    stats.solved = stats.admitted = rest.count()
    return SearchResult(ranked(_solve(canvases, rest, query, spec, solver, floor), k, per_image), stats)


def _solve(canvases: DataFrame, align: DataFrame, query: Query, spec: ScoreSpec, solver: str, floor: float = -np.inf) -> DataFrame:
    return solve_canvases(with_alignments(canvases, align.select("query_id", "image_id", "dr", "dc")), [query], spec, None, solver, floor=floor, only=True)


def range_search(tiles: DataFrame, query: Query, theta: float, spec: ScoreSpec, solver: str = "corner_dp") -> DataFrame:
    admitted = overlap_bounds(tiles, query, spec).filter(F.col("bound") >= F.lit(float(theta)))
    return _solve(canvas(tiles), admitted, query, spec, solver, theta)


def whole_overlap(tiles: DataFrame, query: Query, k: int, metric: str = "l1", min_cells: int | None = None) -> DataFrame:
    """Alignments by mean distance of all aligned tiles (at least `min_cells`, all by default)."""
    p = pairs(tiles, query_tiles(tiles.sparkSession, query), metric)
    g = p.groupBy("query_id", "image_id", "dr", "dc").agg(F.sum("dist").alias("total"), F.count("*").alias("n_cells")).filter(F.col("n_cells") >= (min_cells or query.n))
    mean = F.col("total") / F.col("n_cells")
    top = g.withColumn("mean_dist", mean).orderBy("mean_dist", "image_id", "dr", "dc").limit(k)
    return top.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("mean_dist", "image_id", "dr", "dc")))


def uniform_bound(query: Query, spec: ScoreSpec, d: np.ndarray) -> np.ndarray:
    """Safe bound of a matrix whose cells all have distance d: falls as d grows."""
    d = np.atleast_1d(np.asarray(d, float))
    return solvers.positive_sum(spec.numpy(query.bg[None, :], np.repeat(d[:, None], query.n, 1)))


def radius_for(query: Query, spec: ScoreSpec, tau: float, most: float = 1e12) -> float:
    """The largest distance at which the uniform bound still reaches `tau` (rounded up)."""
    if tau == -np.inf or uniform_bound(query, spec, most)[0] >= tau:
        return np.inf
    lo, hi = 0.0, most
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if uniform_bound(query, spec, mid)[0] >= tau else (lo, mid)
        if hi - lo < 1e-9 * max(1, hi):
            break
    return hi


def _alignments(found: DataFrame) -> DataFrame:
    return found.select("query_id", "image_id", "dr", "dc").distinct()


def radius(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, index: PackedIndex | None = None, solver: str = "corner_dp") -> SearchResult:
    """A region of score tau has an aligned pair within the radius of tau, so two jobs do."""
    _check(k, query, spec, tiles)
    index = index or PackedIndex.build(tiles)
    canvases, qt = canvas(tiles), query_tiles(tiles.sparkSession, query)
    first = index.nearest_leaves(query, spec, 2 * query.n)
    near = pairs(index.inside(first).drop("leaf_id"), qt, spec.metric)
    seed = near.orderBy("dist", "image_id", "r", "c", "q").limit(4 * k * query.n)
    tau = kth(_solve(canvases, _alignments(seed), query, spec, solver), k)
    r = radius_for(query, spec, tau)
    rows = index.within(query, spec, r)
    found = pairs(rows, qt, spec.metric)
    align = _alignments(found if r == np.inf else found.filter(F.col("dist") <= r))
    align = saved(align)
    return SearchResult(ranked(_solve(canvases, align, query, spec, solver, tau), k), SearchStats("radius", solved=align.count(), rounds=2))


def _walked(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, shards: Shards | None, algorithm: str, solver: str, **how) -> SearchResult:
    _check(k, query, spec, tiles)
    shards = shards or Shards.build(tiles)
    found = shards.search([query], k, spec, algorithm, solver, **how)
    c = counters(found).first()
    stats = SearchStats(algorithm, *((c["solved"], c["rounds"], c["popped"], c["max_queue"], c["accesses"], c["distances"], c["nn_seconds"], c["solve_seconds"]) if c else ()))
    return SearchResult(ranked(hits_of(found), k), stats)


def threshold(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, shards: Shards | None = None, batch: int = 64, doubling: bool = True, bound: str = "positive_sum", solver: str = "corner_dp") -> SearchResult:
    """Sorted access, beside each shard: a round reads the next `batch` nearest tiles of every query
    tile (twice as many each time if `doubling`), solves their new alignments, and bounds the unseen
    ones by the matrix of the last distances seen."""
    return _walked(tiles, query, k, spec, shards, "threshold", solver, batch=batch, doubling=doubling, bound=bound)


def frontier(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, shards: Shards | None = None, wave: int = 256, growing: bool = True, defer: bool = True, solver: str = "corner_dp") -> SearchResult:
    """Best-first down each shard's tree: inner boxes, leaves and (tile, query tile) pairs share one
    queue; alignments are solved `wave` at a time, and what cannot reach the k-th score ends it."""
    return _walked(tiles, query, k, spec, shards, "frontier", solver, wave=wave, growing=growing, defer=defer)


def auto(tiles: DataFrame, query: Query, k: int, spec: ScoreSpec, cut: int = 20, admit: float = 0.3, **how) -> SearchResult:
    """Threshold for small queries, frontier for large ones; bound-and-verify where a sample says
    that the radius of a good score admits most pairs anyway."""
    sample = tiles.filter(F.pmod(F.xxhash64("image_id"), F.lit(16)) == 0)
    p = pairs(sample, query_tiles(tiles.sparkSession, query), spec.metric)
    r = radius_for(query, spec, float(solvers.positive_sum(spec.numpy(query.bg, np.zeros(query.n))[None, :])[0]) / 2)
    share = p.agg(F.avg((F.col("dist") <= F.lit(r)).cast("double"))).first()[0] or 0.0
    if share > admit / query.n:
        return bound_verify(tiles, query, k, spec, **how)
    return threshold(tiles, query, k, spec, **how) if query.n <= cut else frontier(tiles, query, k, spec, **how)


ALGORITHMS = {"scan": scan, "scan_sql": scan_sql, "threshold": threshold, "frontier": frontier, "radius": radius, "bound_verify": bound_verify, "auto": auto}


def search(tiles: DataFrame, query: Query, k: int = 10, *, spec: ScoreSpec, algorithm: str = "auto", **how) -> SearchResult:
    if algorithm not in ALGORITHMS:
        raise ValueError(f"unknown algorithm {algorithm}")
    return ALGORITHMS[algorithm](tiles, query, k, spec, **how)
