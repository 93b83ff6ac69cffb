"""What the searches share: options, results, and solving alignments next to their images.

An image's tiles travel as one row (`canvas`); a task computes each distance of an image once
and slices it for every alignment.  Only k rows of a task leave it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..carriers.grids import feature_columns
from ..overlap.placements import Query
from ..region import solvers
from ..score.functions import ScoreSpec

HITS = "query_id long, image_id long, dr int, dc int, score double, n_cells int, mask long"


def order() -> tuple:
    """Best first: higher score, then image, row and column offset."""
    return F.desc("score"), F.asc("image_id"), F.asc("dr"), F.asc("dc")


@dataclass
class SearchStats:
    algorithm: str
    solved: int = 0
    rounds: int = 0
    opened: int = 0
    max_queue: int = 0
    accesses: int = 0
    distances: int = 0
    nn_seconds: float = 0.0
    solve_seconds: float = 0.0
    admitted: int = 0


@dataclass
class SearchResult:
    df: DataFrame
    stats: SearchStats = field(default_factory=lambda: SearchStats(""))


def canvas(tiles: DataFrame) -> DataFrame:
    """image_id, tiles: one row for each image.  Images are rasters of bounded size; the tile
    store keeps them clustered, so a stored canvas needs no exchange."""
    f = feature_columns(tiles)
    return tiles.groupBy("image_id").agg(F.collect_list(F.struct("r", "c", *[F.col(x).cast("double").alias(x) for x in f])).alias("tiles"))


class ImageScores:
    """All alignments' matrices of one image: (O, n) with NaN where there is no tile."""

    def __init__(self, r: np.ndarray, c: np.ndarray, f: np.ndarray, query: Query, spec: ScoreSpec):
        h, w = query.h, query.w
        rows, cols = int(r.max()) + 1, int(c.max()) + 1
        self.lo, self.shape = (1 - h, 1 - w), (rows + h - 1, cols + w - 1)
        grid = np.full((query.n, rows + 2 * h - 2, cols + 2 * w - 2), np.nan)
        d = np.stack([spec.distance(f, q) for q in query.features])
        grid[:, r + h - 1, c + w - 1] = spec.numpy(query.bg[:, None], d)
        parts = [grid[i, i // w : i // w + self.shape[0], i % w : i % w + self.shape[1]].ravel() for i in range(query.n)]
        self.matrix = np.stack(parts, 1)
        at = np.indices(self.shape)
        self.dr, self.dc = at[0].ravel() + self.lo[0], at[1].ravel() + self.lo[1]

    def rows_of(self, dr: np.ndarray, dc: np.ndarray) -> np.ndarray:
        return (dr - self.lo[0]) * self.shape[1] + dc - self.lo[1]


def best_rows(dr, dc, matrix, query: Query, solver: str, corners, k: int | None, floor: float, min_cells: int, inside) -> tuple:
    """Solve the alignments whose safe bound reaches `floor` and the k-th best found so far,
    best bounds first; (dr, dc, score, mask, solved)."""
    live = (~np.isnan(matrix)).sum(1) >= max(1, min_cells)
    if inside is not None:
        live &= inside
    at = np.flatnonzero(live)
    bound = solvers.positive_sum(matrix[at])
    at, bound = at[bound >= floor], bound[bound >= floor]
    order = np.argsort(-bound, kind="stable")
    got_s, got_m, got_i = np.zeros(0), np.zeros(0, np.int64), np.zeros(0, np.int64)
    step, x = max(64, 2 * (k or 0)), 0
    while x < len(order):
        part = at[order[x : x + step]]
        if k is not None and len(got_s) >= k and bound[order[x]] < np.sort(got_s)[-k]:
            break
        s, m = solvers.solve(matrix[part], query.h, query.w, solver, corners)
        got_s, got_m, got_i = np.concatenate([got_s, s]), np.concatenate([got_m, m]), np.concatenate([got_i, part])
        x += step
    solved = len(got_s)
    keep = np.flatnonzero(got_s >= floor)
    if k is not None:
        keep = keep[np.lexsort((dc[got_i[keep]], dr[got_i[keep]], -got_s[keep]))[:k]]
    i = got_i[keep]
    return dr[i], dc[i], got_s[keep], got_m[keep], solved


def solve_canvases(canvases: DataFrame, queries: list[Query], spec: ScoreSpec, k: int | None, solver: str = "corner_dp", corners=solvers.CORNERS, floor: float = -np.inf, overlap: str = "overhang", min_cells: int = 1, exclude_self: bool = False, only: bool = False, prune: bool = True, counts: bool = False) -> DataFrame:
    """Best k alignments of each image for each query (all that reach `floor` for k=None).

    `only`: the canvas rows carry `at`, an array of (query_id, dr, dc), and nothing else is
    solved.  `counts`: rows are (query_id, image_id, solved) instead."""
    names = feature_columns_of(canvases)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            flat, ends = b.column("tiles").flatten(), b.column("tiles").value_lengths().to_numpy().cumsum()
            every_r, every_c = (flat.field(x).to_numpy().astype(np.int64) for x in ("r", "c"))
            every_f = np.stack([flat.field(x).to_numpy() for x in names], 1)
            wanted = b.column("at").to_pylist() if only else None
            for row, (image_id, end) in enumerate(zip(b.column("image_id").to_pylist(), ends.tolist())):
                own_tiles = slice(int(ends[row - 1]) if row else 0, end)
                r, c, f = every_r[own_tiles], every_c[own_tiles], every_f[own_tiles]
                for q in queries:
                    if exclude_self and q.source == image_id:
                        continue
                    s = ImageScores(r, c, f, q, spec)
                    dr, dc, m, inside = s.dr, s.dc, s.matrix, None
                    if overlap == "inside":
                        inside = (dr >= 0) & (dc >= 0) & (dr + q.h <= r.max() + 1) & (dc + q.w <= c.max() + 1)
                    if only:
                        own = np.array([(x["dr"], x["dc"]) for x in wanted[row] if x["query_id"] == q.query_id], np.int64).reshape(-1, 2)
                        at = s.rows_of(own[:, 0], own[:, 1])
                        dr, dc, m, inside = dr[at], dc[at], m[at], None if inside is None else inside[at]
                    if not len(dr):
                        continue
                    a, d, score, mask, solved = best_rows(dr, dc, m, q, solver, corners, k if prune else None, floor, min_cells, inside)
                    if counts:
                        out.append((q.query_id, image_id, solved))
                        continue
                    if k is not None and not prune:
                        top = np.lexsort((d, a, -score))[:k]
                        a, d, score, mask = a[top], d[top], score[top], mask[top]
                    out += [(q.query_id, image_id, int(x), int(y), float(z), int(n).bit_count(), int(n)) for x, y, z, n in zip(a, d, score, mask)]
            kinds = [pa.int64(), pa.int64(), pa.int64()] if counts else [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.float64(), pa.int32(), pa.int64()]
            cols = list(zip(*out)) if out else [[] for _ in kinds]
            labels = ["query_id", "image_id", "solved"] if counts else ["query_id", "image_id", "dr", "dc", "score", "n_cells", "mask"]
            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(cols, kinds)], labels)

    return canvases.mapInArrow(run, "query_id long, image_id long, solved long" if counts else HITS)


def feature_columns_of(canvases: DataFrame) -> list[str]:
    fields = canvases.schema["tiles"].dataType.elementType.fieldNames()
    return sorted((x for x in fields if x[0] == "f" and x[1:].isdigit()), key=lambda x: int(x[1:]))


def with_alignments(canvases: DataFrame, align: DataFrame) -> DataFrame:
    """Canvases of the images that `align` (query_id, image_id, dr, dc) names, with their alignments."""
    at = align.groupBy("image_id").agg(F.collect_set(F.struct("query_id", "dr", "dc")).alias("at"))
    return canvases.join(at, "image_id")


def ranked(hits: DataFrame, k: int, per_image: bool = False, single: bool = True) -> DataFrame:
    """Add `rank` and keep k for each query; one query is a bounded top-k, not a sort."""
    if per_image:
        w = Window.partitionBy("query_id", "image_id").orderBy(*order())
        hits = hits.withColumn("_i", F.row_number().over(w)).filter("_i = 1").drop("_i")
    if single:
        hits = hits.orderBy(*order()).limit(k)
    w = Window.partitionBy("query_id").orderBy(*order())
    return hits.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def kth(hits: DataFrame, k: int) -> float:
    """The k-th best score (one number), -inf with fewer hits."""
    got = [x[0] for x in hits.orderBy(F.desc("score")).limit(k).select("score").collect()]
    return got[-1] if len(got) == k else -np.inf
