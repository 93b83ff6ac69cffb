"""Alignments of a query on images, and their score matrices, as DataFrames.

An alignment (image_id, dr, dc) puts query cell (qr, qc) on image cell (qr + dr, qc + dc)."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..carriers.grids import feature_columns
from ..score.functions import ScoreSpec, dist


@dataclass(frozen=True)
class Query:
    """A small tiled image on the driver: features n x D and bg n, row-major, row 0 at the bottom."""

    h: int
    w: int
    features: np.ndarray
    bg: np.ndarray
    query_id: int = 0
    source: int | None = None
    names: tuple[str, ...] = field(default=())

    def __post_init__(self):
        if self.h * self.w > 62:
            raise ValueError("a query has 62 cells at most")
        if np.isnan(self.features).any() or np.isnan(self.bg).any():
            raise ValueError("query features must not be NULL or NaN")

    @property
    def n(self) -> int:
        return self.h * self.w

    @property
    def whole(self) -> bool:
        """Are all values whole numbers, so that scores can be BIGINT?"""
        return bool((self.features % 1 == 0).all() and (self.bg % 1 == 0).all())

    @classmethod
    def from_rows(cls, rows: list[dict], h: int, w: int, query_id: int = 0, source: int | None = None) -> Query:
        names = sorted((k for k in rows[0] if k[0] == "f" and k[1:].isdigit()), key=lambda k: int(k[1:]))
        f, bg = np.full((h * w, len(names)), np.nan), np.full(h * w, np.nan)
        for x in rows:
            f[x["r"] * w + x["c"]], bg[x["r"] * w + x["c"]] = [x[k] for k in names], x["bg"]
        return cls(h, w, f, bg, query_id, source, tuple(names))

    @classmethod
    def from_image(cls, tiles: DataFrame, image_id: int, r0: int, c0: int, h: int, w: int, query_id: int = 0) -> Query:
        inside = (F.col("image_id") == image_id) & F.col("r").between(r0, r0 + h - 1) & F.col("c").between(c0, c0 + w - 1)
        rows = [x.asDict() | {"r": x["r"] - r0, "c": x["c"] - c0} for x in tiles.filter(inside).collect()]  # h*w rows
        if len(rows) != h * w:
            raise ValueError("the patch leaves the image or has holes")
        return cls.from_rows(rows, h, w, query_id, image_id)


def query_tiles(spark, query: Query) -> DataFrame:
    """query_id, q (cell number), qr, qc, qbg, q0..q{D-1}: n rows."""
    kind = "bigint" if query.whole else "double"
    cast = int if query.whole else float
    rows = [(query.query_id, i, i // query.w, i % query.w, cast(query.bg[i]), *map(cast, query.features[i])) for i in range(query.n)]
    return spark.createDataFrame(rows, f"query_id bigint, q int, qr int, qc int, qbg {kind}, " + ", ".join(f"q{j} {kind}" for j in range(query.features.shape[1])))


def image_shapes(tiles: DataFrame) -> DataFrame:
    return tiles.groupBy("image_id").agg((F.max("r") + 1).alias("n_rows"), (F.max("c") + 1).alias("n_cols"))


def enumerate_overlaps(shapes: DataFrame, h: int, w: int, mode: str = "overhang") -> DataFrame:
    """image_id, dr, dc of every translation that shares a cell with the image's rectangle."""
    inside = mode == "inside"
    lo_r, lo_c = (0, 0) if inside else (1 - h, 1 - w)
    hi_r = F.col("n_rows") - (h if inside else 1)
    hi_c = F.col("n_cols") - (w if inside else 1)
    ok = shapes.filter((hi_r >= lo_r) & (hi_c >= lo_c))
    return ok.select("image_id", F.explode(F.sequence(F.lit(lo_r), hi_r.cast("int"))).alias("dr"), hi_c.alias("hi")).select("image_id", "dr", F.explode(F.sequence(F.lit(lo_c), F.col("hi").cast("int"))).alias("dc"))


def overlap_count(shapes: DataFrame, h: int, w: int) -> DataFrame:
    return shapes.agg(F.sum((F.col("n_rows") + h - 1) * (F.col("n_cols") + w - 1)).cast("long").alias("overlaps"))


def pairs(tiles: DataFrame, queries: DataFrame, metric: str = "l1") -> DataFrame:
    """Every (tile, query tile): the query side is broadcast (a few hundred rows at most)."""
    f = feature_columns(tiles)
    d = dist([F.col(x) for x in f], [F.col(f"q{i}") for i in range(len(f))], metric)
    return tiles.crossJoin(F.broadcast(queries)).withColumn("dist", d).withColumns({"dr": F.col("r") - F.col("qr"), "dc": F.col("c") - F.col("qc")})


def cells(tiles: DataFrame, queries: DataFrame, spec: ScoreSpec) -> DataFrame:
    """query_id, image_id, dr, dc, q, qr, qc, dist, score."""
    p = pairs(tiles, queries, spec.metric)
    return p.withColumn("score", spec.column(F.col("qbg"), F.col("dist"))).select("query_id", "image_id", "dr", "dc", "q", "qr", "qc", "dist", "score")


def matrices(cell_rows: DataFrame, n: int, value: str = "score", keys: tuple[str, ...] = ("query_id", "image_id", "dr", "dc")) -> DataFrame:
    """One row for each alignment with s0..s{n-1}: one hash aggregation of fixed-width buffers."""
    return cell_rows.groupBy(*keys).agg(*[F.max(F.when(F.col("q") == i, F.col(value))).alias(f"s{i}") for i in range(n)])


def dihedral(query: Query) -> list[Query]:
    """The query and its rotations and reflections (distinct shapes of one batch; query_id = 0..7)."""
    grid = np.arange(query.n).reshape(query.h, query.w)
    out = []
    for k, g in enumerate(x for turn in range(4) for x in (np.rot90(grid, turn), np.fliplr(np.rot90(grid, turn)))):
        i = g.ravel()
        out.append(Query(g.shape[0], g.shape[1], query.features[i], query.bg[i], k, query.source, query.names))
    return out
