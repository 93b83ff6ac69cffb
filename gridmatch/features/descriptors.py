"""Descriptors and dimension reduction.

Texts become rasters (64 characters a row, code points as gray values), cut into 8 x 8 tiles;
a tile's structure histogram counts in how many 3 x 3 windows each level occurs.  PCA needs one
pass: each task adds up a D x D moment matrix, the driver solves the eigenproblem."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WIDTH, TILE, LEVELS, WIN = 64, 8, 256, 3


def glyph_tiles(texts: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, tile: int = TILE, edge: str = "drop") -> DataFrame:
    """image_id, r, c, bg (sum of pixels), px (the tile's pixels in order) of every text's raster.

    Characters become pixels in the Arrow batch, so only whole tiles leave it.  `edge`: `drop` cuts
    an unfinished band of lines off, `pad` fills it with zeros.  Null texts have no tiles."""
    if edge not in ("drop", "pad"):
        raise ValueError("edge is drop or pad")
    band = width * tile

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for image, text in zip(b.column("image_id"), b.column("text")):
                px = np.frombuffer((text.as_py() or "").encode("utf-32-le"), "<u4") % LEVELS
                if edge == "pad":
                    px = np.pad(px, (0, -len(px) % band))
                bands = len(px) // band
                for at in range(0, bands, 1024):  # a very long text goes out in parts
                    part = px[at * band : min(at + 1024, bands) * band].astype(np.int32)
                    grid = part.reshape(-1, tile, width // tile, tile).transpose(0, 2, 1, 3).reshape(-1, tile * tile)
                    r, c = np.divmod(np.arange(len(grid)), width // tile)
                    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(grid) + 1, dtype=np.int32) * tile**2), pa.array(grid.ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array([image.as_py()] * len(grid), pa.int64()), pa.array((r + at).astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(grid.sum(1).astype(np.int64)), lists], ["image_id", "r", "c", "bg", "px"])

    return texts.select(F.col(id_col).cast("long").alias("image_id"), F.col(text_col).alias("text")).mapInArrow(run, "image_id long, r int, c int, bg long, px array<int>")


def binary_tiles(files: DataFrame, width: int, tile: int = TILE) -> DataFrame:
    """The same for raw 8-bit gray images as Spark's `binaryFile` source reads them (path, content);
    image_id is a hash of the path, and incomplete border tiles go."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for image, raw in zip(b.column("image_id"), b.column("content")):
                px = np.frombuffer(raw.as_py() or b"", np.uint8)
                lines, across = len(px) // width // tile * tile, width // tile
                grid = px[: lines * width].reshape(lines, width)[:, : across * tile].astype(np.int32)
                grid = grid.reshape(-1, tile, across, tile).transpose(0, 2, 1, 3).reshape(-1, tile * tile)
                r, c = np.divmod(np.arange(len(grid)), max(across, 1))
                yield pa.RecordBatch.from_arrays([pa.array([image.as_py()] * len(grid), pa.int64()), pa.array(r.astype(np.int32)), pa.array(c.astype(np.int32)), pa.array(grid.sum(1).astype(np.int64)), pa.array(list(grid), pa.list_(pa.int32()))], ["image_id", "r", "c", "bg", "px"])

    return files.select(F.xxhash64("path").alias("image_id"), "content").mapInArrow(run, "image_id long, r int, c int, bg long, px array<int>")


def structure_histogram(px: np.ndarray, tile: int = TILE, win: int = WIN) -> np.ndarray:
    """Share of the window positions where each level occurs: rows x LEVELS."""
    grid = px.reshape(-1, tile, tile)
    at = tile - win + 1
    first = np.arange(len(grid))[:, None] * LEVELS
    out = np.zeros(len(grid) * LEVELS, np.uint16)
    for y in range(at):
        for x in range(at):
            seen = np.zeros(len(grid) * LEVELS, bool)
            seen[(grid[:, y : y + win, x : x + win].reshape(len(grid), -1) + first).ravel()] = True
            out += seen
    return out.reshape(-1, LEVELS) / at**2


def level_histogram(px: np.ndarray) -> np.ndarray:
    """Share of the pixels at each level: rows x LEVELS."""
    out = np.zeros((len(px), LEVELS))
    np.add.at(out, (np.repeat(np.arange(len(px)), px.shape[1]), px.ravel()), 1 / px.shape[1])
    return out


def moments_descriptor(px: np.ndarray) -> np.ndarray:
    """Mean, deviation, and mean steps across and down: rows x 4."""
    side = int(np.sqrt(px.shape[1]))
    g = px.reshape(-1, side, side).astype(float)
    return np.stack([g.mean((1, 2)), g.std((1, 2)), np.abs(np.diff(g, axis=2)).mean((1, 2)), np.abs(np.diff(g, axis=1)).mean((1, 2))], 1)


DESCRIPTORS: dict[str, Callable[[np.ndarray], np.ndarray]] = {"structure": structure_histogram, "levels": level_histogram, "moments": moments_descriptor}


def register_descriptor(name: str, f: Callable[[np.ndarray], np.ndarray]) -> None:
    """Make `f` (rows x pixels -> rows x D) usable in `describe`; it must be importable on the workers."""
    DESCRIPTORS[name] = f


def describe(tiles: DataFrame, descriptor: str = "structure", model: PcaModel | None = None, dim: int = 0) -> DataFrame:
    """image_id, r, c, bg, fv (the descriptor's D numbers); with a model f0..f{dim-1} instead, projected
    in the same batch, so that D numbers a tile never leave the worker."""
    f = DESCRIPTORS[descriptor]
    names = ["fv"] if model is None else [f"f{i}" for i in range(dim)]
    mean, comp = (None, None) if model is None else (model.mean, model.components[:dim].T)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, 500):
                part = b.slice(a, 500)
                h = f(part.column("px").flatten().to_numpy().astype(np.int64).reshape(part.num_rows, -1))
                if model is None:
                    out = [pa.ListArray.from_arrays(pa.array(np.arange(len(h) + 1, dtype=np.int32) * h.shape[1]), pa.array(h.ravel()))]
                else:
                    out = [pa.array(x) for x in ((h - mean) @ comp).T]
                yield pa.RecordBatch.from_arrays([*(part.column(n) for n in ("image_id", "r", "c", "bg")), *out], ["image_id", "r", "c", "bg", *names])

    kind = "array<double>" if model is None else "double"
    return tiles.select("image_id", "r", "c", "bg", "px").mapInArrow(run, "image_id long, r int, c int, bg long, " + ", ".join(f"{x} {kind}" for x in names))


@dataclass
class PcaModel:
    mean: np.ndarray
    components: np.ndarray  # D x D, best first
    variance: np.ndarray

    def energy(self, dim: int) -> float:
        return float(self.variance[:dim].sum() / self.variance.sum())


def moments(df: DataFrame, column: str = "fv") -> DataFrame:
    """One row for each task: count, sum and sum of outer products (D and D*D numbers)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, g = 0, None, None
        for b in batches:
            if b.num_rows:
                x = b.column(column).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(b.num_rows, -1)
                n, s, g = n + len(x), x.sum(0) + (0 if s is None else s), x.T @ x + (0 if g is None else g)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([s.tolist()], pa.list_(pa.float64())), pa.array([g.ravel().tolist()], pa.list_(pa.float64()))], ["n", "s", "g"])

    return df.select(column).mapInArrow(run, "n long, s array<double>, g array<double>")


def fit_pca(df: DataFrame, column: str = "fv") -> PcaModel:
    parts = moments(df, column)
    one_row = df.select(F.size(column)).first()
    if one_row is None:
        raise ValueError("PCA needs rows")
    size = one_row[0]
    one = parts.select(F.posexplode(F.concat(F.array(F.col("n").cast("double")), "s", "g")).alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v"))
    v = np.zeros(1 + size + size * size)
    for r in one.collect():  # 1 + D + D*D numbers, whatever the data
        v[r["i"]] = r["v"]
    n, mean = v[0], v[1 : size + 1] / v[0]
    cov = v[size + 1 :].reshape(size, size) / n - np.outer(mean, mean)
    val, vec = np.linalg.eigh(cov)
    return PcaModel(mean, vec[:, ::-1].T, np.maximum(val[::-1], 0))


def project(df: DataFrame, model: PcaModel, dim: int, column: str = "fv") -> DataFrame:
    """f0..f{dim-1} instead of the vector; unrolled arithmetic for small D, Arrow for large."""
    mean, comp = model.mean, model.components[:dim]
    keep = [c for c in df.columns if c != column]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column(column).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(b.num_rows, -1)
            y = (x - mean) @ comp.T
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keep), *(pa.array(c) for c in y.T)], [*keep, *(f"f{i}" for i in range(dim))])

    schema = df.select(*keep).schema
    for i in range(dim):
        schema = schema.add(f"f{i}", "double")
    return df.select(*keep, column).mapInArrow(run, schema)


def standardize(df: DataFrame, features: list[str]) -> DataFrame:
    """Zero mean and unit deviation for each feature (one summary row is broadcast)."""
    s = df.agg(*[F.avg(f).alias(f"m_{f}") for f in features], *[F.stddev_samp(f).alias(f"d_{f}") for f in features])
    out = df.crossJoin(F.broadcast(s))
    for f in features:
        out = out.withColumn(f, (F.col(f) - F.col(f"m_{f}")) / F.when(F.col(f"d_{f}") > 0, F.col(f"d_{f}")).otherwise(F.lit(1.0)))
    return out.select(*df.columns)


def bg_to_vector(fv: Column, b: list[float]) -> Column:
    """Distance of a vector column to a constant background."""
    return F.aggregate(F.zip_with(fv, F.array(*map(F.lit, b)), lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)


def learn_background(tiles: DataFrame, features: list[str]) -> DataFrame:
    """The mean of the tenth of the tiles with the least bg: one row of features."""
    cut = tiles.agg(F.percentile_approx("bg", 0.1, 10000).alias("cut"))
    return tiles.crossJoin(F.broadcast(cut)).filter(F.col("bg") <= F.col("cut")).agg(*[F.avg(f).alias(f) for f in features])
