"""A bulk-packed box index kept as DataFrames: leaves (tile rows with leaf_id) and boxes.

Packing sorts by one feature after another: cut points of each feature split a slab into equal
parts (approximate quantiles on a summary, then narrow expressions), so tiles of a leaf are
close in all features.  Only boxes reach the driver, and at most `MAX_BOXES` of them; larger
stores keep coarser levels for the driver (see `nodes`).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..carriers.grids import feature_columns
from ..durable import saved
from ..overlap.placements import Query, pairs
from ..score.functions import ScoreSpec

MAX_BOXES = 20_000


def _below(feature: str) -> Callable:
    return lambda c: F.col(feature) > c


def str_pack(tiles: DataFrame, leaf_rows: int = 256, dims: int = 3, total: int | None = None) -> DataFrame:
    """`tiles` with leaf_id: sort-tile-recursive slabs over the first `dims` features."""
    f = feature_columns(tiles)[:dims]
    n = tiles.count() if total is None else total
    parts = max(1, round((n / leaf_rows) ** (1 / len(f))))
    out = tiles.withColumn("leaf_id", F.lit(0).cast("long"))
    for x in f:
        cuts = F.percentile_approx(x, [i / parts for i in range(1, parts)] or [0.5], 2000)
        slabs = out.groupBy("leaf_id").agg(cuts.alias("_cuts"))
        # one row for each slab so far: at most the number of leaves
        out = out.join(slabs, "leaf_id").withColumn("leaf_id", F.col("leaf_id") * parts + F.size(F.filter("_cuts", _below(x))).cast("long")).drop("_cuts")
    return out


def ntile_pack(tiles: DataFrame, parts: tuple[int, ...]) -> DataFrame:
    """Exact slabs in a total order (for checks on small data): ntile inside ntile."""
    out, keys = tiles, []
    for i, p in enumerate(parts):
        w = Window.partitionBy(*keys) if keys else Window.partitionBy(F.lit(0))
        out = out.withColumn(f"p{i}", F.ntile(p).over(w.orderBy(f"f{i}", "image_id", "r", "c")) - 1)
        keys.append(f"p{i}")
    leaf = F.lit(0)
    for i, p in enumerate(parts):
        leaf = leaf * p + F.col(f"p{i}")
    return out.withColumn("leaf_id", leaf.cast("long")).drop(*keys)


def morton_pack(tiles: DataFrame, leaf_rows: int = 256, bits: int = 8, dims: int = 3) -> DataFrame:
    """leaf_id from interleaved bits of scaled features: one exchange, no recursion."""
    f = feature_columns(tiles)[:dims]
    span = tiles.agg(F.count("*").alias("n"), *[F.min(x).alias(f"lo_{x}") for x in f], *[F.max(x).alias(f"hi_{x}") for x in f]).first()
    code = F.lit(0).cast("long")
    for i, x in enumerate(f):
        width = float(span[f"hi_{x}"] - span[f"lo_{x}"]) or 1.0
        q = F.least(F.lit((1 << bits) - 1), F.floor((F.col(x) - span[f"lo_{x}"]) / width * (1 << bits))).cast("long")
        for b in range(bits):
            code = code + F.shiftleft(F.shiftright(q, b).bitwiseAND(F.lit(1).cast("long")), b * len(f) + i)
    keep = max(0, len(f) * bits - max(1, int(span["n"] / leaf_rows)).bit_length())
    return tiles.withColumn("leaf_id", F.shiftright(code, keep))


def boxes(leaf: DataFrame, key: str = "leaf_id") -> DataFrame:
    f = feature_columns(leaf)
    return leaf.groupBy(key).agg(*[F.min(x).alias(f"lo_{x}") for x in f], *[F.max(x).alias(f"hi_{x}") for x in f], F.count("*").alias("n"))


def nodes(leaf_boxes: DataFrame, fanout: int = 16, levels: int = 2) -> DataFrame:
    """level, node_id, parent_id and box: level 0 are leaves, each level joins `fanout` of the one below."""
    lo = [c for c in leaf_boxes.columns if c.startswith("lo_")]
    hi = [c for c in leaf_boxes.columns if c.startswith("hi_")]
    up = lambda c: F.expr(f"{c} DIV {fanout}")
    level = leaf_boxes.select(F.lit(0).alias("level"), F.col("leaf_id").alias("node_id"), up("leaf_id").alias("parent_id"), *lo, *hi, "n")
    out = level
    for i in range(1, levels + 1):
        level = level.groupBy(F.col("parent_id").alias("node_id")).agg(*[F.min(x).alias(x) for x in lo], *[F.max(x).alias(x) for x in hi], F.sum("n").alias("n"))
        level = level.select(F.lit(i).alias("level"), "node_id", up("node_id").alias("parent_id"), *lo, *hi, "n")
        out = out.union(level)
    return out


@dataclass
class PackedIndex:
    leaf: DataFrame
    ids: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    counts: np.ndarray
    unit: int = 1  # leaves to a box on the driver

    @classmethod
    def build(cls, tiles: DataFrame, leaf_rows: int = 256, method: str = "str") -> PackedIndex:
        packed = str_pack(tiles, leaf_rows) if method == "str" else morton_pack(tiles, leaf_rows)
        return cls.of(saved(packed.repartitionByRange("leaf_id").sortWithinPartitions("leaf_id")))

    @classmethod
    def of(cls, leaf: DataFrame, most: int = MAX_BOXES, fanout: int = 16) -> PackedIndex:
        f, level, unit = feature_columns(leaf), boxes(leaf), 1
        while len(got := level.orderBy("leaf_id").limit(most + 1).collect()) > most:  # `most` + 1 boxes at most
            up = level.withColumn("leaf_id", F.expr(f"leaf_id DIV {fanout}")).groupBy("leaf_id")
            level = up.agg(*[F.min(f"lo_{x}").alias(f"lo_{x}") for x in f], *[F.max(f"hi_{x}").alias(f"hi_{x}") for x in f], F.sum("n").alias("n"))
            unit *= fanout
        col = lambda p: np.array([[float(x[f"{p}_{k}"]) for k in f] for x in got]).reshape(len(got), len(f))
        return cls(leaf, np.array([x["leaf_id"] for x in got]), col("lo"), col("hi"), np.array([x["n"] for x in got]), unit)

    def inside(self, ids) -> DataFrame:
        """The tiles of these boxes."""
        box = F.col("leaf_id") if self.unit == 1 else F.expr(f"leaf_id DIV {self.unit}")
        return self.leaf.filter(box.isin([int(i) for i in ids]))

    @property
    def rows(self) -> int:
        return int(self.counts.sum())

    def mindist(self, query: Query, spec: ScoreSpec) -> np.ndarray:
        """boxes x query tiles."""
        return np.stack([spec.mindist(q, self.lo, self.hi) for q in query.features], 1)

    def bounds(self, query: Query, spec: ScoreSpec, u: Callable) -> list[tuple[int, float]]:
        return list(zip(self.ids.tolist(), u(self.mindist(query, spec).min(1)).tolist()))

    def nearest_leaves(self, query: Query, spec: ScoreSpec, n: int) -> list[int]:
        return self.ids[np.argsort(self.mindist(query, spec).min(1), kind="stable")[:n]].tolist()

    def within(self, query: Query, spec: ScoreSpec, r: float) -> DataFrame:
        """Tiles of the boxes within r of any query tile: box pruning by leaf and by features."""
        near = self.mindist(query, spec).min(1) <= r
        rows = self.leaf
        if not near.all():
            rows = self.inside(self.ids[near])
        if np.isfinite(r):  # each feature lies within r of some query tile, whatever the metric
            for j, f in enumerate(feature_columns(rows)):
                rows = rows.filter(F.col(f).between(F.lit(float(query.features[:, j].min() - r)), F.lit(float(query.features[:, j].max() + r))))
        return rows.drop("leaf_id")

    def first_neighbours(self, query: Query, qt: DataFrame, spec: ScoreSpec, upto: int) -> DataFrame:
        """The `upto` nearest tiles of every query tile with `nn` (1 = nearest), from the boxes that
        can hold them: enough rows lie within the radius by the boxes' far corners."""
        parts = []
        for i, q in enumerate(query.features):
            far, near = spec.maxdist(q, self.lo, self.hi), spec.mindist(q, self.lo, self.hi)
            order = np.argsort(far, kind="stable")
            enough = np.searchsorted(np.cumsum(self.counts[order]), min(upto, self.rows))
            r = float(far[order[min(enough, len(order) - 1)]])
            rows = pairs(self.inside(self.ids[near <= r]).drop("leaf_id"), qt.filter(F.col("q") == i), spec.metric)
            top = rows.filter(F.col("dist") <= r).orderBy("dist", "image_id", "r", "c").limit(upto)
            parts.append(top.withColumn("nn", F.row_number().over(Window.partitionBy("q").orderBy("dist", "image_id", "r", "c"))))
        out = parts[0]
        for p in parts[1:]:
            out = out.union(p)
        return out.select("query_id", "q", "nn", "dist", "image_id", "r", "c", "dr", "dc")


def sorted_access(tiles: DataFrame, qt: DataFrame, spec: ScoreSpec, upto: int) -> DataFrame:
    """The same by a full ranking (no index)."""
    p = pairs(tiles, qt, spec.metric)
    w = Window.partitionBy("query_id", "q").orderBy("dist", "image_id", "r", "c")
    return p.withColumn("nn", F.row_number().over(w)).filter(F.col("nn") <= upto).select("query_id", "q", "nn", "dist", "image_id", "r", "c", "dr", "dc")
