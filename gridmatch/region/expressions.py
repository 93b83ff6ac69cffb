"""Regions as Column expressions: the corner sweeps unrolled cell by cell, mask enumeration and
bounds.  Input is a wide row s0..s{n-1} (row-major, NULL where there is no tile)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .solvers import CORNERS, connected_masks, sweep_order

REGION = "STRUCT<s: BIGINT, n: INT, m: BIGINT>"


def positive_sum(cells: list[Column]) -> Column:
    most = F.greatest(*cells) if len(cells) > 1 else cells[0]
    return F.when(most > 0, sum(F.greatest(F.coalesce(x, F.lit(0)), F.lit(0)) for x in cells)).otherwise(most)


def mask_sum(mask: Column, cells: list[Column]) -> Column:
    return sum(F.when(mask.bitwiseAND(F.lit(1 << i)) != 0, F.coalesce(x, F.lit(0))).otherwise(F.lit(0)) for i, x in enumerate(cells))


def _best(options: list[Column]) -> Column:
    """Largest of (score, fewer cells, smaller mask); NULL options lose."""
    return F.array_max(F.array(*options))


def _region(s: Column, m: Column) -> Column:
    return F.when(s.isNotNull(), F.struct(s.alias("s"), (-F.bit_count(m).cast("int")).alias("n"), (-m).alias("m")))


def sweep(df: DataFrame, h: int, w: int, corner: str, prefix: str = "s", out: str = "region") -> DataFrame:
    """Adds `out`: struct s, n (minus cells), m (minus mask) of the corner's best end cell.

    One projection for each cell, so every cell's region is computed once."""
    cell = [F.col(f"{prefix}{i}") for i in range(h * w)]
    kept = df.columns
    for i, row, col in sweep_order(h, w, corner):
        own = F.lit(1 << i).cast("long")
        options = [_region(cell[i], own)]
        for j in (row, col):
            if j >= 0:
                b = F.col(f"_g{j}")
                options.append(_region(cell[i] + b["s"], own.bitwiseOR(-b["m"])))
        if row >= 0 and col >= 0:
            a, b = F.col(f"_g{row}"), F.col(f"_g{col}")
            both = (-a["m"]).bitwiseAND(-b["m"])
            options.append(_region(cell[i] + a["s"] + b["s"] - mask_sum(both, cell), own.bitwiseOR(-a["m"]).bitwiseOR(-b["m"])))
        df = df.withColumn(f"_g{i}", _best(options))
    return df.select(*kept, _best([F.col(f"_g{i}") for i in range(h * w)]).alias(out))


def corner_dp(df: DataFrame, h: int, w: int, corners: tuple[str, ...] = CORNERS, prefix: str = "s") -> DataFrame:
    """Adds score, n_cells and mask of the best sweep."""
    kept = df.columns
    for k in corners:
        df = sweep(df, h, w, k, prefix, f"_{k}")
    best = _best([F.col(f"_{k}") for k in corners])
    return df.withColumn("_b", best).select(*kept, F.col("_b.s").alias("score"), (-F.col("_b.n")).alias("n_cells"), (-F.col("_b.m")).alias("mask"))


def exact(df: DataFrame, h: int, w: int, prefix: str = "s") -> DataFrame:
    """Adds score, n_cells and mask of the best connected region, by all masks of a small grid."""
    cell = [F.col(f"{prefix}{i}") for i in range(h * w)]
    options = [_region(sum(cell[i] for i in range(h * w) if m >> i & 1), F.lit(m).cast("long")) for m in connected_masks(h, w)]
    kept = df.columns
    return df.withColumn("_b", _best(options)).select(*kept, F.col("_b.s").alias("score"), (-F.col("_b.n")).alias("n_cells"), (-F.col("_b.m")).alias("mask"))


def _moved(mask: Column, h: int, w: int, dr: int, dc: int) -> Column:
    """The cells that a mask's cells reach by one move, inside the grid."""
    stay = sum(1 << i for i in range(h * w) if 0 <= i % w + dc < w and 0 <= i // w + dr < h)
    by, kept = dr * w + dc, mask.bitwiseAND(F.lit(stay).cast("long"))
    return F.shiftleft(kept, by) if by > 0 else F.shiftright(kept, -by)


def _spread(seed: Column, mask: Column, h: int, w: int, moves: tuple) -> Column:
    """All cells of the mask that the seed reaches by the moves inside it: one step for each cell."""

    def step(seen: Column) -> Column:
        for m in moves:
            seen = seen.bitwiseOR(_moved(seen, h, w, *m)).bitwiseAND(mask)
        return seen

    return F.aggregate(F.sequence(F.lit(1), F.lit(h * w)), seed.bitwiseAND(mask), lambda seen, _: step(seen))


def connected(mask: Column, h: int, w: int) -> Column:
    """Is the mask one 4-connected region?"""
    seed = mask.bitwiseAND(-mask)
    return (mask != 0) & (_spread(seed, mask, h, w, ((0, 1), (0, -1), (1, 0), (-1, 0))) == mask)


def has_sink(mask: Column, h: int, w: int, corner: str) -> Column:
    """Has the region a cell that all of it reaches by the corner's two moves (so that the sweep can give it)?"""
    back = ((-1 if corner[0] == "B" else 1, 0), (0, -1 if corner[1] == "L" else 1))
    any_cell = F.lit(False)
    for i in range(h * w):
        any_cell = any_cell | (_spread(F.lit(1 << i).cast("long"), mask, h, w, back) == mask)
    return (mask != 0) & any_cell


def region_union(a: Column, b: Column) -> Column:
    return a.bitwiseOR(b)


def region_intersect(a: Column, b: Column) -> Column:
    return a.bitwiseAND(b)
