"""The methods as SQL functions: `register(spark)` adds the grid_* names to a session.

Distances, scores and bounds are SQL functions that the optimizer inlines; regions are Arrow
functions over arrays of scores; placements and cells are table functions for LATERAL use."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import PandasUDFType, pandas_udf

from ..region import solvers

#: name -> (parameters, result, body)
INLINED = {
    "grid_l1": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x)"),
    "grid_l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))"),
    "grid_linf": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "array_max(zip_with(a, b, (x, y) -> abs(x - y)))"),
    "grid_score": ("bg DOUBLE, dist DOUBLE, lam DOUBLE, c DOUBLE", "DOUBLE", "bg - lam * dist - c"),
    "grid_bound": ("scores ARRAY<DOUBLE>", "DOUBLE", "CASE WHEN array_max(scores) > 0 THEN aggregate(filter(scores, x -> x > 0), 0D, (s, x) -> s + x) ELSE array_max(scores) END"),
    "grid_mindist": ("q ARRAY<DOUBLE>, lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(zip_with(lo, q, (l, x) -> greatest(l - x, 0D)), zip_with(q, hi, (x, h) -> greatest(x - h, 0D)), (a, b) -> a + b), 0D, (s, x) -> s + x)"),
}
REGION = "score double, n_cells int, mask long"


def _solver(name: str):
    def solve(scores: pd.Series, h: pd.Series, w: pd.Series) -> pd.DataFrame:
        score, mask = np.full(len(scores), np.nan), np.zeros(len(scores), np.int64)
        for (a, b), at in pd.Series(range(len(scores))).groupby([h.to_numpy(), w.to_numpy()]).groups.items():
            # matrices of one shape are solved together
            score[at], mask[at] = solvers.solve(np.stack([np.asarray(scores.iloc[i], float) for i in at]), int(a), int(b), name)
        return pd.DataFrame({"score": score, "n_cells": [int(m).bit_count() for m in mask], "mask": mask})

    return pandas_udf(solve, REGION)


def _gathered(name: str, what: int, kind: str):
    """The best region's score or mask as an aggregate over rows of cells (score, cell from 0, rows
    and columns of the matrix); cells without a row or a score are missing."""

    def solve(score: pd.Series, cell: pd.Series, h: pd.Series, w: pd.Series) -> float:
        m = np.full((1, int(h.iloc[0]) * int(w.iloc[0])), np.nan)
        m[0, cell.to_numpy(int)] = score.to_numpy(float)
        return solvers.solve(m, int(h.iloc[0]), int(w.iloc[0]), name)[what][0].item()

    return pandas_udf(solve, kind, PandasUDFType.GROUPED_AGG)


class Overlaps:
    """Placements of an h x w query on an image of n_rows x n_cols."""

    def eval(self, n_rows: int, n_cols: int, h: int, w: int):
        for dr in range(1 - h, n_rows):
            for dc in range(1 - w, n_cols):
                yield dr, dc


class RegionCells:
    """Cells (qr, qc) of a region mask of width w."""

    def eval(self, mask: int, w: int):
        yield from solvers.region_cells(mask, w)


def register(spark: SparkSession) -> None:
    for name, (parameters, result, body) in INLINED.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {result} RETURN {body}")
    spark.udf.register("grid_best_region", _solver("corner_dp"))
    spark.udf.register("grid_exact_region", _solver("exact"))
    spark.udf.register("grid_best_score_agg", _gathered("corner_dp", 0, "double"))
    spark.udf.register("grid_best_mask_agg", _gathered("corner_dp", 1, "long"))

    def connected(mask: pd.Series, h: pd.Series, w: pd.Series) -> pd.Series:
        return pd.Series([solvers.is_connected(int(m), int(a), int(b)) for m, a, b in zip(mask, h, w)])

    def sinks(mask: pd.Series, h: pd.Series, w: pd.Series) -> pd.Series:
        return pd.Series([",".join(sorted(solvers.sink_class(int(m), int(a), int(b)))) for m, a, b in zip(mask, h, w)])

    spark.udf.register("grid_is_connected", pandas_udf(connected, "boolean"))
    spark.udf.register("grid_sinks", pandas_udf(sinks, "string"))
    spark.udtf.register("grid_overlaps", F.udtf(Overlaps, returnType="dr int, dc int"))
    spark.udtf.register("grid_region_cells", F.udtf(RegionCells, returnType="qr int, qc int"))
