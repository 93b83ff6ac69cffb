"""Training of (lam, c): the grid point with the best precision wins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..score.functions import ScoreSpec
from .quality import precision_at_k


def train_parameters(run: Callable[[ScoreSpec], DataFrame], truth: DataFrame, lams: list[float], cs: list[float], k: int = 5, metric: str = "l1", denominator: str = "returned") -> DataFrame:
    """lam, c, precision, best.  `run` gives ranked results of the training queries for a spec;
    the grid is a handful of points, each one job."""
    out = None
    for lam in lams:
        for c in cs:
            p = precision_at_k(run(ScoreSpec(metric, lam, c)), truth, k, denominator, truth).agg(F.avg("precision").alias("precision"))
            row = p.select(F.lit(float(lam)).alias("lam"), F.lit(float(c)).alias("c"), "precision")
            out = row if out is None else out.union(row)
    best = out.agg(F.max_by(F.struct("lam", "c"), F.struct("precision", -F.col("lam"), -F.col("c"))).alias("b"))
    return out.crossJoin(F.broadcast(best)).select("lam", "c", "precision", ((F.col("lam") == F.col("b.lam")) & (F.col("c") == F.col("b.c"))).alias("best"))
