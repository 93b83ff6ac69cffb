"""Tile distances and scores as Column expressions, with numpy twins in `ScoreSpec`.

A score is f(query tile) - g(distance) - c with g increasing, so it never grows with distance.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

METRICS = ("l1", "l2", "linf")
SHAPES: dict[str, tuple[Callable, Callable]] = {
    "linear": (lambda d: d, lambda d: d),
    "sqrt": (F.sqrt, np.sqrt),
    "square": (lambda d: d * d, lambda d: d * d),
    "capped": (lambda d: F.least(d, F.lit(1000.0)), lambda d: np.minimum(d, 1000.0)),
}


def dist(a: list[Column], b: list[Column], metric: str = "l1") -> Column:
    """Unrolled over scalar columns, so it stays in generated code."""
    gaps = [F.abs(x - y) for x, y in zip(a, b)]
    if metric == "l1":
        return sum(gaps[1:], gaps[0])
    if metric == "linf":
        return F.greatest(*gaps) if len(gaps) > 1 else gaps[0]
    squares = [(x - y) * (x - y) for x, y in zip(a, b)]
    return F.sqrt(sum(squares[1:], squares[0]).cast("double"))


def array_dist(a: Column, b: Column, metric: str = "l1") -> Column:
    """The same over array columns."""
    gaps = F.zip_with(a, b, lambda x, y: F.abs(x.cast("double") - y.cast("double")))
    if metric == "linf":
        return F.array_max(gaps)
    if metric == "l1":
        return F.aggregate(gaps, F.lit(0.0), lambda s, x: s + x)
    return F.sqrt(F.aggregate(gaps, F.lit(0.0), lambda s, x: s + x * x))


def mindist(q: list, lo: list[Column], hi: list[Column], metric: str = "l1") -> Column:
    """Least distance from a point to a box."""
    gaps = [F.greatest(a - x, F.lit(0), x - b) for x, a, b in zip(q, lo, hi)]
    return dist(gaps, [F.lit(0)] * len(gaps), metric)


def emd(a: Column, b: Column) -> Column:
    """Earth mover's distance of two histograms on a line: L1 of their cumulative differences."""
    step = lambda acc, x: F.struct((acc["run"] + x).alias("run"), (acc["sum"] + F.abs(acc["run"] + x)).alias("sum"))
    diff = F.zip_with(a, b, lambda x, y: (x - y).cast("double"))
    return F.aggregate(diff, F.struct(F.lit(0.0).alias("run"), F.lit(0.0).alias("sum")), step)["sum"]


def mahalanobis(a: list[Column], b: list[Column], inverse: np.ndarray) -> Column:
    d = [x - y for x, y in zip(a, b)]
    return F.sqrt(sum(d[i] * d[j] * float(inverse[i, j]) for i in range(len(d)) for j in range(len(d))))


def template_score(f: Column, d: Column, g: str | Callable = "linear", c: float = 0) -> Column:
    grow = SHAPES[g][0] if isinstance(g, str) else g
    return f - grow(d) - c


def exp_density(x: Column, lam: float) -> Column:
    return lam * F.exp(-lam * x)


def log_odds_score(bg: Column, d: Column, lam1: float, lam2: float) -> Column:
    """ln of match density (lam1 exp(-lam1 d)) over background density (lam2 exp(-lam2 bg))."""
    return lam2 * bg - lam1 * d + math.log(lam1 / lam2)


def discriminator_score(bg: Column, d: Column, lam: float = 1, c: float = 0) -> Column:
    return bg - (d if lam == 1 else lam * d) - c


def to_discriminator(lam1: float, lam2: float) -> tuple[float, float]:
    """(lam, c) whose discriminator is the log-odds score over lam2."""
    return lam1 / lam2, -math.log(lam1 / lam2) / lam2


def fit_exponential(df: DataFrame, column: str) -> float:
    """Maximum-likelihood rate of an exponential: one over the mean."""
    return 1 / df.agg(F.avg(column)).first()[0]


@dataclass(frozen=True)
class ScoreSpec:
    """bg - lam * g(distance) - c."""

    metric: str = "l1"
    lam: float = 1
    c: float = 0
    g: str = "linear"

    def __post_init__(self):
        if self.metric not in METRICS or self.g not in SHAPES:
            raise ValueError(f"unknown metric or shape: {self.metric}, {self.g}")
        if self.lam < 0:
            raise ValueError("lam must not be negative: the score would grow with distance")

    def column(self, bg: Column, d: Column) -> Column:
        g = SHAPES[self.g][0](d)
        return bg - (g if self.lam == 1 else self.lam * g) - self.c

    def numpy(self, bg: np.ndarray, d: np.ndarray) -> np.ndarray:
        return bg - self.lam * SHAPES[self.g][1](d) - self.c

    def distance(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        gap = np.abs(a - b)
        return gap.sum(-1) if self.metric == "l1" else gap.max(-1) if self.metric == "linf" else np.sqrt((gap**2).sum(-1))

    def mindist(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        gap = np.maximum(np.maximum(lo - q, q - hi), 0)
        return self.distance(gap, np.zeros_like(gap))

    def maxdist(self, q: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        gap = np.maximum(np.abs(q - lo), np.abs(q - hi))
        return self.distance(gap, np.zeros_like(gap))
