"""The experiments: the same sampled queries by every algorithm on one store, with their counters.

Times are seconds of work beside the data (one core each), split into finding neighbours and solving
matrices; counters do not depend on the machine."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..overlap.placements import Query
from ..score.functions import ScoreSpec
from ..search.shards import CLOCKS, COUNTERS, Shards, counters
from .sampler import sample_queries

ALGORITHMS = ("scan", "threshold", "frontier")
SIZES = ((2, 5), (4, 5), (5, 6), (4, 10))


def compare(store: Shards, queries: list[Query], k: int, spec: ScoreSpec, algorithms: tuple[str, ...] = ALGORITHMS, **axes) -> DataFrame:
    """A row for each algorithm: the `axes`, means over the queries, and shares.

    solved_share: solved matrices of all overlaps; nn_share: neighbours' part of the time;
    speedup: the first algorithm's time over this one's."""
    out = None
    for name in algorithms:
        c = counters(store.search(queries, k, spec, name))
        row = c.agg(F.count("*").alias("queries"), *[F.avg(x).alias(x) for x in (*COUNTERS, *CLOCKS)])
        row = row.select(F.lit(name).alias("algorithm"), *[F.lit(v).alias(a) for a, v in axes.items()], F.lit(queries[0].n if queries else 0).alias("n"), "*")
        out = row if out is None else out.union(row)
    seconds = F.col("nn_seconds") + F.col("solve_seconds")
    first = out.filter(F.col("algorithm") == algorithms[0]).select(seconds.alias("_first"))
    return out.crossJoin(F.broadcast(first)).select("*", (F.col("solved") / F.col("overlaps")).alias("solved_share"), seconds.alias("seconds"), (F.col("nn_seconds") / seconds).alias("nn_share"), (F.col("_first") / seconds).alias("speedup")).drop("_first")


def query_size_sweep(tiles: DataFrame, spec: ScoreSpec, sizes=SIZES, n_queries: int = 20, k: int = 10, algorithms=ALGORITHMS) -> DataFrame:
    """Cost against the query's size on one database."""
    store, out = Shards.build(tiles), None
    for h, w in sizes:
        part = compare(store, sample_queries(tiles, n_queries, h, w), k, spec, algorithms)
        out = part if out is None else out.union(part)
    return out


def database_size_sweep(tiles: DataFrame, spec: ScoreSpec, h: int, w: int, shares=(10, 30, 50, 100), n_queries: int = 20, k: int = 10, algorithms=ALGORITHMS) -> DataFrame:
    """Cost against the share of the images (by hash) that are searched; the same queries for all."""
    queries, out = sample_queries(tiles, n_queries, h, w), None
    for share in shares:
        part = compare(Shards.build(tiles.filter(F.pmod(F.xxhash64("image_id"), F.lit(100)) < share)), queries, k, spec, algorithms, share=share)
        out = part if out is None else out.union(part)
    return out


def dimension_sweep(tiles_of, spec: ScoreSpec, h: int, w: int, dims=(3, 6, 13), n_queries: int = 20, k: int = 10, algorithms=("scan", "frontier")) -> DataFrame:
    """Cost against the features' number; `tiles_of(dim)` gives the tiles."""
    out = None
    for dim in dims:
        tiles = tiles_of(dim)
        part = compare(Shards.build(tiles), sample_queries(tiles, n_queries, h, w), k, spec, algorithms, dim=dim)
        out = part if out is None else out.union(part)
    return out


def growth(sweep: DataFrame, x: str, algorithm: str = "frontier", y: str = "distances") -> DataFrame:
    """How straight a sweep's cost is: r2, slope and the power of a log-log fit."""
    own = sweep.filter(F.col("algorithm") == algorithm).select(F.col(x).cast("double").alias("x"), F.col(y).cast("double").alias("y"))
    return own.agg(F.regr_r2("y", "x").alias("r2"), F.regr_slope("y", "x").alias("slope"), F.regr_slope(F.log("y"), F.log("x")).alias("power"))
