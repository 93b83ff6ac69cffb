"""The algorithms side by side: ten-tile results against SQL, and cost against query size, database
size and dimension."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..carriers import grids
from ..durable import saved
from ..score.functions import ScoreSpec
from ..search import algorithms as A
from ..search.core import ranked
from ..search.shards import Shards, counters, hits_of
from ..workload import experiments as E
from ..workload.sampler import sample_queries
from .base import K, SPEC, TILES, corner_sql, hits, patch, tiles, topk_sql

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


P25 = topk_sql(corner_sql("p25"))
for _walk, _how in (("scan", {}), ("scan_pruned", {}), ("threshold", {}), ("frontier", {})):

    @query(f"store_{_walk}_topk_p25", P25)
    def stored(spark, d, walk=_walk, how=_how):
        """A ten-tile query on a shard store."""
        t = tiles(spark, d)
        return hits(ranked(hits_of(Shards.build(t).search([patch(t, "p25")], K, SPEC, walk, **how)), K))


@query("store_append_topk_p25", P25)
def appended(spark, d):
    """The same on a store that got half of its images later, after compaction."""
    t = tiles(spark, d)
    store = Shards.build(t.filter("image_id % 2 = 0")).append(t.filter("image_id % 2 = 1")).compact()
    return hits(ranked(hits_of(store.search([patch(t, "p25")], K, SPEC, "frontier")), K))


@query("scan_counters_p25", f"WITH {TILES}, s AS (SELECT image_id, max(r) + 1 nr, max(c) + 1 nc FROM tiles GROUP BY 1) SELECT CAST(sum((nr + 1) * (nc + 4)) AS BIGINT) \"overlaps\", CAST(sum((nr + 1) * (nc + 4)) AS BIGINT) solved, (SELECT count(*) * 10 FROM tiles) distances FROM s")
def scan_counters(spark, d):
    """The plain scan solves every overlap and measures every pair once."""
    t = tiles(spark, d)
    return counters(Shards.build(t).search([patch(t, "p25")], K, SPEC, "scan")).select("overlaps", "solved", "distances")


@query("walks_agree", "SELECT * FROM (VALUES ('frontier', 5, 50), ('threshold', 5, 50)) v(algorithm, queries, same)")
def walks_agree(spark, d):
    """Five sampled ten-tile queries: how many of their results each walk shares with the scan."""
    t = tiles(spark, d)
    store, qs = Shards.build(t), sample_queries(t, 5, 2, 5)
    rows = lambda walk: ranked(hits_of(store.search(qs, K, SPEC, walk)), K, single=False).select("query_id", "image_id", "dr", "dc", "score", "mask")
    want, out = saved(rows("scan")), None
    for walk in ("frontier", "threshold"):
        x = rows(walk).intersect(want).agg(F.lit(walk).alias("algorithm"), F.count_distinct("query_id").cast("int").alias("queries"), F.count("*").cast("int").alias("same"))
        out = x if out is None else out.union(x)
    return out


def _glyph(spark, d, dim=6):
    return saved(grids.glyph(spark, d, dim))


#: Costs: c as in the catalogue for the calendar, a third of a tile's usual distance to blank for texts.
CALENDAR, GLYPH, VECTOR = SPEC, ScoreSpec("l1", 1, 900), ScoreSpec("l1", 1, 0.1)


@query("experiment_query_size_calendar")
def by_size_calendar(spark, d):
    return E.query_size_sweep(saved(tiles(spark, d)), CALENDAR, n_queries=4, algorithms=("scan", "scan_pruned", "threshold", "frontier"))


@query("experiment_query_size_glyph")
def by_size_glyph(spark, d):
    return E.query_size_sweep(_glyph(spark, d), GLYPH, sizes=((2, 5), (4, 5), (5, 6), (5, 8)), n_queries=3)


for _h, _w in ((2, 5), (5, 6)):

    @query(f"experiment_database_size_glyph_n{_h * _w}")
    def by_database(spark, d, h=_h, w=_w):
        return E.database_size_sweep(_glyph(spark, d), GLYPH, h, w, n_queries=3)


@query("experiment_dimension_glyph")
def by_dimension(spark, d):
    return E.dimension_sweep(lambda dim: _glyph(spark, d, dim), GLYPH, 2, 5, n_queries=3)


@query("experiment_dimension_vectors")
def by_dimension_vectors(spark, d):
    return E.dimension_sweep(lambda dim: saved(grids.vectors(spark, d, dim)), VECTOR, 2, 5, n_queries=10)


@query("experiment_growth")
def growth(spark, d):
    """How straight the frontier's distance count grows with query size and database size."""
    t = _glyph(spark, d)
    by_n = E.query_size_sweep(t, GLYPH, sizes=((2, 5), (4, 5), (5, 6), (5, 8)), n_queries=3, algorithms=("frontier",))
    by_db = E.database_size_sweep(t, GLYPH, 2, 5, n_queries=3, algorithms=("frontier",))
    return E.growth(by_n, "n").withColumn("axis", F.lit("n")).union(E.growth(by_db, "share").withColumn("axis", F.lit("share")))


@query("hundred_queries")
def hundred(spark, d):
    """A hundred hash-sampled ten-tile queries, ten best: mean cost of each algorithm."""
    t = saved(tiles(spark, d))
    return E.compare(Shards.build(t), sample_queries(t, 100, 2, 5), K, CALENDAR, ("scan", "threshold", "frontier"))


@query("speedups")
def speedups(spark, d):
    """Time of one algorithm over another's for small and large queries."""
    s = E.query_size_sweep(saved(tiles(spark, d)), CALENDAR, sizes=((2, 5), (4, 10)), n_queries=5)
    one = lambda a: F.max(F.when(F.col("algorithm") == a, F.col("seconds")))
    return s.groupBy("n").agg((one("scan") / one("threshold")).alias("threshold_over_scan"), (one("scan") / one("frontier")).alias("frontier_over_scan"), (one("frontier") / one("threshold")).alias("threshold_over_frontier"))
