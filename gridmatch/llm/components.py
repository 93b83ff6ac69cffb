"""Connected components by contraction, as DataFrame rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut


def components(edges: DataFrame) -> DataFrame:
    """`edges` (a, b) to (v, component): the smallest vertex reachable from each vertex of an edge.

    Every round points each vertex at its smallest neighbour, follows pointers twice, and
    contracts the edges; pointers fall, so a vertex's last one is the smallest of its component.
    Minima are combined before the shuffle, so a vertex with very many edges is no hot spot."""
    edges = cut(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct())
    names = edges.select(F.col("a").alias("v")).union(edges.select(F.col("b").alias("v"))).distinct().select("v", F.col("v").alias("c"))
    while not edges.isEmpty():
        # the larger end of an edge has a smaller neighbour; roots point at themselves
        up = edges.groupBy(F.col("b").alias("v")).agg(F.min("a").alias("p"))
        for _ in range(2):
            above = up.select(F.col("v").alias("p"), F.col("p").alias("pp"))
            up = cut(up.join(above, "p", "left").select("v", F.coalesce("pp", "p").alias("p")))
        at = lambda x: F.coalesce(f"{x}p", x)
        moved = edges.join(up.select(F.col("v").alias("a"), F.col("p").alias("ap")), "a", "left").join(up.select(F.col("v").alias("b"), F.col("p").alias("bp")), "b", "left").select(at("a").alias("a"), at("b").alias("b"))
        edges = cut(moved.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct())
        names = cut(names.join(up.select(F.col("v").alias("c"), "p"), "c", "left").select("v", F.coalesce("p", "c").alias("c")))
    return names.withColumnRenamed("c", "component")
