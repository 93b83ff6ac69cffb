"""Cost and accuracy measures as DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def precision_at_k(result: DataFrame, truth: DataFrame, k: int = 5, denominator: str = "returned", asked: DataFrame | None = None) -> DataFrame:
    """query_id, precision: true rows among the first k, of those returned, of `k`, or of as many as
    could be true (`possible`: k, or all true rows if they are fewer).

    Every query of `asked` (query_id) counts, also one without results; without it those with results do."""
    if denominator not in ("returned", "k", "possible"):
        raise ValueError("denominator is returned, k or possible")
    t = truth.filter("is_true").select("query_id", "image_id").distinct().withColumn("hit", F.lit(1))
    top = result.filter(F.col("rank") <= k).join(t, ["query_id", "image_id"], "left")
    found = top.groupBy("query_id").agg(F.coalesce(F.sum("hit"), F.lit(0)).alias("hits"), F.count("*").alias("returned"))
    if asked is not None:
        found = asked.select("query_id").distinct().join(found, "query_id", "left").fillna(0)
    if denominator == "possible":
        found = found.join(t.groupBy("query_id").agg(F.least(F.lit(k), F.count("*")).alias("possible")), "query_id", "left")
    of = F.lit(k) if denominator == "k" else F.col(denominator)
    return found.select("query_id", F.coalesce(F.col("hits") / F.nullif(of, F.lit(0)), F.lit(0.0)).alias("precision"))


def recall_of(found: DataFrame, wanted: DataFrame, keys: list[str]) -> DataFrame:
    """Share of `wanted` rows that `found` has."""
    have = found.select(*keys).distinct().withColumn("_in", F.lit(1))
    return wanted.select(*keys).join(have, keys, "left").agg(F.avg(F.coalesce("_in", F.lit(0))).alias("recall"))


def saving(seconds: float, baseline: float) -> float:
    return 1 - seconds / baseline


def linearity(df: DataFrame, x: str, y: str) -> DataFrame:
    return df.agg(F.regr_r2(y, x).alias("r2"), F.regr_slope(y, x).alias("slope"))


def mask_iou(mask, truth):
    """Intersection over union of two region masks (Columns)."""
    return F.bit_count(mask.bitwiseAND(truth)) / F.bit_count(mask.bitwiseOR(truth))
