"""Results and tiles written in other formats and read again."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from .. import sinks
from ..durable import shared_dir
from ..search import algorithms as A
from .base import K, PATCHES, SPEC, TILES, exact_sql, hits, patch, tiles, topk_sql

QUERIES: dict = {}
ORACLES: dict = {}


def _through(format: str):
    def run(spark, d):
        """The ten best regions, written and read."""
        t = tiles(spark, d)
        path = f"{shared_dir(spark).rstrip('/')}/hits-{uuid.uuid4().hex}"
        sinks.write_hits(A.scan(t, patch(t), K, SPEC).df, path, format)
        return hits(sinks.read_hits(spark, path, format))

    return run


for _format in sinks.FORMATS:
    QUERIES[f"hits_through_{_format}"] = _through(_format)
    ORACLES[f"hits_through_{_format}"] = topk_sql(exact_sql("p22"))


def region_cells_text(spark, d):
    """The best regions with their cells as text."""
    t = tiles(spark, d)
    found = sinks.with_cells(A.scan(t, patch(t), K, SPEC).df, PATCHES["p22"][4])
    return found.select("image_id", "dr", "dc", "cells")


QUERIES["region_cells_text"] = region_cells_text
ORACLES["region_cells_text"] = f"""WITH {exact_sql("p22")}, top AS (SELECT image_id, dr, dc, b.s s, -b.m m FROM best ORDER BY s DESC, image_id, dr, dc LIMIT {K})
SELECT image_id, dr, dc, list_aggregate(list_transform(list_filter(range(4), lambda i: (m >> i) & 1 = 1), lambda i: (i // 2) || ':' || (i % 2)), 'string_agg', ' ') cells FROM top"""


def bucketed_tiles(spark, d):
    """Tiles of an image from a table clustered by it: grouped without an exchange."""
    name = f"gridmatch_tiles_{uuid.uuid4().hex}"
    t = sinks.bucketed(tiles(spark, d), name, f"{shared_dir(spark).rstrip('/')}/{name}", 8)
    return t.groupBy("image_id").agg(F.count("*").alias("n"), F.sum("bg").cast("long").alias("bg"))


QUERIES["bucketed_tiles"] = bucketed_tiles
ORACLES["bucketed_tiles"] = f"WITH {TILES} SELECT image_id, count(*) n, CAST(sum(bg) AS BIGINT) bg FROM tiles GROUP BY 1"
