"""Query patches drawn from the data by hash: the same ones on every run."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..overlap.placements import Query, image_shapes


def sample_queries(tiles: DataFrame, n: int, h: int, w: int, seed: int = 0) -> list[Query]:
    """n patches of h x w tiles from n images; n bounds what reaches the driver."""
    shapes = image_shapes(tiles).filter((F.col("n_rows") >= h) & (F.col("n_cols") >= w))
    draw = lambda i: F.md5(F.concat_ws(":", F.col("image_id").cast("string"), F.lit(str(seed + i))).cast("binary"))
    number = lambda i: F.conv(F.substring(draw(i), 1, 6), 16, 10).cast("long")
    pick = shapes.withColumn("k", draw(0)).orderBy("k", "image_id").limit(n)
    pick = pick.select("image_id", (number(1) % (F.col("n_rows") - h + 1)).alias("r0"), (number(2) % (F.col("n_cols") - w + 1)).alias("c0"))
    inside = F.col("r").between(F.col("r0"), F.col("r0") + h - 1) & F.col("c").between(F.col("c0"), F.col("c0") + w - 1)
    rows: dict[int, list[dict]] = {}
    for x in tiles.join(F.broadcast(pick), "image_id").filter(inside).collect():
        rows.setdefault(x["image_id"], []).append(x.asDict() | {"r": x["r"] - x["r0"], "c": x["c"] - x["c0"]})
    full = [(i, r) for i, r in sorted(rows.items()) if len(r) == h * w]
    return [Query.from_rows(r, h, w, query_id, i) for query_id, (i, r) in enumerate(full)]
