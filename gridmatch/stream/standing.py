"""Searches beside a stream of tiles: a standing query, and a store that grows by batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..carriers.grids import feature_columns
from ..overlap.placements import Query
from ..region.solvers import CORNERS
from ..score.functions import ScoreSpec
from ..search.core import HITS, ImageScores, best_rows
from ..search.shards import STORED, Shards

KEPT = "r array<int>, c array<int>, f array<double>"


def standing(tiles: DataFrame, query: Query, theta: float, spec: ScoreSpec, keep: int = 64, solver: str = "corner_dp") -> DataFrame:
    """Alerts (columns of a hit): alignments that a batch's new tiles touch and whose region then
    scores `theta` or more.  `tiles` is a stream of image_id, r, c, f0...; a tile that comes again
    replaces the one before.

    The state of an image is its tiles of the last `keep` rows, so it is bounded by keep x columns;
    an alignment is judged on those.  An alignment can give one alert for each batch."""
    if keep < query.h:
        raise ValueError("keep as many rows as the query has")
    names = feature_columns(tiles)

    def react(key: tuple, chunks: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        r, c, f = (np.array(x) for x in state.get) if state.exists else (np.zeros(0, int), np.zeros(0, int), np.zeros(0))
        new = pd.concat(list(chunks))
        at_r, at_c = np.concatenate([r, new["r"]]).astype(np.int64), np.concatenate([c, new["c"]]).astype(np.int64)
        every = np.concatenate([f.reshape(-1, len(names)), new[names].to_numpy(float)])
        fresh = np.arange(len(at_r)) >= len(r)
        cell = at_r * (at_c.max() + 1) + at_c
        last = len(cell) - 1 - np.unique(cell[::-1], return_index=True)[1]  # a later tile wins
        last = last[at_r[last] > at_r.max() - keep]
        at_r, at_c, every, fresh = at_r[last], at_c[last], every[last], fresh[last]
        state.update((at_r.tolist(), at_c.tolist(), every.ravel().tolist()))
        base = at_r.min()
        s = ImageScores(at_r - base, at_c, every, query, spec)
        touched = np.zeros(s.shape, bool)
        for i in range(query.n):  # placements that put cell i on a new tile
            touched[at_r[fresh] - base - i // query.w - s.lo[0], at_c[fresh] - i % query.w - s.lo[1]] = True
        dr, dc, score, mask, _ = best_rows(s.dr, s.dc, s.matrix, query, solver, CORNERS, None, theta, 1, touched.ravel())
        yield pd.DataFrame({"query_id": query.query_id, "image_id": key[0], "dr": dr + base, "dc": dc, "score": score, "n_cells": [int(m).bit_count() for m in mask], "mask": mask})

    rows = tiles.select(F.col("image_id").cast("long").alias("image_id"), F.col("r").cast("int").alias("r"), F.col("c").cast("int").alias("c"), *[F.col(x).cast("double").alias(x) for x in names])
    return rows.groupBy("image_id").applyInPandasWithState(react, HITS, KEPT, "append", GroupStateTimeout.NoTimeout)


def grow(tiles: DataFrame, path: str) -> StreamingQuery:
    """Each batch of whole images becomes shards of its own under `path`; a batch that is run again
    is written over.  An image must come within one batch."""

    def add(batch: DataFrame, n: int) -> None:
        Shards.build(batch, f"{path}/batch_no={n}", mode="overwrite")

    return tiles.writeStream.foreachBatch(add).option("checkpointLocation", f"{path}.state").trigger(availableNow=True).start()


def grown(spark: SparkSession, path: str) -> Shards:
    """The store that `grow` keeps; `compact()` joins its small shards."""
    rows = spark.read.schema(STORED).parquet(path)
    shard = F.pmod(F.xxhash64("batch_no", "shard"), F.lit(1 << 31)).cast("int")
    return Shards.of(rows.withColumn("shard", shard).drop("batch_no"))
