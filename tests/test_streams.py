"""Streams over several batches: late rows, restarts, alerts, growing stores; results in files."""

import os
from datetime import datetime, timedelta

import numpy as np
from hypothesis import given
from hypothesis import strategies as st
from pyspark.sql import functions as F

from gridmatch import sinks
from gridmatch.overlap.placements import Query
from gridmatch.score.functions import ScoreSpec
from gridmatch.search.core import canvas, ranked, solve_canvases
from gridmatch.search.shards import hits_of
from gridmatch.sql.register import register
from gridmatch.stream import tiles as S
from gridmatch.stream.standing import grow, grown, standing

START = datetime(2024, 1, 1)
SPEC = ScoreSpec("l1", 1, 3)


def _put(spark, folder, number, rows, schema):
    """One file of the stream's folder, with a time of its own so that files come in order."""
    path = f"{folder}/part-{number}.parquet"
    spark.createDataFrame(rows, schema).toPandas().to_parquet(path, coerce_timestamps="us")
    os.utime(path, (1_700_000_000 + number, 1_700_000_000 + number))


def _events(*hours):
    return [(i, START + timedelta(hours=h), 1, "view", 2.5) for i, h in enumerate(hours)]


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    for n, hours in enumerate([(1, 2, 20), (21,), (1.5, 22, 40)]):
        _put(spark, tmp_path, n, _events(*hours), S.EVENTS)
    counts, late = S.drained_with_late(S.tile_counts(S.source(spark, str(tmp_path), files=1)), "append")
    got = {r["start"].hour + 24 * (r["start"].day - 1): r["n"] for r in counts.collect()}
    assert got == {0: 2, 20: 3} and late == 1  # 1.5 came when the watermark was at 18; 40 is still open


def test_a_restarted_stream_goes_on(spark, tmp_path):
    folder, out = tmp_path / "in", str(tmp_path / "out")
    folder.mkdir()
    stream = S.deduplicated(S.source(spark, str(folder)))
    seen = lambda: sorted(r["event_id"] for r in S.stored(spark, out, stream.schema).collect())
    assert S.stored(spark, out, stream.schema).isEmpty()
    _put(spark, folder, 0, _events(1, 2), S.EVENTS)
    S.started(stream, out).awaitTermination()
    assert seen() == [0, 1]
    _put(spark, folder, 1, _events(1, 2, 3), S.EVENTS)
    S.started(stream, out).awaitTermination()
    assert seen() == [0, 1, 2]


def test_update_keeps_the_newest_row(spark, tmp_path):
    for n, hours in enumerate([(1, 2), (3,)]):
        _put(spark, tmp_path, n, _events(*hours), S.EVENTS)
    counts = S.drained(S.tile_counts(S.source(spark, str(tmp_path), files=1)), "update", ["user_id", "start"])
    assert [r["n"] for r in counts.collect()] == [3]


def _tiles(images, rows, columns, seed=5):
    rng = np.random.default_rng(seed)
    return [(i, r, c, float(rng.integers(0, 4))) for i in range(images) for r in range(rows) for c in range(columns)]


TILE = "image_id long, r int, c int, f0 double"


def _query():
    return Query(2, 2, np.array([[1.0], [2.0], [0.0], [3.0]]), np.array([5.0, 6.0, 4.0, 7.0]))


def test_standing_query_over_batches(spark, tmp_path):
    """Row by row, the alerts are those of a search over the tiles so far that touch the new row."""
    every, q = _tiles(3, 5, 4), _query()
    want = set()
    for r in range(5):
        _put(spark, tmp_path, r, [t for t in every if t[1] == r], TILE)
        so_far = spark.createDataFrame([t for t in every if max(0, r - 2) <= t[1] <= r], TILE)
        found = solve_canvases(canvas(so_far), [q], SPEC, None, floor=6.0).filter(F.col("dr").between(r - 1, r))
        want |= {tuple(x) for x in found.collect()}
    stream = spark.readStream.schema(TILE).option("maxFilesPerTrigger", 1).parquet(str(tmp_path))
    whole = {tuple(x) for x in S.drained(standing(stream, q, 6.0, SPEC), "append").collect()}
    short = {tuple(x) for x in S.drained(standing(stream, q, 6.0, SPEC, keep=3), "append").collect()}
    assert whole == want and short == want and len(want) > 5


def test_store_grown_by_batches(spark, tmp_path):
    every, q, store = _tiles(4, 3, 3), _query(), str(tmp_path / "store")
    folder = tmp_path / "in"
    folder.mkdir()
    for n in range(2):
        _put(spark, folder, n, [t for t in every if t[0] % 2 == n], TILE)
        grow(spark.readStream.schema(TILE).parquet(str(folder)), store).awaitTermination()
    shards = grown(spark, store)
    got = [tuple(x) for x in ranked(hits_of(shards.search([q], 5, SPEC, "scan")), 5).collect()]
    want = [tuple(x) for x in ranked(solve_canvases(canvas(spark.createDataFrame(every, TILE)), [q], SPEC, None), 5).collect()]
    assert got == want and shards.n == 2 and shards.compact().n == 1


def test_bucketed_tiles_need_no_exchange(spark, tmp_path):
    t = sinks.bucketed(spark.createDataFrame(_tiles(3, 2, 2), TILE), "gridmatch_bucketed_test", str(tmp_path / "b"), 4)
    plan = t.groupBy("image_id").count()
    assert "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()
    assert {tuple(r) for r in plan.collect()} == {(0, 4), (1, 4), (2, 4)}
    spark.sql("DROP TABLE gridmatch_bucketed_test")


def test_hits_through_files(spark, tmp_path):
    rows = [(0, 7, -1, 2, 1.5, 2, 9), (0, 8, 0, 0, -3.25, 1, 1 << 61)]
    hits = sinks.with_cells(spark.createDataFrame(rows, sinks.HITS), 4)
    assert [r["cells"] for r in hits.orderBy("image_id").collect()] == ["0:0 0:3", "15:1"]
    for form in sinks.FORMATS:
        sinks.write_hits(hits.select("cells", *hits.columns[:-1]), str(tmp_path / form), form)
        back = sinks.read_hits(spark, str(tmp_path / form), form, "cells string")
        assert [tuple(r) for r in back.orderBy("image_id").collect()] == [tuple(r) for r in hits.orderBy("image_id").collect()]


def test_region_aggregates(spark):
    register(spark)
    cells = "VALUES (1D, 0), (-5D, 1), (2D, 2), (CAST(NULL AS DOUBLE), 3) AS t(s, i)"
    got = spark.sql(f"SELECT grid_best_score_agg(s, i, 2, 2), grid_best_mask_agg(s, i, 2, 2) FROM {cells}").first()
    assert tuple(got) == (3.0, 5)
    mixed = "SELECT grid_best_region(s, h, w).score v FROM VALUES (array(1D, -2D), 1, 2), (array(3D, 4D), 2, 1), (array(5D, 6D), 1, 2) AS t(s, h, w)"
    assert [r["v"] for r in spark.sql(mixed).collect()] == [1.0, 7.0, 11.0]


@given(bg=st.floats(0, 1e6), other=st.floats(0, 1e6), near=st.floats(0, 1e6), far=st.floats(0, 1e6), c=st.floats(0, 1e6))
def test_score_falls_with_distance_and_with_likeness_to_background(bg, other, near, far, c):
    spec = ScoreSpec("l1", 1, c)
    of = lambda b, d: float(spec.numpy(np.array([b]), np.array([d]))[0])
    assert of(bg, max(near, far)) <= of(bg, min(near, far))
    assert of(min(bg, other), near) <= of(max(bg, other), near)
