"""The walks beside the data against the scan: results, counters, empty tables, growth of the store."""

import numpy as np
import pytest

from gridmatch.overlap.placements import Query
from gridmatch.score.functions import ScoreSpec
from gridmatch.search import algorithms as A
from gridmatch.search import shards as S

SPEC = ScoreSpec("l1", 1, 6)
TILE = "image_id long, r int, c int, f0 double, f1 double, bg double"


@pytest.fixture(scope="module")
def tiles(spark):
    rng = np.random.default_rng(2)
    rows = []
    for i in range(60):
        h, w = rng.integers(1, 7, 2)
        for r in range(h):
            for c in range(w):
                if rng.random() < 0.9 or (r, c) == (h - 1, w - 1):
                    f = rng.integers(0, 12, 2)
                    rows.append((i * 7, r, c, float(f[0]), float(f[1]), float(f.sum())))
    return spark.createDataFrame(rows, TILE).repartition(3)


@pytest.fixture(scope="module")
def store(tiles):
    return S.Shards.build(tiles, tiles_per_shard=150)


def a_query(h, w, seed=0):
    f = np.random.default_rng(seed).integers(0, 12, (h * w, 2)).astype(float)
    return Query(h, w, f, f.sum(1))


def rows_of(found):
    return [tuple(r) for r in found.select("image_id", "dr", "dc", "score", "mask").orderBy("score", "image_id", "dr", "dc").collect()]


@pytest.mark.parametrize("size", [(1, 1), (2, 2), (1, 4), (3, 3)])
@pytest.mark.parametrize(("walk", "how"), [("scan", {}), ("scan_pruned", {}), ("threshold", {"batch": 1, "doubling": False}), ("threshold", {"batch": 5}), ("threshold", {"batch": 3, "bound": "exact", "solver": "exact"}), ("frontier", {"wave": 1, "growing": False}), ("frontier", {}), ("frontier", {"wave": 4, "defer": False})])
def test_walks_give_the_scan(tiles, store, size, walk, how):
    q = a_query(*size)
    want = A.scan(tiles, q, 7, SPEC, solver=how.get("solver", "corner_dp")).df
    found = store.search([q], 7, SPEC, walk, **how)
    assert rows_of(A.ranked(S.hits_of(found), 7)) == rows_of(want)
    c = S.counters(found).first()
    assert 0 < c["solved"] <= c["overlaps"] and (walk == "scan") <= (c["solved"] > c["overlaps"] / 2)


def test_early_shards_set_a_floor(spark, tiles):
    many = S.Shards.build(tiles, tiles_per_shard=10)
    assert many.n > 2 * spark.sparkContext.defaultParallelism
    qs = [a_query(2, 2, s) for s in range(3)]
    qs = [Query(q.h, q.w, q.features, q.bg, i) for i, q in enumerate(qs)]
    got = A.ranked(S.hits_of(many.search(qs, 5, SPEC, "frontier")), 5, single=False)
    want = A.scan(tiles, qs, 5, SPEC).df
    assert rows_of(got) == rows_of(want)


def test_early_shards_set_a_floor_for_pruned_scans(spark, tiles):
    many = S.Shards.build(tiles, tiles_per_shard=10)
    qs = [Query(2, 2, q.features, q.bg, i) for i, q in enumerate(a_query(2, 2, s) for s in range(3))]
    found = {early: many.search(qs, 5, SPEC, "scan_pruned", per_image=True, early=early) for early in (None, True)}
    want = rows_of(A.scan(tiles, qs, 5, SPEC, per_image=True).df)
    assert rows_of(A.ranked(S.hits_of(found[None]), 5, single=False)) == rows_of(A.ranked(S.hits_of(found[True]), 5, single=False)) == want
    c = [S.counters(found[early]).agg({"solved": "sum", "distances": "sum"}).first() for early in (None, True)]
    assert c[1]["sum(solved)"] < c[0]["sum(solved)"] and c[0]["sum(distances)"] == c[1]["sum(distances)"]


@pytest.mark.parametrize("size", [(1, 1), (2, 2), (1, 4), (3, 3)])
def test_bounds_of_all_alignments(store, size):
    for row in store.rows.collect():
        space = S.Space(*(row[x] for x in ("ids", "sizes", "r", "c", "f", "place")))
        for c in (2, 6, 40):
            t = S.Task(space, a_query(*size), ScoreSpec("l1", 1, c), 5, "corner_dp", S.solvers.CORNERS, -np.inf)
            t.measure()
            assert np.allclose(t.bounds(), S.solvers.positive_sum(t.matrices(np.arange(t.first[-1]))))


@pytest.mark.parametrize("how", [{}, {"wave": 4}, {"wave": 8, "defer": False}, {"wave": 1, "growing": False}])
def test_pairs_aside_change_nothing(store, monkeypatch, how):
    """The frontier's rows and counters are those of a walk that keeps all pairs together."""

    def walked(limit):
        out = []
        for row in store.rows.collect():
            space = S.Space(*(row[x] for x in ("ids", "sizes", "r", "c", "f", "place")))
            for floor in (-np.inf, 20.0):
                t = S.Task(space, a_query(2, 3, 1), SPEC, 5, "corner_dp", S.solvers.CORNERS, floor)
                monkeypatch.setattr(S.Task, "reach", limit)
                S.frontier(t, **how)
                out.append((t.score.tolist(), t.mask.tolist(), t.at.tolist(), t.count))
        return out

    usual = S.Task.reach
    assert walked(usual) == walked(lambda t, most, score: (-1.0, np.inf)) == walked(lambda t, most, score: (-1.0, 2.0))


def test_files_of_a_store_hold_few_shards(tiles, tmp_path):
    """A reader holds all rows of a file, up to some thousands, at once."""
    many = S.Shards.build(tiles.repartition(1), f"{tmp_path}/store", tiles_per_shard=10)
    assert many.n > 1
    few = S.Shards.build(tiles.repartition(1), f"{tmp_path}/whole", tiles_per_shard=4 * S.TILES)
    a_file = lambda x: max(r["count"] for r in x.rows.groupBy(S.F.input_file_name()).count().collect())
    assert few.n == a_file(few) == 1
    old, S.TILES = S.TILES, 5
    try:
        assert a_file(S.Shards.build(tiles.repartition(1), tiles_per_shard=10)) <= 2
    finally:
        S.TILES = old


def test_best_of_each_image(tiles, store):
    q = a_query(2, 2, 5)
    want = rows_of(A.scan(tiles, q, 8, SPEC, per_image=True).df)
    for walk in ("scan", "threshold", "frontier"):
        assert rows_of(A.ranked(S.hits_of(store.search([q], 8, SPEC, walk, per_image=True)), 8)) == want


def test_empty_table(spark, tiles):
    none = tiles.filter("false")
    for walk in ("threshold", "frontier"):
        assert A.ALGORITHMS[walk](none, a_query(2, 2), 5, SPEC).df.count() == 0


def test_store_keeps_appends_and_compacts(spark, tiles, tmp_path):
    old = S.Shards.build(tiles.filter("image_id < 200"), str(tmp_path / "a"), 100)
    both = S.Shards.open(spark, str(tmp_path / "a")).append(tiles.filter("image_id >= 200"))
    q = a_query(2, 3)
    want = rows_of(A.scan(tiles, q, 9, SPEC).df)
    for store in (both, both.compact()):
        assert rows_of(A.ranked(S.hits_of(store.search([q], 9, SPEC, "threshold")), 9)) == want
    assert old.n < both.n and both.compact().n == 1
    have = {tuple(r) for r in both.tiles().collect()}
    assert have == {tuple(r) for r in tiles.drop("bg").collect()}


def test_packed_order_keeps_rows_and_closeness():
    f = np.random.default_rng(0).random((5000, 3))
    place = S.packed_order(f)
    assert sorted(place) == list(range(5000))
    spread = lambda p: np.mean([np.ptp(f[p[i : i + 64]], axis=0).prod() for i in range(0, 4992, 64)])
    assert spread(place) < 0.05 * spread(np.arange(5000))
    assert len(S.packed_order(np.zeros((0, 3)))) == 0


def test_walks_save_work(spark):
    """On images that are mostly unlike the query, both walks solve a small part of the alignments."""
    rng = np.random.default_rng(1)
    rows = [(i, r, c, *(float(x) for x in f), 0.0) for i in range(100) for r in range(6) for c in range(6) for f in [rng.normal((i % 50) * 8, 1, 2)]]
    df = spark.createDataFrame(rows, TILE)
    store = S.Shards.build(df)
    f = np.array([[x[3], x[4]] for x in rows if x[0] == 20 and x[1] < 2 and x[2] < 5])
    q = Query(2, 5, f, np.full(10, 30.0))
    solved = {w: S.counters(store.search([q], 10, ScoreSpec("l1", 1, 5), w)).first()["solved"] for w in ("scan", "threshold", "frontier")}
    assert solved["threshold"] < 0.2 * solved["scan"] and solved["frontier"] < 0.2 * solved["scan"]


def test_driver_holds_few_boxes(tiles):
    from gridmatch.index.packed import PackedIndex
    from gridmatch.overlap.placements import query_tiles

    q = a_query(2, 2, 1)
    fine = PackedIndex.build(tiles, leaf_rows=8)
    coarse = PackedIndex.of(fine.leaf, most=20)
    assert len(fine.ids) > 20 >= len(coarse.ids) and coarse.rows == fine.rows and coarse.unit == 16
    near = lambda i: sorted(map(tuple, i.first_neighbours(q, query_tiles(tiles.sparkSession, q), SPEC, 9).select("q", "nn", "image_id", "r", "c").collect()))
    assert near(coarse) == near(fine)
    assert rows_of(A.radius(tiles, q, 5, SPEC, coarse).df) == rows_of(A.scan(tiles, q, 5, SPEC).df)


def test_a_few_shards_go_out_in_copies(spark, tiles):
    """One shard's queries are walked by several tasks, and each query once."""
    one = S.Shards.build(tiles)
    assert one.n == 1
    qs = [Query(2, 2, q.features, q.bg, i) for i, q in enumerate(a_query(2, 2, s) for s in range(6))]
    found = one.walk(one.rows, qs, 5, SPEC, "scan", "corner_dp", S.solvers.CORNERS, {}, False, {})
    assert found.rdd.getNumPartitions() == 6
    assert rows_of(A.ranked(S.hits_of(found), 5, single=False)) == rows_of(A.scan(tiles, qs, 5, SPEC).df)
    assert sorted(x["query_id"] for x in S.counters(found).collect()) == list(range(6))
