"""Rasters, descriptors, components and measures against direct computation."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridmatch.features import descriptors as D
from gridmatch.measure.quality import precision_at_k
from gridmatch.region import expressions, solvers
from gridmatch.score import functions as S
from gridmatch.workload.experiments import growth


def test_glyph_tiles_of_odd_texts(spark):
    text = "".join(chr(33 + i % 90) for i in range(1100))
    df = spark.createDataFrame([(1, text), (2, None), (3, ""), (4, "é" * 511), (5, "x" * 512)], "doc_id long, text string")
    got = {(r["image_id"], r["r"], r["c"]): r["px"] for r in D.glyph_tiles(df).collect()}
    assert sorted({k[0] for k in got}) == [1, 5] and len(got) == 24
    assert got[1, 1, 3] == [ord(text[512 + 64 * y + 24 + x]) for y in range(8) for x in range(8)]
    padded = D.glyph_tiles(df, edge="pad").groupBy("image_id").count().collect()
    assert {r["image_id"]: r["count"] for r in padded} == {1: 24, 4: 8, 5: 8}
    with pytest.raises(ValueError):
        D.glyph_tiles(df, edge="wrap")


def test_binary_images(spark):
    px = np.random.default_rng(0).integers(0, 256, (20, 24)).astype(np.uint8)
    df = spark.createDataFrame([("a", bytearray(px.tobytes())), ("b", bytearray())], "path string, content binary")
    got = {(r["r"], r["c"]): r["px"] for r in D.binary_tiles(df, 24).collect()}
    assert len(got) == 6 and got[1, 2] == px[8:16, 16:24].ravel().tolist()


def test_descriptors():
    px = np.random.default_rng(1).integers(0, 256, (5, 64))
    h = D.structure_histogram(px)
    g = px[2].reshape(8, 8)
    want = np.zeros(256)
    for y in range(6):
        for x in range(6):
            want[np.unique(g[y : y + 3, x : x + 3])] += 1 / 36
    assert np.allclose(h[2], want)
    assert np.allclose(D.level_histogram(px)[3], np.bincount(px[3], minlength=256) / 64)
    assert D.moments_descriptor(px).shape == (5, 4)


def test_registered_descriptor(spark):
    D.register_descriptor("mean", D.moments_descriptor)
    t = D.glyph_tiles(spark.createDataFrame([(1, "ab" * 256)], "doc_id long, text string"))
    assert D.describe(t, "mean").first()["fv"][0] == pytest.approx(97.5)


def test_components_against_numpy(spark):
    x = np.random.default_rng(2).normal(size=(300, 5)) @ np.diag([5, 3, 1, 0.5, 0.1])
    df = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "id long, fv array<double>").repartition(3)
    m = D.fit_pca(df)
    val, vec = np.linalg.eigh(np.cov(x.T, bias=True))
    assert np.allclose(m.variance, val[::-1]) and m.energy(2) == pytest.approx(val[::-1][:2].sum() / val.sum())
    got = np.array([[r["f0"], r["f1"]] for r in D.project(df, m, 2).orderBy("id").collect()])
    assert np.allclose(np.abs(got), np.abs((x - x.mean(0)) @ vec[:, ::-1][:, :2]))
    back = D.standardize(D.project(df, m, 2), ["f0", "f1"]).agg(F.avg("f0").alias("m"), F.stddev_samp("f1").alias("s")).first()
    assert abs(back["m"]) < 1e-9 and back["s"] == pytest.approx(1)
    with pytest.raises(ValueError):
        D.fit_pca(df.filter("false"))


def test_background_of_the_darkest_tenth(spark):
    df = spark.createDataFrame([(float(i), i % 7) for i in range(100)], "bg double, f0 int")
    want = np.mean([i % 7 for i in range(100) if i <= 9])
    assert D.learn_background(df, ["f0"]).first()["f0"] == pytest.approx(want, abs=0.4)


def test_score_properties(spark):
    """Scores fall with distance for every shape; an exponential's fitted rate is one over its mean."""
    d = spark.range(0, 500).select(F.col("id").cast("double").alias("d"))
    for g in S.SHAPES:
        s = [r[0] for r in d.orderBy("d").select(S.template_score(F.lit(10.0), F.col("d"), g, 3)).collect()]
        assert all(a >= b for a, b in zip(s, s[1:]))
    assert S.fit_exponential(d.filter("d > 0"), "d") == pytest.approx(1 / 250)
    area = d.select(S.exp_density(F.col("d") / 10, 0.5).alias("p")).agg(F.sum("p") / 10).first()[0]
    assert area == pytest.approx(1, abs=0.03)
    m = d.limit(1).select(S.mahalanobis([F.lit(1.0), F.lit(2.0)], [F.lit(0.0), F.lit(0.0)], np.diag([1.0, 0.25]))).first()[0]
    assert m == pytest.approx(np.sqrt(2))


@pytest.mark.parametrize(("h", "w"), [(2, 3), (3, 3)])
def test_mask_expressions(spark, h, w):
    m = spark.range(1, 1 << (h * w)).withColumnRenamed("id", "m")
    rows = m.select("m", expressions.connected(F.col("m"), h, w).alias("c"), *[expressions.has_sink(F.col("m"), h, w, k).alias(k) for k in solvers.CORNERS]).collect()
    for r in rows:
        assert r["c"] == solvers.is_connected(r["m"], h, w)
        if r["c"]:
            assert {k for k in solvers.CORNERS if r[k]} == solvers.sink_class(r["m"], h, w)


def test_precision_counts_queries_without_results(spark):
    r = spark.createDataFrame([(1, 5, 1), (1, 6, 2)], "query_id long, image_id long, rank int")
    t = spark.createDataFrame([(1, 6, True), (2, 7, True)], "query_id long, image_id long, is_true boolean")
    got = {of: {x["query_id"]: x["precision"] for x in precision_at_k(r, t, 5, of, t).collect()} for of in ("returned", "k", "possible")}
    assert got == {"returned": {1: 0.5, 2: 0.0}, "k": {1: 0.2, 2: 0.0}, "possible": {1: 1.0, 2: 0.0}}


def test_growth_of_a_line(spark):
    df = spark.createDataFrame([("frontier", x, 3.0 * x) for x in (10, 20, 40)], "algorithm string, n int, distances double")
    g = growth(df, "n").first()
    assert (g["r2"], g["slope"], g["power"]) == pytest.approx((1, 3, 1))
