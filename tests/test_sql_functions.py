from gridmatch.sql.register import register


def test_functions(spark):
    register(spark)
    one = lambda q: spark.sql(f"SELECT {q}").first()[0]
    a, b = "array(1D, 5D)", "array(4D, 1D)"
    assert (one(f"grid_l1({a}, {b})"), one(f"grid_l2({a}, {b})"), one(f"grid_linf({a}, {b})")) == (7, 5, 4)
    assert one("grid_score(10D, 3D, 2D, 1D)") == 3
    assert one("grid_bound(array(1D, -5D, 3D, CAST(NULL AS DOUBLE)))") == 4 and one("grid_bound(array(-2D, -1D))") == -1
    assert one("grid_mindist(array(0D, 5D), array(1D, 1D), array(2D, 3D))") == 3
    fig = "array(-1D,-1D,10D,-1D,-1D,10D,1D,35D,-1D,-1D,40D,-90D)"
    assert one(f"grid_best_region({fig}, 3, 4)")["score"] == 95 and one(f"grid_exact_region({fig}, 3, 4)")["score"] == 96
    assert one("grid_is_connected(9L, 2, 2)") is False and one("grid_is_connected(7L, 2, 2)") is True
    assert one("grid_sinks(1L, 2, 2)") == "BL,BR,TL,TR"
    assert spark.sql("SELECT count(*) FROM VALUES (2, 2) AS v(r, c), LATERAL grid_overlaps(v.r, v.c, 2, 2)").first()[0] == 9
    assert [tuple(r) for r in spark.sql("SELECT * FROM grid_region_cells(9L, 2)").collect()] == [(0, 0), (1, 1)]
