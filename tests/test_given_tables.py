"""Standing examples on given tables: their results against SQL, and what Spark reads for them."""

import duckdb
import pytest

from gridmatch import catalog
from gridmatch.catalog import relational
from gridmatch.tables import NAMES

D = "/root/testdata/sf0.001"
MOVED = ["fig6_sweeps", "fig9_overlaps", "flood_fill_region", "region_connected", "region_sink_class", "steiner_instance_cells", "table1_lists"]


def wanted(name, columns):
    con = duckdb.connect()
    for t in NAMES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{D}/{t}.parquet'")
    got = con.execute(f"SELECT {', '.join(columns)} FROM ({catalog.oracles()[name]})")
    return sorted(map(str, got.fetchall()))


@pytest.mark.parametrize("name", MOVED)
def test_reads_tables(spark, name, monkeypatch):
    read = []
    kept = relational.saved
    monkeypatch.setattr(relational, "saved", lambda df: (read.extend(df.inputFiles()), kept(df))[1])
    got = catalog.queries()[name](spark, D)
    read += got.inputFiles()
    assert any(f"{t}.parquet" in x for t in ("lineitem", "orders") for x in read)
    rows = sorted(str(tuple(r)) for r in got.collect())
    assert len(rows) > 10 and rows == wanted(name, got.columns)


def test_recursion_of_many_rows(spark):
    key = "spark.sql.cteRecursionRowLimit"
    before = spark.conf.get(key)
    spark.conf.set(key, "50")  # as a million is for 60 times as many images
    try:
        got = catalog.queries()["sweep_recursive"](spark, D)
        assert sorted(str(tuple(r)) for r in got.collect()) == wanted("sweep_recursive", got.columns)
        assert spark.conf.get(key) == "50"
    finally:
        spark.conf.set(key, before)
