import duckdb

from parsieve.operators import metrics
from parsieve.plans import catalog


def test_bounds_follow_the_table(spark):
    """A constant column is in no lattice."""
    rows = metrics.fold_bounds(spark.createDataFrame([(1, "x", 5, 0), (2, "y", 6, 0)], "a int, b string, c int, d int")).collect()
    assert [tuple(r) for r in rows] == [(0, 3, 1, 1.5), (1, 6, 3, 1.0), (2, 3, 3, 0.5)]
    assert metrics.fold_bounds(spark.createDataFrame([], "a int, b int")).count() == 0


def test_bounds_match_sql(spark):
    sf = "/root/testdata/sf0.01"
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{sf}/lineitem.parquet'")
    want = con.execute(catalog.oracle_sql()["fold_memory_bounds"]).fetchall()
    got = [tuple(r) for r in catalog.queries()["fold_memory_bounds"](spark, sf).collect()]
    assert sorted(got) == sorted(want) and len(got) == 12
