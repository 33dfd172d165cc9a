"""The operators around the search, against SQL on the smallest tables."""

import duckdb
import pytest

from parsieve.plans import surround

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(surround.QUERIES))
def test_same_rows_as_sql(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages labels".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    want = con.execute(surround.SQL[name])
    columns = sorted(c[0] for c in want.description)
    order = [c[0] for c in want.description]
    expected = sorted((tuple(r[order.index(c)] for c in columns) for r in want.fetchall()), key=repr)
    df = surround.QUERIES[name](spark, SF)
    assert sorted(df.columns) == columns
    assert sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr) == expected
