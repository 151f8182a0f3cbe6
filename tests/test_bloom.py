"""The Bloom curve has steps before and after capacity whatever the table's size."""

import pytest


@pytest.mark.parametrize("scale", ["sf0.001", "sf0.01"])
@pytest.mark.parametrize("name", ["bloom_fpr_quarter", "bloom_fpr_quarter_strict"])
def test_capacity_follows_the_stream(spark, name, scale):
    import duckdb

    from segdedup import queries

    d = f"/root/testdata/{scale}"
    got = sorted(map(tuple, queries.QUERIES[name](spark, d).select("step", "n_inserted", "fp", "holdout").collect()))
    base = duckdb.connect()
    base.execute(f"create view lineitem as select * from '{d}/lineitem.parquet'")
    assert got == sorted(base.sql(queries.ORACLE_SQL[name]).fetchall())
    print(name, scale, got)
    share = [fp / holdout for _, _, fp, holdout in got]
    assert share[0] < 0.02 and share[-1] > 0.4
