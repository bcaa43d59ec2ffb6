"""Bounds and warm-up sizes come from the given tables, and equal their SQL."""

import os

import pytest

from echowalk.plans import catalogue


@pytest.mark.parametrize("name", ["bounds_table", "warmup_size"])
def test_sizes_of_the_given_tables(spark, sf, name):
    import duckdb

    db = duckdb.connect()
    for t in ("orders", "lineitem", "events"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{os.path.join(sf, t)}.parquet'")
    want = sorted(db.execute(catalogue.ORACLE_SQL[name]).fetchall(), key=repr)
    got = sorted(map(tuple, catalogue.QUERIES[name](spark, sf).collect()), key=repr)
    assert got == want and len({r[0] for r in got}) == 3
