"""Every SQL twin belongs to a query, and a few run side by side."""

import duckdb
import pytest

from radarlake import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def test_names():
    assert set(registry.oracles()) <= set(registry.queries())


@pytest.mark.parametrize("name", ["m1_audit", "m2_kernel", "m4_cells", "m7_label", "m8_split", "m9_tail"])
def test_side_by_side(spark, sf, name):
    db = duckdb.connect()
    for t in TABLES:
        db.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = registry.queries()[name](spark, sf)
    columns = sorted(df.columns)
    got = sorted(tuple(str(v) for v in r) for r in df.select(*columns).collect())
    told = db.sql(registry.oracles()[name])
    want = sorted(tuple(str(r[told.columns.index(c)]) for c in columns) for r in told.fetchall())
    assert got == want


def test_entry_runs(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).limit(1).count() == 1
