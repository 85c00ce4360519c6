"""Queries over all rows of their tables, against their SQL twins, which name no subset either."""

import duckdb
import pytest

from radarlake import registry
from test_registry import TABLES


def _whole(sf, name):
    """Columns and rows of a twin."""
    db = duckdb.connect()
    for t in TABLES:
        db.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    told = db.sql(registry.oracles()[name])
    return told.columns, told.fetchall()


def _same(got, want):
    """Equal rows; fractions to 2e-5."""
    split = lambda r: (tuple(v for v in r if not isinstance(v, float)), [v for v in r if isinstance(v, float)])
    got, want = sorted(map(split, got)), sorted(map(split, want))
    assert [k for k, _ in got] == [k for k, _ in want]
    assert [x for _, v in got for x in v] == pytest.approx([x for _, v in want for x in v], abs=2e-5)


def _against_twin(spark, sf, name):
    columns, want = _whole(sf, name)
    _same([tuple(r) for r in registry.queries()[name](spark, sf).select(*columns).collect()], want)


@pytest.mark.parametrize("name", ["m4_index", "m4_index_shift", "m4_index_pad"])
def test_index_holds_all_scenes(spark, sf, name):
    _against_twin(spark, sf, name)


@pytest.mark.parametrize("name", ["m6_map", "m6_warp_join", "m6_warp", "m6_warp_nn", "m6_valid", "m12_label_stats"])
def test_maps_hold_all_tiles(spark, sf, name):
    _against_twin(spark, sf, name)


def test_cover_holds_all_scenes(spark, sf):
    cover = registry.queries()["m5_cover"](spark, sf)
    orders = spark.read.parquet(f"{sf}/orders.parquet")
    assert {r[0] for r in cover.select("scene_id").distinct().collect()} == {r[0] for r in orders.select("o_orderkey").collect()}
    requests = registry.queries()["m5_requests"](spark, sf)
    assert requests.agg({"patches": "sum"}).first()[0] == cover.count()


def test_retrieval_searches_all_rows(spark, sf):
    _against_twin(spark, sf, "e_retrieval")


def test_recall_leaves_out_only_the_own_row(spark, sf):
    _against_twin(spark, sf, "e_recall")


def test_retrieval_in_blocks(spark, sf, monkeypatch):
    """More blocks, the same hits; one vector held by many ids goes to the smallest ids."""
    from radarlake.methods import evaluate

    def hits():
        rows = [(i, i % 3, [1.0, 0.0] if i % 4 else [0.0, float(i)]) for i in range(60)]
        e = spark.createDataFrame(rows, "vec_id long, label int, embedding array<float>")
        return sorted(tuple(r) for r in evaluate.retrieval(e.filter("vec_id % 10 = 1"), e, 5).select("query", "hit", "rank").collect())

    one = hits()
    monkeypatch.setattr(evaluate, "QUERY_BLOCK", 2)
    monkeypatch.setattr(evaluate, "CORPUS_BLOCK", 7)
    assert hits() == one
    assert [h for q, h, _ in one if q == 1] == [1, 2, 3, 5, 6]


@pytest.mark.parametrize("name", ["m10_repr", "op_map", "m8_shuffle"])
def test_no_first_ids_only(spark, sf, name):
    _against_twin(spark, sf, name)
    assert not any(x in registry.oracles()[name] for x in ("< 100", "<= 50"))
