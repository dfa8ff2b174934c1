"""Arrivals of different columns in one store."""

import pytest

from geopages.llm.sharding import ShardStore


def test_merges_keep_the_columns_of_all_arrivals(spark, tmp_path):
    store = ShardStore(spark, f"file://{tmp_path}/c", target_bytes=10**9, fan_in=2)
    store.append(spark.range(0, 10, 1, 1).selectExpr("id as doc_id"))
    store.append(spark.range(10, 20, 1, 1).selectExpr("id as doc_id", "string(id) as lang"))
    want = {(i, None if i < 10 else str(i)) for i in range(20)}
    assert {(r.doc_id, r.lang) for r in store.read().collect()} == want
    store.compact()
    assert len(store.shards()) == 1
    assert {(r.doc_id, r.lang) for r in store.read().collect()} == want
    with pytest.raises(ValueError, match="lang"):
        store.append(spark.range(1).selectExpr("id as doc_id", "id as lang"))
    assert store.version() == 3
