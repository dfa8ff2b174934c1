from fractions import Fraction

import pytest

from geopages.llm import mixing
from geopages.llm.sharding import ShardStore, shard


@pytest.mark.parametrize("weights", [{"a": 1}, {"a": 3, "b": 2, "c": 2}, {"a": 50, "b": 1, "c": 1, "d": 1}, {f"s{i}": i + 1 for i in range(15)}])
def test_deviation_is_below_one_block(weights):
    total = sum(weights.values())
    given = dict.fromkeys(weights, 0)
    for t, s in enumerate(mixing.period(weights) * 2, 1):
        given[s] += 1
        assert all(abs(given[x] - Fraction(t * w, total)) < 1 for x, w in weights.items())


def test_schedule_keeps_all_rows_and_meets_windows(spark):
    docs = [(i, "big" if i % 3 else f"s{i % 7}", "x", i) for i in range(3000)] + [(None, None, None, 1), (5, "big", "x", 5), (5, "big", "x", 5)]
    df = spark.createDataFrame(docs, "doc_id long, source string, text string, slot long").repartition(5)
    targets = {"big": 4, "s0": 2, "s1": 1}
    rows = mixing.schedule(df, targets, rest_weight=1, block=10).collect()
    assert len(rows) == len(docs) and len({r._mix.position for r in rows}) == len(docs)
    assert sorted(str(tuple(r)[:4]) for r in rows) == sorted(map(str, docs))
    assert all(r._mix.release <= r._mix.slot < r._mix.deadline for r in rows)
    owner = {}
    for r in rows:
        owner.setdefault(r._mix.slot, set()).add(r.source if r.source in targets else "")
    assert all(len(v) == 1 for v in owner.values()) and sorted(owner) == list(range(len(owner)))
    first = [next(iter(owner[t])) for t in range(16)]
    assert first.count("big") == 8 and first.count("s0") == 4
    ordered = mixing.mixed(df, targets, 1, 10)
    assert ordered.columns == df.columns and ordered.count() == len(docs)
    assert mixing.schedule(df.limit(0), targets).collect() == []


def test_store_versions_and_merges(spark, tmp_path):
    store = ShardStore(spark, f"file://{tmp_path}/s", target_bytes=400_000, fan_in=4)
    df = spark.range(0, 20_000).selectExpr("id as doc_id", "sha2(string(id), 256) as text", "id as _name")
    for i in range(3):
        store.append(df.where(f"doc_id % 3 = {i}").repartition(8))
    before = store.shards()
    assert store.version() == 3 and len(before) == 24 and sum(s.rows for s in before) == 20_000
    store.compact(sole=True)
    after = store.shards()
    assert sum(s.rows for s in after) == 20_000 and len(after) < 24 and not store.plan(after)
    got = store.read()
    assert got.drop("_shard").columns == df.columns
    assert {r.doc_id: r.text for r in got.collect()} == {r.doc_id: r.text for r in df.collect()}
    with pytest.raises(Exception, match="exist"):
        store.commit(after, 0)
    assert len(list((tmp_path / "s/data").glob("*/*.parquet"))) == len(after)


def test_merged_order_is_arrival_order(spark, tmp_path):
    store = ShardStore(spark, f"file://{tmp_path}/o", target_bytes=10**9, fan_in=4)
    store.append(spark.range(0, 1000, 1, 4))
    store.compact()
    (one,) = store.shards()
    assert [r.id for r in spark.read.parquet(one.path).collect()] == list(range(1000))


def test_shard_small_cases(spark):
    df = spark.createDataFrame([(1, None), (1, None), (None, "x")], "doc_id long, text string")
    assert sorted(map(str, [r.doc_id for r in shard(df).collect()])) == ["1", "1", "None"]
    out = shard(df.limit(0))
    assert out.collect() == [] and out.columns == ["doc_id", "shard_id", "shard_rows", "shard_level"]
