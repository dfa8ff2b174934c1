"""Two writers of one store, an older reader, and what vacuum may remove."""

from concurrent.futures import ThreadPoolExecutor

import pytest

from geopages.llm.sharding import ShardStore, VersionTaken


def _ids(df):
    return sorted(r.doc_id for r in df.select("doc_id").collect())


def _part(spark, lo, hi):
    return spark.range(lo, hi, 1, 4).selectExpr("id as doc_id", "sha2(string(id), 256) as text")


def test_a_merge_does_not_lose_an_arrival_in_between(spark, tmp_path):
    root = f"file://{tmp_path}/w"
    one, two = ShardStore(spark, root, 10**9, 2), ShardStore(spark, root, 10**9, 2)
    one.append(_part(spark, 0, 100))
    written = two._written(_part(spark, 100, 200), 0)  # an arrival that is not committed yet
    old = one.version()
    reader = one.read(old)
    one.compact()
    one.vacuum()
    assert all(two._fs.exists(two._path(p)) for p, _, _ in written)
    assert _ids(reader) == list(range(100))
    two.append(_part(spark, 100, 200))
    assert _ids(one.read()) == list(range(200)) and _ids(one.read(old)) == list(range(100))
    one.vacuum(1, 0)
    assert _ids(one.read()) == list(range(200))
    assert not any(two._fs.exists(two._path(p)) for p, _, _ in written)


def test_writers_at_once_all_get_in(spark, tmp_path):
    root = f"file://{tmp_path}/p"
    ShardStore(spark, root, 10**9, 2).append(_part(spark, 0, 10))

    def write(i):
        store = ShardStore(spark, root, 10**9, 2)
        store.append(_part(spark, 10 * i, 10 * i + 10))
        store.compact()

    with ThreadPoolExecutor(4) as pool:
        list(pool.map(write, range(1, 5)))
    store = ShardStore(spark, root, 10**9, 2)
    assert _ids(store.read()) == list(range(50))
    shards = store.shards()
    assert sum(s.rows for s in shards) == 50 and len({s.path for s in shards}) == len(shards)
    with pytest.raises(VersionTaken):
        store.commit(shards, store.version() - 1)
