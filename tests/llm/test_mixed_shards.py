"""The mixture's schedule holds on the shards that the pipeline leaves."""

import random
from fractions import Fraction

import corpus_pipeline
from geopages.llm import mixing
from geopages.llm.sharding import Shard, ShardStore


def test_shards_hold_the_schedule(spark, tmp_path):
    r = random.Random(3)
    docs = [(i, f"src{r.choice([0, 0, 0, 0, 1, 2, 3])}", "".join(r.choice("abcdefgh ") for _ in range(r.choice([20, 50, 4000])))) for i in range(2000)]
    df = spark.createDataFrame(docs, "doc_id long, source string, text string").repartition(3)
    want = [x.doc_id for x in mixing.schedule(df).orderBy("_mix.position").select("doc_id").collect()]
    was = {k: spark.conf.get(k) for k in ("spark.sql.adaptive.coalescePartitions.enabled", "spark.sql.files.maxPartitionBytes", "spark.sql.files.openCostInBytes")}
    for k, v in zip(was, ("false", "400000", "1"), strict=True):
        spark.conf.set(k, v)
    try:
        # files of unlike sizes, in the order of the schedule
        for i, (a, b) in enumerate([(0, 30), (30, 900), (900, 1000), (1000, 1020), (1020, 1900), (1900, 2000)]):
            place = {d: n for n, d in enumerate(want)}
            rows = sorted((x for x in docs if a <= place[x[0]] < b), key=lambda x: place[x[0]])
            spark.createDataFrame(rows, df.schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in/k={i}")
        again = spark.read.parquet(f"{tmp_path}/in").select("doc_id", "source", "text")
        got = corpus_pipeline.sharding(spark, again, "").collect()
        assert [x.doc_id for x in sorted(got, key=lambda x: x.position)] == want
        assert sorted(x.position for x in got) == list(range(len(docs)))
        store = ShardStore(spark, f"file://{tmp_path}/s", target_bytes=300_000, fan_in=2)
        mixing.mixed(df).write.parquet(f"{tmp_path}/mixed")
        store.append(spark.read.parquet(f"{tmp_path}/mixed"))
        store.compact()
        shards = store.shards()
        assert len(shards) > 2
        rows = [x for s in shards for x in spark.read.parquet(s.path).collect()]
    finally:
        for k, v in was.items():
            spark.conf.set(k, v)
    assert [x.doc_id for x in rows] == want
    # while all sources last, each is less than one block from its share after every prefix
    weights = {s: mixing.TARGETS[s] for s in ("src0", "src1", "src2", "src3")}
    left = {s: sum(x[1] == s for x in docs) for s in weights}
    given = dict.fromkeys(weights, 0)
    for n, x in enumerate(rows, 1):
        given[x.source] += 1
        if any(given[s] > left[s] - mixing.BLOCK for s in weights):
            break
        assert all(abs(given[s] - Fraction(n * weights[s], sum(weights.values()))) < 2 * mixing.BLOCK for s in weights)
        if n % mixing.BLOCK == 0:
            assert all(abs(given[s] - Fraction(n * weights[s], sum(weights.values()))) < mixing.BLOCK for s in weights)
    assert n > 10 * mixing.BLOCK


def test_only_neighbours_are_merged(spark, tmp_path):
    store = ShardStore(spark, f"file://{tmp_path}/n", target_bytes=1000, fan_in=2)
    sizes = [10, 900, 10, 10, 900, 10]
    runs = store.plan([Shard(f"p{i}", b, 1, 0, i) for i, b in enumerate(sizes)])
    assert [[s.seq for s in r] for r in runs] == [[2, 3]]
