"""Clashing columns, very long texts, and both plans of joins that depend on sizes."""

import random

import pytest
from pyspark.sql import functions as F

from geopages.llm import _common, decontaminate, license_scan, ngram_join, quality_rules, sharding, surrogates, token_counts

from . import brute

#: Names that operators use inside.
NAMES = "_shard __file __row __place doc pos term t window items h cut kind form rows n words text2 _id _digest _row found label".split()


def _clashing(spark, rows):
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    return d.withColumns({n: F.lit(f"x{i}") for i, n in enumerate(NAMES)} | {"a.b": F.lit(1)})


ROWS = [(i, f"alpha beta gamma {i} the of and to in is it for was on with be by as this are at from " + "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10" * (i % 3 == 0), "en", "src1") for i in range(12)] + [(None, None, None, None), (5, "a@b.example.org Released under the MIT License.", "en", "src0"), (5, "a@b.example.org Released under the MIT License.", "en", "src0")]
ITEMS = [("i1", "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10")]


def test_columns_of_clashing_names(spark):
    d = _clashing(spark, ROWS)
    items = spark.createDataFrame(ITEMS, "item_id string, text string").withColumn("terms", F.lit(1)).withColumn("doc", F.lit(2))
    plain = d.select("doc_id", "text", "lang", "source")
    rows = lambda x: sorted(map(str, x.collect()))
    assert rows(decontaminate.contamination(d, items)) == rows(decontaminate.contamination(plain, items))
    assert rows(token_counts.section_tokens(d)) == rows(token_counts.section_tokens(plain))
    assert rows(license_scan.find_licenses(d)) == rows(license_scan.find_licenses(plain))
    assert rows(surrogates.with_surrogates(d, "k")) == rows(surrogates.with_surrogates(plain, "k"))
    assert rows(quality_rules.judge(d)) == rows(quality_rules.judge(plain))
    for out in (decontaminate.drop_contaminated(d, items), quality_rules.keep_good(d), ngram_join.keep_one_of_each_group(d)):
        assert out.columns == d.columns and 0 < out.count() < d.count()
    assert sharding.shard(d, position=True).count() == d.count()


def test_very_long_texts(spark):
    r = random.Random(4)
    long = " ".join(r.choice("the of and to harbour lamp boat w3 w4".split()) for _ in range(300_000))
    d = spark.createDataFrame([(1, long + " w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 mail a@b.example.org. Released under the MIT License."), (2, "z" * 1_000_000)], "doc_id long, text string")
    items = spark.createDataFrame(ITEMS, "item_id string, text string")
    got = {x.doc_id: x for x in decontaminate.contamination(d, items).collect()}
    assert (got[1].n_hit, got[2].n_hit) == (10, 0) and got[2].n_words == 1
    assert {x.doc_id: [y.license for y in x.licenses] for x in license_scan.find_licenses(d).collect()} == {1: ["MIT"], 2: []}
    assert {x.doc_id: x.n_entities for x in surrogates.with_surrogates(d, "k").collect()} == {1: 1, 2: 0}
    assert {x.doc_id: x.n_bytes for x in token_counts.section_tokens(d).collect()} == {x.doc_id: len(x.text) for x in d.collect()}


@pytest.mark.parametrize("limit", [0, 200_000])
def test_joins_by_broadcast_and_by_shuffle(spark, monkeypatch, limit):
    monkeypatch.setattr(decontaminate, "BROADCAST_ROWS", limit)
    monkeypatch.setattr(_common, "BROADCAST_ROWS", limit)
    r = random.Random(7)
    vocab = [f"v{i}" for i in range(12)]
    text = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    items = [(i, text(r.choice([2, 5, 10, 12]))) for i in range(10)]
    docs = [(i, text(40) + " " + items[i % 10][1]) for i in range(60)]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {x.doc_id: (x.n_words, x.n_hit, len(x["items"])) for x in decontaminate.contamination(d, b).collect()}
    assert got == {k: v[:3] for k, v in brute.op3(docs, items).items()}
    shared = spark.createDataFrame(docs[:5] + [(1, "other text"), (1, docs[1][1]), (None, "x")], "doc_id long, text string")
    assert decontaminate.contamination(shared, b).count() == 8
