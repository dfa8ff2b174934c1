"""The registered queries over their whole tables, against brute force."""

import __spark_entry__ as entry

from . import brute

SF = "/root/testdata/sf0.001"


def _docs(spark):
    return [tuple(r) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]


def _rows(spark, name):
    return {r[0]: tuple(r)[1:] for r in entry.queries()[name](spark, SF).collect()}


def test_op1(spark):
    got = _rows(spark, "op1_quality_rules")
    assert {d: v[:5] for d, v in got.items()} == {d: brute.op1_base(t) for d, t in _docs(spark)}


def test_op2(spark):
    assert _rows(spark, "op2_suffix_dedup") == brute.op2(_docs(spark))


def test_op3(spark):
    items = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    assert _rows(spark, "op3_decontaminate") == brute.op3(_docs(spark), items)


def test_op4_and_op10_have_every_document_once(spark):
    ids = sorted(d for d, _ in _docs(spark))
    assert sorted(r.doc_id for r in entry.queries()["op4_sharding"](spark, SF).collect()) == ids
    assert sorted(r.doc_id for r in entry.queries()["op10_mixing"](spark, SF).collect()) == ids


def test_op6(spark):
    assert _rows(spark, "op6_ngram_join") == brute.op6(_docs(spark))


def test_op7_leaves_no_planted_pattern(spark):
    import re

    found = re.compile(r"[\w.]+@mail\d+\.example\.com|[0-9a-f]{40}")
    before, after = _docs(spark), {r.doc_id: r.text for r in entry.queries()["op7_surrogates"](spark, SF).collect()}
    assert len(after) == len(before)
    kept = {m for _, t in before for m in found.findall(t)}
    assert kept and not any(m in t for m in kept for t in after.values())


def test_op5_and_op8_cover_every_document(spark):
    docs = dict(_docs(spark))
    got = entry.queries()["op5_token_counts"](spark, SF).groupBy("doc_id").agg({"n_bytes": "sum", "n_tokens": "sum"}).collect()
    assert {r.doc_id: r["sum(n_bytes)"] for r in got} == {d: len(t.encode()) for d, t in docs.items()}
    found = {r.doc_id: r.licenses for r in entry.queries()["op8_license_scan"](spark, SF).collect()}
    assert set(found) == set(docs)
    for d, t in docs.items():
        assert ("MIT" in found[d]) == ("Released under the MIT License." in t)


def test_op9(spark):
    assert _rows(spark, "op9_seed_extend") == brute.op9(_docs(spark))
