import corpus_pipeline
from geopages.llm import decontaminate, quality_rules

from . import brute

SF = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    good = {r.doc_id for r in quality_rules.judge(docs).where("kept").collect()}
    text = {r.doc_id: r.text for r in docs.collect()}
    groups = brute.op6([(d, text[d]) for d in good], 5, 80)
    one = {d for d, (_, c) in groups.items() if c == d}
    items = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    clean = {d for d, v in brute.op3([(d, text[d]) for d in one], items).items() if not v[4]}
    want = [good, one, clean, clean, clean]
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, SF).write.parquet(f"{tmp_path}/{i}")
        docs = spark.read.parquet(f"{tmp_path}/{i}")
        assert name == ["quality", "near_duplicates", "decontamination", "mixing", "sharding"][i]
        assert i == 4 or docs.columns == columns
        rows = [r.doc_id for r in docs.select("doc_id").collect()]
        assert len(rows) == len(set(rows)) and set(rows) == want[i]
    assert len(clean) < len(one) < len(good) < len(text)
    assert {r.doc_id for r in corpus_pipeline.run(spark, SF).collect()} == clean
    assert decontaminate.WINDOW == 10
