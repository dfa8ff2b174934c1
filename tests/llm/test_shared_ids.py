"""Rows that share a doc_id, or have none, are judged each by its own text."""

from collections import Counter

from geopages.llm.decontaminate import contamination, drop_contaminated
from geopages.llm.ngram_join import keep_one_of_each_group, similar_groups
from geopages.llm.seed_extend import remove_repeated_passages
from geopages.llm.suffix_dedup import remove_repeated_strings


def _prose(tag, n=60):
    return " ".join(f"{tag}{i}" for i in range(n))


def _rows(df, *columns):
    return Counter(tuple(r[c] for c in columns) for r in df.collect())


def test_decontamination_judges_each_row(spark):
    bad, clean = _prose("b"), _prose("z")
    docs = [(1, bad, "x"), (1, clean, "y"), (None, bad + " q", "x"), (None, clean + " q", "y"), (None, None, "y"), (2, clean, "y"), (2, clean, "y"), (2**63 - 1, bad, "x")]
    d = spark.createDataFrame(docs, "doc_id long, text string, mark string").repartition(3)
    b = spark.createDataFrame([(7, bad)], "item_id long, text string")
    assert _rows(contamination(d, b), "doc_id", "n_hit") == Counter({(1, 60): 1, (1, 0): 1, (None, 60): 1, (None, 0): 2, (2, 0): 2, (2**63 - 1, 60): 1})
    kept = drop_contaminated(d, b)
    assert kept.columns == d.columns
    assert _rows(kept, "doc_id", "text", "mark") == Counter(x for x in docs if x[2] == "y")


def test_near_duplicates_of_shared_ids(spark):
    t, u = _prose("t"), _prose("u")
    docs = [(1, t, 0), (1, u, 0), (2, u + " more", 1), (3, _prose("v"), 0), (3, _prose("v"), 0), (None, t, 1), (None, _prose("w"), 0), (None, _prose("x"), 0), (None, None, 0), (None, None, 0)]
    d = spark.createDataFrame(docs, "doc_id long, text string, drop int").repartition(3)
    got = _rows(similar_groups(d), "doc_id", "component_id", "n_shingles")
    assert got == Counter({(1, 1, 56): 2, (2, 1, 57): 1, (3, 3, 56): 2, (None, 1, 56): 1, (None, None, 56): 2, (None, None, 0): 2})
    assert _rows(keep_one_of_each_group(d), *d.columns) == Counter({x: 1 for x in docs if not x[2]})


def test_repeats_of_shared_ids(spark):
    t, u = _prose("t"), _prose("u")
    docs = [(1, "a " + t), (1, u), (1, t), (2, u), (2, "b " + u), (None, t), (None, _prose("w")), (None, _prose("w") + " c"), (4, _prose("y")), (4, _prose("y"))]
    d = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    n = lambda x: len(x.encode())
    # texts of one id, or of none, aren't earlier than one another
    got = _rows(remove_repeated_strings(d), "doc_id", "n_bytes", "n_removed")
    want = [(1, n(t) + 2, 0), (1, n(u), 0), (1, n(t), 0), (2, n(u), n(u)), (2, n(u) + 2, n(u)), (None, n(t), n(t)), (None, n(_prose("w")), 0), (None, n(_prose("w")) + 2, 0), (4, n(_prose("y")), 0), (4, n(_prose("y")), 0)]
    assert got == Counter(want)
    got = _rows(remove_repeated_passages(d), "doc_id", "n_words", "n_removed")
    assert got == Counter([(1, 61, 60), (1, 60, 60), (1, 60, 60), (2, 60, 60), (2, 61, 60), (None, 60, 60), (None, 60, 60), (None, 61, 60), (4, 60, 0), (4, 60, 0)])
