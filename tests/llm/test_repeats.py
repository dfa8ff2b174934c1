import random

import pytest

from geopages.llm.deep_shallow import blind_trie_order, deep_shallow_order
from geopages.llm.seed_extend import remove_repeated_passages
from geopages.llm.suffix_dedup import remove_repeated_strings

from . import brute


def corpus(seed, n=60, unit=6):
    r = random.Random(seed)
    vocab = ["w%d" % i for i in range(40)] + ["é", "ßa", "the", "of"]
    text = lambda k: " ".join(r.choice(vocab) for _ in range(k))
    passages = [text(r.choice([8, 14, 36, 50, 80])) for _ in range(unit)]
    docs = []
    for i in range(n):
        kind = r.random()
        if kind < 0.15 and docs:
            t = r.choice(docs)[1] or ""
            w = t.split(" ")
            if len(w) > 3 and r.random() < 0.7:
                w[r.randrange(len(w))] = "edit%d" % i
            t = " ".join(w)
        else:
            t = " ".join(r.choice(passages) if r.random() < 0.4 else text(r.randrange(1, 60)) for _ in range(r.randrange(1, 5)))
        docs.append((i * 3 + 1, t))
    docs += [(1000, None), (1001, ""), (1002, " \n\t "), (1003, "a" * 400), (1004, "a" * 120), (1005, "ab " * 200), (1006, "ab " * 150 + "end"), (1007, "x" * 50), (1008, "x" * 49)]
    r.shuffle(docs)
    return docs


@pytest.mark.parametrize("seed", [1, 2])
def test_suffix_dedup_against_brute_force(spark, seed):
    docs = corpus(seed)
    got = remove_repeated_strings(spark.createDataFrame(docs, "doc_id long, text string").repartition(3)).collect()
    want = brute.op2(docs)
    assert {r.doc_id: (r.n_bytes, r.n_removed, len(r.removed), r.kept_sha256) for r in got} == want
    assert len(got) == len(docs) and sum(w[1] for w in want.values()) > 1000


@pytest.mark.parametrize("seed", [3, 4])
def test_seed_extend_against_brute_force(spark, seed):
    docs = corpus(seed)
    got = remove_repeated_passages(spark.createDataFrame(docs, "doc_id long, text string").repartition(3)).collect()
    want = brute.op9(docs)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in got} == want
    assert len(got) == len(docs) and sum(w[1] for w in want.values()) > 100


def test_hot_seeds_take_the_other_way_with_equal_results(spark, monkeypatch):
    from geopages.llm import _repeats

    monkeypatch.setattr(_repeats, "HOT_SEED", 1)
    docs = corpus(5)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert {r.doc_id: (r.n_bytes, r.n_removed, len(r.removed), r.kept_sha256) for r in remove_repeated_strings(df).collect()} == brute.op2(docs)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in remove_repeated_passages(df).collect()} == brute.op9(docs)


def test_small_batches_and_long_texts(spark, monkeypatch):
    from geopages.llm import _symbols

    r = random.Random(9)
    passage = " ".join("p%d" % r.randrange(500) for _ in range(300))
    long = " ".join("q%d" % r.randrange(900) for _ in range(4000))
    docs = [(i, f"{i} {passage[i:]} tail{i}" if i % 3 else f"{long[i * 50:]} {i}") for i in range(40)]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(2)
    was = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    monkeypatch.setattr(_symbols, "BLOCK", 1000)
    try:
        got = remove_repeated_strings(df).collect()
        assert {r.doc_id: (r.n_bytes, r.n_removed, len(r.removed), r.kept_sha256) for r in got} == brute.op2(docs)
        got = remove_repeated_passages(df).collect()
        assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in got} == brute.op9(docs)
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", was)


def test_pieces_of_long_texts_give_the_same_anchors(monkeypatch):
    import numpy as np

    from geopages.llm import _repeats, _symbols

    r = np.random.default_rng(1)
    values = r.integers(97, 101, 30_000).astype(np.uint8)
    borders = np.array([0, 20, 20, 25_000, 30_000])
    spec = _repeats.Spec(50, 16, True, "bytes")
    whole = _repeats.anchors(values, borders, spec)
    monkeypatch.setattr(_symbols, "BLOCK", 700)
    parts = _repeats.anchors(values, borders, spec)
    rows = lambda x: set(zip(*[c.tolist() for c in x], strict=True))
    assert rows(whole) == rows(parts)


def test_empty_repeated_and_clashing(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert remove_repeated_strings(empty).collect() == [] and remove_repeated_passages(empty).collect() == []
    t = " ".join("w%d" % i for i in range(60))
    df = spark.createDataFrame([(1, t, 5, "x"), (1, t, 5, "x"), (None, t, 6, "y"), (None, None, 6, "y"), (7, None, 1, "z")], "doc_id long, text string, kept long, spans string")
    got = {r.doc_id: r for r in remove_repeated_strings(df).collect()}
    assert set(got) == {1, None, 7} and got[1].n_removed == 0 and got[None].n_removed == len(t) and got[7].n_bytes == 0
    got = {r.doc_id: r.n_removed for r in remove_repeated_passages(df).collect()}
    assert got == {1: 60, None: 60, 7: 0}


def test_deep_shallow_order():
    r = random.Random(4)
    for _ in range(200):
        s = [bytes(r.choice(b"ab\0") for _ in range(r.randrange(0, 40))) for _ in range(r.randrange(1, 30))]
        s += [s[0]] * 3
        want = sorted(range(len(s)), key=lambda i: s[i])
        assert [s[i] for i in deep_shallow_order(s, 0, r.choice([0, 4, 8, 24]))] == [s[i] for i in want]
        assert [s[i] for i in blind_trie_order(s, list(range(len(s))))] == [s[i] for i in want]
