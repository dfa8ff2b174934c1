import random

import pytest

from geopages.llm.decontaminate import PositionalIndex, contamination, drop_contaminated, windows_of
from geopages.llm._common import Scratch
from geopages.llm.quality_rules import judge, keep_good

from . import brute


def test_base_counts_against_brute_force(spark):
    r = random.Random(5)
    vocab = ["the", "de", "Ünï", "#a", "b|", "x", "y z", "😀"]
    docs = [(i, "".join(r.choice(vocab) + r.choice([" ", "  ", "\n", "\r\n", "\t", "\x0b"]) for _ in range(r.choice([0, 3, 10, 40, 300])))) for i in range(60)]
    docs += [(100, None), (101, ""), (102, "a b c d e f g h " * 5), (103, "\n\n x\n x\n y\n"), (104, "the " * 5000), (104, "the " * 5000)]
    df = spark.createDataFrame([(*d, "en", 1) for d in docs], "doc_id long, text string, lang string, kept int")
    got = judge(df).collect()
    assert sorted((x.doc_id, x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words) for x in got) == sorted((d, *brute.op1_base(t)) for d, t in docs)
    assert all(x.base_failed == (x.n_words < 20 or 100 * x.n_repeat_words > 30 * x.n_words) for x in got) and not any(x.kept for x in got if x.base_failed)
    assert judge(df.limit(0)).collect() == []


def prose(r, n, odd=0.0):
    common = "the of and to a in is that it for was on".split()
    return " ".join(r.choice(common) if r.random() < 0.4 else "".join(r.choice("abcdefghij") for _ in range(6)) + ("***" if r.random() < odd else "") for _ in range(n))


def test_divergence_rejects_other_distributions_and_keeps_short_texts(spark):
    r = random.Random(6)
    docs = [(i, prose(r, 150), r.choice(["en", None, "xx", "en"])) for i in range(60)]
    docs += [(100, prose(r, 150).upper(), "en"), (101, " ".join("".join(r.choice("#$%&*") for _ in range(8)) for _ in range(200)), "en"), (102, prose(r, 25), "en"), (103, " ".join(f"{i}zq{i}" for i in range(25)), "en")]
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string")
    kept = {x.doc_id for x in judge(df).where("kept").collect()}
    assert kept == {*range(60), 102, 103}
    assert {x.doc_id for x in keep_good(df).collect()} == kept and keep_good(df).columns == df.columns


@pytest.mark.parametrize("seed", [1, 2])
def test_contamination_against_brute_force(spark, seed):
    r = random.Random(seed)
    vocab = ["w%d" % i for i in range(25)] + ["É", "The", "a1"]
    text = lambda n: "".join(r.choice(vocab) + r.choice([" ", ", ", "-", "\n"]) for _ in range(n))
    items = [(i, text(r.choice([1, 2, 4, 9, 10, 11, 25]))) for i in range(30)] + [(90, None), (91, "--"), (5, "w1 w2 rare"), (5, "w1 w2 rare")]
    docs = []
    for i in range(120):
        t = text(r.randrange(0, 60))
        if r.random() < 0.4:
            w = (r.choice(items)[1] or "").split(" ")
            t = t + " ".join(w[r.randrange(len(w)) :]).upper() + t
        docs.append((i, t))
    docs += [(500, None), (501, ""), (502, "?!")]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = contamination(d, b).collect()
    want = brute.op3(docs, items)
    sha = lambda x: __import__("hashlib").sha256(",".join(x).encode()).hexdigest()
    assert {x.doc_id: (x.n_words, x.n_hit, len(x["items"]), sha(x["items"]), x.n_hit > 0) for x in got} == want
    assert {x.doc_id for x in drop_contaminated(d, b).collect()} == {k for k, v in want.items() if not v[4]}
    assert {x.n_hit for x in contamination(d, b.limit(0)).collect()} == {0} and contamination(d.limit(0), b).collect() == []


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x x beta"), (2, "beta y alpha"), (3, "alpha " + "z " * 30 + "beta")], "doc long, text string")
    w = windows_of(spark.createDataFrame([(1, "alpha beta")], "item_id long, text string"), 10)
    got = PositionalIndex(docs, w, Scratch(spark, "t")).near(w, 4).collect()
    assert sorted((r.doc, r.start) for r in got) == [(1, 0), (2, 0)]
