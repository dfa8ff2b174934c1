import random

import pytest

from geopages.llm._common import Scratch
from geopages.llm.components import connected_components
from geopages.llm.ngram_join import keep_one_of_each_group, similar_groups

from . import brute


def corpus(seed, n=150):
    r = random.Random(seed)
    vocab = ["w%d" % i for i in range(60)] + ["É", "Aa", "aA", "the", "of"]
    docs = []
    for i in range(n):
        if docs and r.random() < 0.6:
            w = (r.choice(docs)[1] or "x").split(" ")
            for _ in range(r.choice([0, 1, 1, 2, 3])):
                w[r.randrange(len(w))] = r.choice(vocab)
            t = " ".join(w)
        else:
            t = " ".join(r.choice(vocab) for _ in range(r.choice([1, 2, 3, 5, 30, 80, 120])))
        docs.append((i * 7 % 1009, t))
    docs += [(2000, None), (2001, ""), (2002, "\n"), (2003, "The  OF"), (2004, "the of"), (2005, "w1"), (2006, "W1")]
    return docs


@pytest.mark.parametrize("seed, n, percent", [(1, 3, 90), (2, 3, 90), (3, 5, 80), (4, 2, 70)])
def test_against_brute_force(spark, seed, n, percent):
    docs = corpus(seed)
    got = similar_groups(spark.createDataFrame(docs, "doc_id long, text string").repartition(4), n, percent).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute.op6(docs, n, percent)
    assert len(got) == len(docs)


def test_chains_link_through_members_that_are_not_neighbours(spark):
    base = [f"a{i}" for i in range(200)]
    docs = [(i, " ".join(base[k * 2 :] + [f"x{j}" for j in range(k * 2)])) for i, k in enumerate([0, 3, 1, 4, 2, 9, 8])]
    got = similar_groups(spark.createDataFrame(docs, "doc_id long, text string"), 3, 90).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute.op6(docs)


def test_stage_keeps_the_columns_and_one_of_a_group(spark):
    t = " ".join(f"w{i}" for i in range(40))
    df = spark.createDataFrame([(5, t, "a"), (3, t + " more", "b"), (9, "else", "c"), (None, t, "d"), (10, None, "e")], "doc_id long, text string, n long".replace("n long", "component string"))
    got = {r.doc_id: r.component for r in keep_one_of_each_group(df).collect()}
    assert got == {3: "b", 9: "c", 10: "e"}
    assert similar_groups(df.limit(0)).collect() == []


def test_components(spark):
    edges = [(i, i + 1) for i in range(100, 160)] + [(5, 3), (3, 5), (7, 7), (5, 9), (None, 4)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark, "t")).collect()}
    assert got == {**{i: 100 for i in range(100, 161)}, 3: 3, 5: 3, 9: 3}
    assert connected_components(spark.createDataFrame([], "u long, v long"), Scratch(spark, "t")).collect() == []


def test_sets_that_share_a_class_are_told_apart(spark):
    from geopages.llm.ngram_join import _Join

    docs = corpus(6)
    join = _Join(spark.createDataFrame(docs, "doc_id long, text string"), 3, 90, bits=5)
    assert join.number.shared
    got = {r.doc_id: (r.n_shingles, r.component_id if r.component is not None else r.doc_id) for r in join.keys.again(join.groups()).collect()}
    assert got == brute.op6(docs)
