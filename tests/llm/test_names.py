"""Surrogates of names: one for a surname in all forms of a person, distinct however many there are."""

import re

from pyspark.sql import functions as F

from geopages.llm import surrogates
from geopages.llm.surrogates import surrogate, with_surrogates


def test_a_surname_has_one_surrogate_in_all_forms(spark):
    text = "Mr Karl Stone came. Mr Stone spoke; Mrs. Ada Stone left, Mr Leo Berg stayed. Г-н Иван Петров и Г-н Петров."
    new = with_surrogates(spark.createDataFrame([(1, text)], "doc_id long, text string"), "k").first().text
    m = re.fullmatch(r"Mr (\w+) (\w+) came\. Mr (\w+) spoke; Mrs\. (\w+) (\w+) left, Mr (\w+) (\w+) stayed\. Г-н ([А-Яа-я]+) ([А-Яа-я]+) и Г-н ([А-Яа-я]+)\.", new)
    assert m and m[2] == m[3] == m[5] != m[7] and m[1] != m[6] and m[9] == m[10]


def test_draws_do_not_run_out(spark, monkeypatch):
    # with two syllables to draw from, 300 surnames and given names are far more than the first draws hold
    monkeypatch.setattr(surrogates, "SYLLABLES", {"latin": ["ba", "den"], "cyrillic": ["ба", "ден"]})
    monkeypatch.setattr(surrogates, "GIVEN", {k: v[:2] for k, v in surrogates.GIVEN.items()})
    text = " ".join(f"Mr A{chr(97 + i % 26)}{chr(97 + i // 26)} S{chr(97 + i % 26)}{chr(97 + i // 26)};" for i in range(300))
    new = with_surrogates(spark.createDataFrame([(1, text)], "doc_id long, text string"), "k").first().text
    assert len(set(re.findall(r"Mr \w+ \w+;", new))) == 300


def test_surnames_grow_with_the_salt(spark):
    forms = spark.range(70_000).select(F.lit("surname").alias("kind"), F.concat(F.lit("S"), F.col("id").cast("string")).alias("form"), F.lit(2).alias("salt"))
    n = forms.select(surrogate(F.col("kind"), F.col("form"), F.col("salt"), "k").alias("x")).distinct().count()
    assert n > 69_500
