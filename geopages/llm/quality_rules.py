"""Quality rules: distribution divergence from language references.

Two histograms describe a text: its character classes, and the most common words
of each known language with all other words as one more bin. Each is compared with
every language's reference, the pooled histogram of the documents that declare the
language, by Jensen-Shannon distance (square root of the divergence in bits, 0 to 1);
the nearest language counts, so a wrong or missing label does no harm. Texts too
short for a histogram to mean much are not judged by it. Base rules on length and
repeated windows come first. All of it is built-in expressions over one row; the
only shuffle is the sum that makes the references.

Results by case: a null or empty text has no words, so it fails the base rules; a
language without long enough documents has no reference; where there is none at all
no text is judged by divergence; equal rows get equal results, one for each; an empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from math import log2, sqrt

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import Scratch, table

# The twenty most common words of each language.
COMMON_WORDS = {
    "en": "the of and to a in is that it for was on with be by as this are at from".split(),
    "de": "der die und in den von zu das mit sich auf des für ist nicht im dem ein als eine".split(),
    "fr": "de la le et les des en un du une que pour est qui dans par sur pas au avec".split(),
    "es": "de la que el en y los se del las por un no con su una para es al lo".split(),
}
VOCABULARY = sorted({w for v in COMMON_WORDS.values() for w in v})
SPACE = r"[\x20\x09-\x0D]+"
#: Character classes in the order in which they are taken out of the text; what is left are symbols.
CLASSES = (r"\p{Ll}+", SPACE, r"\p{Lu}+", r"[.,;:!?]+", r"\p{Nd}+", r"\p{L}+")
SYMBOLS = r"[#*$%&|<>]+"
WINDOW = 8

MIN_WORDS, MAX_REPEATED = 20, 30
#: Fewest words (characters) of a text whose word (class) histogram is judged or goes into a reference.
GUARD_WORDS, GUARD_CHARS = 100, 400
#: Greatest distances of a kept text. That of words is a share of the distance that a text with none of
#: the common words has, which depends on how common they are in the references; classes can differ wholly.
MAX_WORD_SHARE, MAX_CLASS_DISTANCE = 0.9, 0.27


def _shifted(a: str, b: int, n: Column) -> Column:
    return F.slice(a, F.lit(b), F.greatest(n, F.lit(0)))


def _pairs(h: str, shift: int) -> Column:
    """Hash of each element with the one ``shift`` places on."""
    n = F.size(h) - shift
    return F.zip_with(_shifted(h, 1, n), _shifted(h, shift + 1, n), lambda a, b: F.xxhash64(a, b))


def features(docs: DataFrame) -> DataFrame:
    """Counts of every text: words, their characters, symbols, repeated lines and words, and both histograms."""
    d = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("t"), F.col("lang").cast("string").alias("lang"))
    d = d.withColumn("words", F.array_remove(F.split("t", SPACE), ""))
    rest, counts = "t", []
    for i, c in enumerate(CLASSES):
        d = d.withColumn(f"r{i}", F.regexp_replace(rest, c, ""))
        counts.append(F.char_length(rest) - F.char_length(f"r{i}"))
        rest = f"r{i}"
    counts.append(F.char_length(rest))
    lines = F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    d = d.select(
        "doc_id", "lang", F.size("words").alias("n_words"), F.char_length("t").alias("n_chars"),
        F.array(*counts).alias("classes"),
        (F.char_length("t") - F.char_length(F.regexp_replace("t", SYMBOLS, ""))).alias("n_symbols"),
        lines.alias("lines"),
        F.filter("words", lambda w: w.isin(VOCABULARY)).alias("common"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("h1"),
    )
    d = d.withColumn("h2", _pairs("h1", 1)).withColumn("h4", _pairs("h2", 2)).withColumn("h8", _pairs("h4", 4))
    d = d.withColumn("repeats", F.size(F.array_distinct("h8")) < F.size("h8"))
    none = F.array().cast("array<struct<h:bigint,i:int>>")
    sorted_windows = F.sort_array(F.transform("h8", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    d = d.withColumn("w", F.when(F.col("repeats"), sorted_windows).otherwise(none))
    same = lambda x, i: F.coalesce(F.get("w", i)["h"] == x["h"], F.lit(False))
    d = d.withColumn("at", F.sort_array(F.transform(F.filter("w", lambda x, i: same(x, i - 1) | same(x, i + 1)), lambda x: x["i"])))
    reach = F.transform("at", lambda p, i: F.least(F.lit(WINDOW), F.coalesce(F.get("at", i + 1) - p, F.lit(WINDOW))))
    n_common = F.size("common")
    return d.select(
        "doc_id", "lang", F.col("n_words").cast("long"), F.col("n_chars").cast("long"), "classes",
        (F.col("n_chars") - F.get("classes", F.lit(1))).cast("long").alias("word_chars"),
        F.col("n_symbols").cast("long"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.aggregate(reach, F.lit(0), lambda a, x: a + x).cast("long").alias("n_repeat_words"),
        F.array(*[n_common - F.size(F.array_remove("common", w)) for w in VOCABULARY]).alias("common"),
    )


def _of_language(lang: str) -> Column:
    """Counts of a language's common words, then of all other words."""
    own = [F.get("common", F.lit(VOCABULARY.index(w))) for w in COMMON_WORDS[lang]]
    return F.array(*own, F.col("n_words") - sum(own[1:], own[0]))


def references(feats: DataFrame) -> dict[str, dict[str, list[float]]]:
    """Of each language in COMMON_WORDS: pooled shares of its word bins and of the character classes. A row for each language at most."""
    long = feats.where((F.col("n_words") >= GUARD_WORDS) & (F.col("n_chars") >= GUARD_CHARS) & F.col("lang").isin(list(COMMON_WORDS)))
    sums = [F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(len(VOCABULARY))]
    sums += [F.sum(F.get("classes", F.lit(i))).alias(f"c{i}") for i in range(len(CLASSES) + 1)]
    out = {}
    for r in long.groupBy("lang").agg(F.sum("n_words").alias("n"), *sums).collect():
        own = [r[f"w{VOCABULARY.index(w)}"] for w in COMMON_WORDS[r.lang]]
        classes = [r[f"c{i}"] for i in range(len(CLASSES) + 1)]
        out[r.lang] = {"words": [x / r.n for x in [*own, r.n - sum(own)]], "classes": [x / sum(classes) for x in classes]}
    return out


def js_distance(counts: Column, total: Column, reference: list[float]) -> Column:
    """Jensen-Shannon distance in bits between counts / total and a reference; null where total is 0."""
    term = lambda x, m: F.when(x > 0, x * F.log2(x / m)).otherwise(0.0)
    q = F.array(*[F.lit(float(x)) for x in reference])
    parts = F.zip_with(F.transform(counts, lambda c: c / total), q, lambda p, r: term(p, (p + r) / 2) + term(r, (p + r) / 2))
    return F.when(total > 0, F.sqrt(F.greatest(F.lit(0.0), F.aggregate(parts, F.lit(0.0), lambda a, x: a + x) / 2)))


def bare_distance(refs: dict[str, dict[str, list[float]]]) -> float:
    """Distance to the nearest reference of a text with no common word of any language: the greatest there is for words."""
    out = []
    for r in refs.values():
        common, other = 1 - r["words"][-1], r["words"][-1]
        m = (1 + other) / 2
        out.append(sqrt(max(0.0, (common + log2(1 / m) + (other * log2(other / m) if other else 0.0)) / 2)))
    return min(out, default=1.0)


def judge(docs: DataFrame) -> DataFrame:
    """A row for each document: its counts, distances to the nearest references, base_failed and kept."""
    scratch = Scratch(docs.sparkSession, "quality_rules")
    feats = scratch.put(features(docs), "features")
    refs = references(feats)
    nearest = lambda cols: F.array_min(F.array(*cols)) if cols else F.lit(None).cast("double")
    word = nearest([js_distance(_of_language(x), F.col("n_words"), r["words"]) for x, r in sorted(refs.items())])
    cls = nearest([js_distance(F.col("classes"), F.col("n_chars"), r["classes"]) for _, r in sorted(refs.items())])
    d = feats.withColumn("word_distance", F.when(F.col("n_words") >= GUARD_WORDS, word)).withColumn("class_distance", F.when(F.col("n_chars") >= GUARD_CHARS, cls))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEATED * F.col("n_words"))
    fits = (F.coalesce("word_distance", F.lit(0.0)) <= MAX_WORD_SHARE * bare_distance(refs)) & (F.coalesce("class_distance", F.lit(0.0)) <= MAX_CLASS_DISTANCE)
    return d.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & fits).alias("kept"), "word_distance", "class_distance")


def keep_good(docs: DataFrame) -> DataFrame:
    """``docs`` without those that the rules reject; of rows with one doc_id, each is judged by its own text. Columns stay as they are."""
    key = F.xxhash64(docs["doc_id"], docs["text"])
    tagged = docs.select("text", "lang", F.struct("doc_id", key.alias("h")).alias("doc_id"))
    good = judge(tagged).where("kept").select(F.col("doc_id.doc_id").alias("_good_id"), F.col("doc_id.h").alias("_good_hash")).distinct()
    return docs.join(good, docs["doc_id"].eqNullSafe(good["_good_id"]) & (key == good["_good_hash"]), "left_semi")


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _oracle() -> str:
    """The same result in DuckDB SQL, with window functions over unnested words."""
    langs = sorted(COMMON_WORDS)
    gone, rest = [], "t"
    for i, c in enumerate(CLASSES):
        gone.append(f"regexp_replace({rest}, '{c}', '', 'g') AS r{i}")
        rest = f"r{i}"
    steps, prev = "base AS (SELECT row_number() OVER () AS rid, doc_id, lang, coalesce(text, '') AS t FROM documents)", "base"
    for i, g in enumerate(gone):
        steps += f", s{i} AS (SELECT *, {g} FROM {prev})"
        prev = f"s{i}"
    names = ["t", *[f"r{i}" for i in range(len(CLASSES))]]
    classes = ", ".join(f"length({a}) - length({b}) AS c{i}" for i, (a, b) in enumerate(zip(names, names[1:], strict=False)))
    classes += f", length(r{len(CLASSES) - 1}) AS c{len(CLASSES)}"
    n_cls = len(CLASSES) + 1
    vocabulary = ", ".join(f"('{x}', {i}, '{w}')" for x in langs for i, w in enumerate(COMMON_WORDS[x]))
    every = ", ".join(f"'{w}'" for w in VOCABULARY)
    term = lambda p, m: f"CASE WHEN {p} > 0 THEN {p} * log2({p} / ({m})) ELSE 0 END"
    js = f"sqrt(greatest(0.0, sum({term('p', '(p + q) / 2')} + {term('q', '(p + q) / 2')}) / 2))"
    return rf"""
WITH {steps}, feats AS (
  SELECT rid, doc_id, lang, t, length(t) AS n_chars, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS words, {classes},
    length(t) - length(regexp_replace(t, '{SYMBOLS}', '', 'g')) AS n_symbols,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM {prev}),
f AS (SELECT *, len(words) AS n_words FROM feats),
w AS (SELECT rid, unnest(words) AS w, generate_subscripts(words, 1) AS i FROM f),
win AS (SELECT rid, i, [w, {', '.join(f'lead(w, {k}) OVER o' for k in range(1, WINDOW))}] AS k, lead(i, {WINDOW - 1}) OVER o AS e FROM w WINDOW o AS (PARTITION BY rid ORDER BY i)),
twice AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, k) AS n FROM win WHERE e IS NOT NULL) WHERE n > 1),
rep AS (SELECT rid, sum(least({WINDOW}, coalesce(nx - i, {WINDOW}))) AS n_repeat FROM (SELECT rid, i, lead(i) OVER (PARTITION BY rid ORDER BY i) AS nx FROM twice) GROUP BY rid),
voc(l, b, v) AS (VALUES {vocabulary}),
cnt AS (SELECT rid, w AS v, count(*) AS n FROM w WHERE w IN ({every}) GROUP BY ALL),
guard AS (SELECT rid, lang FROM f WHERE n_words >= {GUARD_WORDS} AND n_chars >= {GUARD_CHARS} AND lang IN ({', '.join(f"'{x}'" for x in langs)})),
tot AS (SELECT lang AS l, sum(n_words) AS n FROM f SEMI JOIN guard USING (rid) GROUP BY ALL),
wref AS (SELECT voc.l, b, sum(cnt.n) AS n FROM guard JOIN voc ON voc.l = guard.lang LEFT JOIN cnt ON cnt.rid = guard.rid AND cnt.v = voc.v GROUP BY ALL),
wshare AS (SELECT l, b, v, coalesce(wref.n, 0)::DOUBLE / tot.n AS q FROM wref JOIN tot USING (l) JOIN voc USING (l, b)),
oshare AS (SELECT l, (tot.n - sum(coalesce(wref.n, 0)))::DOUBLE / tot.n AS q FROM wref JOIN tot USING (l) GROUP BY l, tot.n),
bare AS (SELECT coalesce(min(sqrt(greatest(0.0, (1 - q + log2(1 / ((1 + q) / 2)) + CASE WHEN q > 0 THEN q * log2(q / ((1 + q) / 2)) ELSE 0 END) / 2))), 1) AS d FROM oshare),
bins AS (
  SELECT f.rid, s.l, coalesce(cnt.n, 0)::DOUBLE / n_words AS p, s.q FROM f CROSS JOIN wshare s LEFT JOIN cnt ON cnt.rid = f.rid AND cnt.v = s.v WHERE n_words >= {GUARD_WORDS}
  UNION ALL
  SELECT f.rid, o.l, (n_words - coalesce(own, 0))::DOUBLE / n_words, o.q FROM f CROSS JOIN oshare o
  LEFT JOIN (SELECT rid, l, sum(n) AS own FROM cnt JOIN voc USING (v) GROUP BY ALL) c ON c.rid = f.rid AND c.l = o.l WHERE n_words >= {GUARD_WORDS}),
wd AS (SELECT rid, min(d) AS d FROM (SELECT rid, l, {js} AS d FROM bins GROUP BY ALL) GROUP BY rid),
csum AS (SELECT lang AS l, {', '.join(f'sum(c{i}) AS c{i}' for i in range(n_cls))} FROM f SEMI JOIN guard USING (rid) GROUP BY ALL),
cbins AS (SELECT f.rid, s.l, unnest([{', '.join(f'f.c{i}::DOUBLE / n_chars' for i in range(n_cls))}]) AS p, unnest([{', '.join(f's.c{i}::DOUBLE / ({" + ".join(f"s.c{j}" for j in range(n_cls))})' for i in range(n_cls))}]) AS q FROM f CROSS JOIN csum s WHERE n_chars >= {GUARD_CHARS}),
cd AS (SELECT rid, min(d) AS d FROM (SELECT rid, l, {js} AS d FROM cbins GROUP BY ALL) GROUP BY rid)
SELECT doc_id, n_words::BIGINT AS n_words, (n_chars - c1)::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
  coalesce(n_repeat, 0)::BIGINT AS n_repeat_words, (n_words < {MIN_WORDS} OR 100 * coalesce(n_repeat, 0) > {MAX_REPEATED} * n_words) AS base_failed,
  NOT (n_words < {MIN_WORDS} OR 100 * coalesce(n_repeat, 0) > {MAX_REPEATED} * n_words) AND coalesce(wd.d, 0) <= {MAX_WORD_SHARE} * (SELECT d FROM bare) AND coalesce(cd.d, 0) <= {MAX_CLASS_DISTANCE} AS kept
FROM f LEFT JOIN rep USING (rid) LEFT JOIN wd USING (rid) LEFT JOIN cd USING (rid)
"""


ORACLE_SQL = _oracle()
