"""Benchmark decontamination by a distributed positional inverted index.

The index holds a posting (document, position) for every training token that a test
text has too; it is written in document order, with no shuffle. A test text is cut
into windows of ``window`` words. Each window is looked up from its rarest term
(document frequency over the whole corpus): that term's postings, moved back by its
place in the window, are the candidate starts, and the postings of the next rarest
terms, moved alike, are intersected with them one by one. Exact phrases are what all
of a window's terms leave; proximity matches have all terms of a phrase within a
span of positions, in any order. Built-in expressions only.

Results by case: a null, empty or wordless text has no words and no hits; a test text
of fewer words than a window is one window, one without words has none; repeated test
rows count once; rows of one doc_id are judged each by its own text, and equal rows get
equal results, one for each; an empty benchmark hits nothing; empty documents give no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import Keyed, Scratch, keyed, table

#: What stands between words; A-Z are lower-cased, other letters stay.
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WINDOW = 10
#: Test vocabulary and windows are broadcast up to this many rows, else they are joined by shuffles; the result is the same.
BROADCAST_ROWS = 200_000
#: Parts into which the rows of a term are dealt in such a shuffle, so that a very common term is no task of its own.
SALTS = 32
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER), GAP), "")


def _bounded(df: DataFrame) -> DataFrame:
    """``df``, a written table, marked for broadcast if it is small enough."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def _met(many: DataFrame, few: DataFrame, key: str) -> DataFrame:
    """Rows of ``many`` (doc, pos, ...) joined with a written table: by broadcast if it is small enough, else by the key and a salt."""
    if few.count() <= BROADCAST_ROWS:
        return many.join(F.broadcast(few), key)
    dealt = F.pmod(F.xxhash64("doc", "pos"), F.lit(SALTS)).cast("int")
    salts = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
    return many.withColumn("_salt", dealt).join(few.withColumn("_salt", salts), [key, "_salt"]).drop("_salt")


def windows_of(items: DataFrame, window: int) -> DataFrame:
    """(item_id, window, terms): every ``window`` consecutive words of each item, or all of them where there are fewer."""
    w = items.select("item_id", words_of(F.col("text")).alias("w")).where(F.size("w") > 0).distinct()
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.size("w") - window))
    w = w.select("item_id", "w", F.explode(starts).alias("s")).select("item_id", F.slice("w", F.col("s") + 1, F.lit(window)).alias("terms"))
    return w.groupBy("terms").agg(F.sort_array(F.collect_set(F.col("item_id").cast("string"))).alias("items")).select(F.xxhash64("terms").alias("window"), "terms", "items")


class PositionalIndex:
    """Postings of the test vocabulary over all documents, and each term's document frequency."""

    def __init__(self, docs: DataFrame, windows: DataFrame, scratch: Scratch):
        """``docs``: (doc, text); ``windows``: (window, terms, ...)."""
        self.scratch = scratch
        names = windows.select(F.explode("terms").alias("term")).distinct()
        # a term's number is a hash; the pair (number, term) is checked for collisions
        names = scratch.put(names.select("term", F.xxhash64("term").alias("t")), "vocabulary")
        if names.groupBy("t").count().where("count > 1").head(1):
            raise ValueError("two test terms share a hash")
        tokens = docs.select("doc", F.posexplode(words_of(F.col("text"))).alias("pos", "term"))
        postings = _met(tokens, names, "term").select("t", "doc", F.col("pos").cast("int").alias("pos"))
        self.postings = scratch.put(postings, "postings")
        self.frequency = scratch.put(self.postings.groupBy("t").agg(F.count("*").alias("df")), "frequency")

    def _ranked(self, windows: DataFrame) -> DataFrame:
        """(window, size, ranked array<struct<df,t,at>>): terms from the rarest; windows with a term that the corpus lacks are left out."""
        t = windows.select("window", F.size("terms").alias("size"), F.posexplode("terms").alias("at", "term")).select("window", "size", "at", F.xxhash64("term").alias("t"))
        t = t.join(_bounded(self.frequency), "t").groupBy("window", "size").agg(F.sort_array(F.collect_list(F.struct("df", "t", "at"))).alias("ranked"))
        return t.where(F.size("ranked") == F.col("size"))

    def phrases(self, windows: DataFrame) -> DataFrame:
        """(doc, start, window, size): every occurrence of every window."""
        ranked = self.scratch.put(self._ranked(windows), "ranked")
        few = lambda df: self.scratch.put(df, "terms")
        first = few(ranked.select("window", "size", F.col("ranked")[0]["t"].alias("t"), F.col("ranked")[0]["at"].alias("at")))
        found = _met(self.postings, first, "t").select("doc", (F.col("pos") - F.col("at")).alias("start"), "window", "size").where("start >= 0")
        # the second rarest term in the same way: its postings, moved, meet the candidates
        second = few(ranked.where("size > 1").select("window", F.col("ranked")[1]["t"].alias("t"), F.col("ranked")[1]["at"].alias("at")))
        again = _met(self.postings, second, "t").select("doc", (F.col("pos") - F.col("at")).alias("start"), "window")
        one = found.where("size = 1")
        found = found.where("size > 1").join(again, ["doc", "start", "window"], "left_semi")
        found = self.scratch.put(found.unionByName(one).distinct(), "candidates")
        # the others, of the documents that are left
        more = ranked.where("size > 2").select("window", F.explode(F.slice("ranked", F.lit(3), F.greatest(F.col("size") - 2, F.lit(0)))).alias("x")).select("window", "x.t", "x.at")
        asked = found.join(_bounded(few(more)), "window").select("doc", "start", "window", "t", (F.col("start") + F.col("at")).alias("pos"))
        kept = self._of_documents(found.select("doc").distinct())
        met = asked.join(kept, ["doc", "pos", "t"]).groupBy("doc", "start", "window").agg(F.count("*").alias("met"))
        return found.join(met, ["doc", "start", "window"], "left").where("coalesce(met, 0) = greatest(size - 2, 0)").select("doc", "start", "window", "size")

    def _of_documents(self, docs: DataFrame) -> DataFrame:
        """Postings of ``docs`` and few others: a bit for each document's hash, in a table of up to 2**20 words, leaves out most others before any shuffle."""
        bits = 1 << min(26, max(10, (16 * docs.count()).bit_length()))
        place = lambda d: F.pmod(F.xxhash64(d["doc"]), F.lit(bits))
        bit = lambda h: F.expr(f"shiftleft(1L, cast({h} & 63 as int))")
        words = docs.select(place(docs).alias("h")).select(F.shiftright("h", 6).alias("word"), bit("h").alias("bit"))
        words = self.scratch.put(words.groupBy("word").agg(F.bit_or("bit").alias("mask")), "bits")
        p = self.postings.withColumn("h", place(self.postings)).withColumn("word", F.shiftright("h", 6))
        return p.join(F.broadcast(words), "word").where(F.col("mask").bitwiseAND(bit("h")) != 0).select("t", "doc", "pos")

    def near(self, phrases: DataFrame, span: int) -> DataFrame:
        """(window, doc, start): places where all distinct terms of a phrase stand within ``span`` positions, in any order.

        Positions fall into overlapping ranges of 2 * span, so each such place lies whole in one.
        """
        t = phrases.select("window", F.explode(F.array_distinct("terms")).alias("term")).select("window", F.xxhash64("term").alias("t"))
        need = t.groupBy("window").agg(F.count("*").alias("need"))
        hit = _met(self.postings, self.scratch.put(t, "terms"), "t").withColumn("range", F.explode(F.array(F.floor(F.col("pos") / span), F.floor(F.col("pos") / span) - 1)))
        places = hit.groupBy("window", "doc", "range").agg(F.array_sort(F.collect_list(F.struct("pos", "t"))).alias("p"), F.count_distinct("t").alias("n")).join(need, "window").where("n = need")
        within = F.filter("p", lambda x: F.size(F.array_distinct(F.transform(F.filter("p", lambda y: (y["pos"] >= x["pos"]) & (y["pos"] < x["pos"] + span)), lambda y: y["t"]))) == F.col("need"))
        return places.select("window", "doc", F.explode(within).alias("x")).select("window", "doc", F.col("x.pos").alias("start")).distinct()


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> tuple[Keyed, DataFrame, Scratch]:
    """All documents under keys, and (doc, n_hit, items) of those in which a window occurs."""
    scratch = Scratch(docs.sparkSession, "decontaminate")
    keys = keyed(docs, scratch)
    windows = scratch.put(windows_of(benchmark, window), "windows")
    found = scratch.put(PositionalIndex(keys.rows, windows, scratch).phrases(windows), "phrases")
    ends = found.groupBy("doc", "start").agg(F.max(F.col("start") + F.col("size")).alias("end"))
    covered = ends.selectExpr("doc", "end - greatest(start, coalesce(max(end) OVER (PARTITION BY doc ORDER BY start ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS n")
    n_hit = covered.groupBy("doc").agg(F.sum(F.greatest("n", F.lit(0))).alias("n_hit"))
    items = found.select("doc", "window").distinct().join(windows.select("window", F.explode("items").alias("item")), "window")
    items = items.groupBy("doc").agg(F.sort_array(F.collect_set("item")).alias("items"))
    return keys, n_hit.join(items, "doc"), scratch


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, n_words, n_hit, items): words inside occurrences of test windows, and the items that have them."""
    keys, found, _ = hits(docs, benchmark, window)
    size = keys.rows.select("doc", F.size(words_of(F.col("text"))).cast("long").alias("n_words"))
    out = keys.again(size.join(found, "doc", "left"))
    return out.select(
        "doc_id", "n_words",
        F.coalesce(F.col("n_hit"), F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` without those in which a test window occurs; columns stay as they are."""
    keys, found, scratch = hits(docs, benchmark, window)
    bad = scratch.put(found.select("doc"), "bad")
    return keys.matched(docs, _bounded(bad), "left_anti")


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"),
    )


ORACLE_SQL = rf"""
WITH iw AS (SELECT DISTINCT item_id, regexp_extract_all(translate(text, '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
k AS (SELECT item_id, list_aggregate(w[s + 1:s + {WINDOW}], 'string_agg', ' ') AS key, len(w[s + 1:s + {WINDOW}]) AS size
      FROM (SELECT item_id, w, unnest(generate_series(0, greatest(0, len(w) - {WINDOW}))) AS s FROM iw WHERE len(w) > 0)),
d AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS w FROM documents),
sizes AS (SELECT DISTINCT size FROM k),
p AS (SELECT doc_id, i, size, list_aggregate(w[i:i + size - 1], 'string_agg', ' ') AS key
      FROM (SELECT doc_id, w, size, unnest(generate_series(1, len(w) - size + 1)) AS i FROM d CROSS JOIN sizes WHERE len(w) >= size)),
m AS (SELECT DISTINCT doc_id, i, size, item_id FROM p JOIN k USING (size, key)),
h AS (SELECT doc_id, count(DISTINCT j) AS n_hit FROM (SELECT doc_id, unnest(generate_series(i, i + size - 1)) AS j FROM m) GROUP BY doc_id),
it AS (SELECT doc_id, list_sort(list(DISTINCT item_id::VARCHAR)) AS items FROM m GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(len(items), 0)::BIGINT AS n_items,
  sha256(coalesce(list_aggregate(items, 'string_agg', ','), '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN it USING (doc_id)
"""
