"""Surrogates for personal data: keyed, type-consistent, distinct and coreferent.

One pattern finds emails, telephone, card and identity numbers, addresses, secrets and
titled names. What an entity is, apart from its spelling, is its canonical form: equal
forms get one surrogate wherever they stand. It is drawn from a keyed hash of the type
and the form: digits for digits under the same punctuation, letters of the same script
and case for letters, hexadecimal for hexadecimal. A name keeps its title; its given name
(of the same gender) and its surname (of the same script) are drawn apart, so a surname has
one surrogate in all forms of a person, and grow with each further draw. A check over the whole corpus draws
anew, with another salt, for forms whose surrogates meet each other or a real entity.
Built-in expressions only.

Results by case: a null text stays null; a text without entities stays as it is; equal
rows get equal results, one for each; an empty table gives no rows; other columns are
ignored; an entity of any length is replaced whole, at its own length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import Scratch, table

# Patterns by type, the more specific first; titles and given names by gender.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)*\.\p{L}{2,}",
    "ip": r"(?<![\d.])(?:\d{1,3}\.){3}\d{1,3}(?![\d]|\.\d)",
    "phone": r"\+\d{1,3}[ .-]?\(?\d{2,4}\)?[ .-]?\d{3,4}[ .-]?\d{4}(?!\d)",
    "identity": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<!\d)\d{4}(?:[ -]?\d{4}){2}[ -]?\d{1,7}(?!\d)",
    "secret": r"(?<![0-9A-Za-z])(?:[0-9a-f]{32,}+|sk-[0-9A-Za-z]{20,}|AKIA[0-9A-Z]{16})(?![0-9A-Za-z])",
    "name": r"(?<!\p{L})(?:Mrs|Mr|Ms|Herr|Frau|Mme|Sra|Sr|Г-жа|Г-н)\.? \p{Lu}\p{Ll}+(?: (?!(?:Mrs|Mr|Ms|Herr|Frau|Mme|Sra|Sr)(?!\p{L}))\p{Lu}\p{Ll}+)?",
}
FEMALE_TITLES = "^(?:Mrs|Ms|Frau|Mme|Sra|Г-жа)"
GIVEN = {
    ("f", "latin"): "Alba Berta Clara Dora Elena Flora Greta Hanna Ines Julia Karla Lena Maria Nora Olga Paula".split(),
    ("m", "latin"): "Anton Bruno Carlos David Emil Felix Georg Hugo Ivan Jonas Karl Leo Martin Nils Oskar Paul".split(),
    ("f", "cyrillic"): "Анна Вера Галина Дарья Елена Зоя Инна Лидия".split(),
    ("m", "cyrillic"): "Антон Борис Виктор Глеб Денис Егор Иван Лев".split(),
}
SYLLABLES = {"latin": "ba den fo gar hel ki lor man nor pe ral sen to vik wal zer".split(), "cyrillic": "ба ден фо гар хел ки лор ман нор пе рал сен то вик вал зер".split()}
ANY = "|".join(PATTERNS.values())
ROUNDS = 12
#: Two hexadecimal digits of a hash are drawn for each syllable of a name.
MOST_SYLLABLES = 2 * ROUNDS


def kind_of(surface: Column) -> Column:
    out = F.lit("name")
    for kind in reversed([k for k in PATTERNS if k != "name"]):
        out = F.when(surface.rlike(f"^(?:{PATTERNS[kind]})$"), F.lit(kind)).otherwise(out)
    return out


def canonical(kind: Column, surface: Column) -> Column:
    digits = F.regexp_replace(surface, r"\D", "")
    return F.when(kind.isin("phone", "identity", "card"), digits).when(kind == "email", F.lower(surface)).when(kind == "name", F.regexp_replace(surface, r"\.", "")).otherwise(surface)


def _number(hex64: Column, start: int, size: int = 7) -> Column:
    return F.conv(F.substring(hex64, start, size), 16, 10).cast("long")


def _syllable(hex64: Column, i: Column) -> Column:
    return F.conv(F.substring(hex64, i * 2 + 9, F.lit(2)), 16, 10).cast("long")


def _pick(values: list[str], n: Column) -> Column:
    return F.get(F.array(*[F.lit(v) for v in values]), F.pmod(n, F.lit(len(values))).cast("int"))


def surrogate(kind: Column, form: Column, salt: Column, key: str) -> Column:
    """Surrogate form of a canonical form, of the same type, length class, script and gender."""
    h = F.sha2(F.concat_ws("\x1f", F.lit(key), kind, form, salt.cast("string")), 256)
    digits = F.translate(h, "abcdef", "036925")
    # a drawn character for each place, kept to the class of what stands there
    at = lambda i, n: F.pmod(F.conv(F.substring(h, F.pmod(i * 2, F.lit(62)) + 1, F.lit(2)), 16, 10).cast("int") + i * 7, F.lit(n))
    letters = "abcdefghijklmnopqrstuvwxyz"
    accents = "áàâäãåæçéèêëíìîïñóòôöõøúùûüýÿß"
    cyrillic = "абвгдежзиклмнопрстуфхцчшщэюя"
    draw = lambda abc, i: F.substring(F.lit(abc), at(i, len(abc)) + 1, F.lit(1))
    chars = lambda text: F.array_join(F.transform(F.split(text, ""), lambda c, i: F.when(c.rlike("[a-z]"), draw(letters, i)).when(c.rlike("[A-Z]"), F.upper(draw(letters, i))).when(c.rlike("[0-9]"), draw("0123456789", i)).when(c.rlike(r"\p{IsCyrillic}"), draw(cyrillic, i)).when(c.rlike(r"\p{L}"), draw(accents, i)).otherwise(c)), "")
    local = F.regexp_extract(form, "^([^@]*)@", 1)
    email = F.concat(chars(local), F.lit("@"), F.substring(h, 50, 8), F.lit(".example.net"))
    ip = F.concat_ws(".", F.lit("10"), *[F.pmod(_number(h, s), F.lit(256)).cast("string") for s in (1, 9, 17)])
    long_digits = F.rpad(digits, 128, "7")
    keep = F.when(kind == "phone", F.length(form) - F.least(F.length(form), F.lit(10))).otherwise(F.lit(1))  # country code, card network
    number = F.concat(F.substring(form, F.lit(1), keep), F.substring(long_digits, F.lit(1), F.length(form) - keep))
    digests = F.array_join(F.transform(F.sequence(F.lit(0), F.floor(F.length(form) / 64).cast("int")), lambda i: F.sha2(F.concat(h, i.cast("string")), 256)), "")
    secret = F.when(form.rlike("^[0-9a-f]+$"), F.substring(digests, F.lit(1), F.length(form))).otherwise(F.concat(F.regexp_extract(form, "^(sk-|AKIA)", 1), chars(F.regexp_replace(form, "^(sk-|AKIA)", ""))))
    # from the second draw on, names grow by syllables, so draws never run out
    word, foreign = F.substring_index(form, " ", -1), form.rlike(r"\p{IsCyrillic}")
    syllables = lambda n: F.array_join(F.transform(F.sequence(F.lit(0), F.lit(MOST_SYLLABLES)), lambda i: F.when(i < n, F.when(word.rlike(r"\p{IsCyrillic}"), _pick(SYLLABLES["cyrillic"], _syllable(h, i))).otherwise(_pick(SYLLABLES["latin"], _syllable(h, i)))).otherwise("")), "")
    surname = F.initcap(syllables(salt + 4))
    female = form.startswith("f ")
    given = F.when(female & foreign, _pick(GIVEN["f", "cyrillic"], _number(h, 1))).when(foreign, _pick(GIVEN["m", "cyrillic"], _number(h, 1))).when(female, _pick(GIVEN["f", "latin"], _number(h, 1))).otherwise(_pick(GIVEN["m", "latin"], _number(h, 1)))
    given = F.concat(F.substring(form, 1, 2), given, syllables(2 * salt))
    return F.when(kind == "email", email).when(kind == "ip", ip).when(kind == "secret", secret).when(kind == "surname", surname).when(kind == "given", given).otherwise(number)


def name_parts(form: Column) -> Column:
    """A name's parts (kind, form) that have surrogates of their own: its surname, and its given name with the gender of its title."""
    parts = F.split(form, " ")
    surname = F.struct(F.lit("surname").alias("kind"), F.element_at(parts, -1).alias("form"))
    gender = F.when(form.rlike(FEMALE_TITLES), F.lit("f ")).otherwise(F.lit("m "))
    given = F.struct(F.lit("given").alias("kind"), F.concat(gender, F.get(parts, F.lit(1))).alias("form"))
    return F.when(F.size(parts) > 2, F.array(surname, given)).otherwise(F.array(surname))


def rendered(kind: Column, surface: Column, replacement: Column) -> Column:
    """The surrogate in the spelling of one surface: digits under its punctuation, a title with its dot."""
    before = lambda i: F.length(F.regexp_replace(F.substring(surface, F.lit(1), i), r"\D", ""))
    digits = F.array_join(F.transform(F.split(surface, ""), lambda c, i: F.when(c.rlike("[0-9]"), F.substring(replacement, before(i) + 1, F.lit(1))).otherwise(c)), "")
    title = F.when(surface.rlike(r"^\S+\. "), F.regexp_replace(replacement, r"^(\S+) ", "$1. ")).otherwise(replacement)
    return F.when(kind.isin("phone", "identity", "card"), digits).when(kind == "name", title).otherwise(replacement)


def distinct_surrogates(forms: DataFrame, key: str, scratch: Scratch) -> DataFrame:
    """(kind, form, replacement) for distinct (kind, form): no two forms of a type share a replacement, none is a real form."""
    todo = forms.withColumn("salt", F.lit(0))
    settled: DataFrame | None = None
    for _ in range(ROUNDS):
        drawn = scratch.put(todo.withColumn("replacement", surrogate(F.col("kind"), F.col("form"), F.col("salt"), key)), "drawn")
        taken = forms.select("kind", F.col("form").alias("replacement"))
        if settled is not None:
            taken = taken.unionByName(settled.select("kind", "replacement"))
        first = drawn.groupBy("kind", "replacement").agg(F.min("form").alias("form")).join(taken, ["kind", "replacement"], "left_anti")
        good = scratch.put(drawn.join(first, ["kind", "replacement", "form"], "left_semi"), "good")
        settled = good if settled is None else settled.unionByName(good)
        left = drawn.join(good, ["kind", "form"], "left_anti").select("kind", "form", (F.col("salt") + 1).alias("salt"))
        todo = scratch.put(left, "left")
        if not todo.head(1):
            return settled.select("kind", "form", "replacement")
    raise RuntimeError(f"surrogates still collide after {ROUNDS} draws")


def _cut(text: Column) -> Column:
    """A text as array: what stands between entities at even places, entities at odd ones.

    The pattern runs once and puts marks around entities, at which the text is cut. A text that
    holds such marks itself (noncharacters, which interchanged texts don't use) is matched twice instead.
    """
    marked = F.split(F.regexp_replace(text, f"(?:{ANY})", f"{_OPEN}$0{_CLOSE}"), f"[{_OPEN}{_CLOSE}]")
    found = F.regexp_extract_all(text, F.lit(f"({ANY})"), F.lit(1))
    twice = F.flatten(F.transform(F.arrays_zip(F.split(text, ANY).alias("a"), found.alias("b")), lambda x: F.when(x["b"].isNull(), F.array(x["a"])).otherwise(F.array(x["a"], x["b"]))))
    return F.when(text.contains(_OPEN) | text.contains(_CLOSE), twice).otherwise(marked)


# Two of Unicode's noncharacters.
_OPEN, _CLOSE = "\ufdd0", "\ufdd1"


def with_surrogates(docs: DataFrame, key: str) -> DataFrame:
    """(doc_id, text, n_entities): every entity replaced."""
    scratch = Scratch(docs.sparkSession, "surrogates")
    d = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    cut = scratch.put(d.select("doc_id", F.xxhash64("text").alias("h"), _cut(F.col("text")).alias("cut")), "cut")
    some, none = cut.where("size(cut) > 1"), cut.where("cut is null or size(cut) <= 1")
    places = scratch.put(some.select("doc_id", "h", F.posexplode("cut").alias("pos", "surface")).where("pos % 2 = 1"), "places")
    surfaces = places.select("surface").distinct().withColumn("kind", kind_of(F.col("surface"))).withColumn("form", canonical(F.col("kind"), F.col("surface")))
    surfaces = scratch.put(surfaces, "surfaces")
    names, others = surfaces.where("kind = 'name'"), surfaces.where("kind <> 'name'")
    parts = names.select(F.explode(name_parts(F.col("form"))).alias("_part")).select("_part.*")
    forms = scratch.put(others.select("kind", "form").unionByName(parts).distinct(), "forms")
    chosen = distinct_surrogates(forms, key, scratch)
    whole = others.join(chosen, ["kind", "form"])
    # a name is put together from its parts, so a surname has one surrogate in all forms of a person
    named = lambda kind, as_: chosen.where(F.col("kind") == kind).select(F.col("form").alias(f"_{as_}"), F.col("replacement").alias(as_))
    part = name_parts(F.col("form"))
    n = names.withColumns({"_last": F.get(part, F.lit(0))["form"], "_first": F.get(part, F.lit(1))["form"]})
    n = n.join(named("surname", "last"), "_last").join(named("given", "first"), "_first", "left")
    n = n.withColumn("replacement", F.concat_ws(" ", F.substring_index("form", " ", 1), F.substring("first", 3, 1000), "last"))
    whole = whole.select("surface", "kind", "replacement").unionByName(n.select("surface", "kind", "replacement"))
    spelled = whole.select("surface", rendered(F.col("kind"), F.col("surface"), F.col("replacement")).alias("new"))
    spelled = scratch.put(spelled, "spelled")
    # equal rows of one document have one list
    by_doc = places.distinct().join(spelled, "surface").groupBy("doc_id", "h").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "new"))), lambda x: x["new"]).alias("new"))
    by_doc = scratch.put(by_doc, "by_doc").withColumnsRenamed({"doc_id": "_id", "h": "_h"})
    joined = some.join(by_doc, some["doc_id"].eqNullSafe(by_doc["_id"]) & (some["h"] == by_doc["_h"]))
    text = F.array_join(F.transform("cut", lambda t, i: F.when(i % 2 == 1, F.get("new", F.floor(i / 2).cast("int"))).otherwise(t)), "")
    changed = joined.select("doc_id", text.alias("text"), F.size("new").cast("long").alias("n_entities"))
    return changed.unionByName(none.select("doc_id", F.get("cut", F.lit(0)).alias("text"), F.lit(0).cast("long").alias("n_entities")))


def op7_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_surrogates(table(spark, sf_dir, "documents"), key="a key that production reads from its secret store")
