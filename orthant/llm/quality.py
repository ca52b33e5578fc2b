"""Quality rules by distribution divergence, in DataFrame functions only.

A document's histograms, of character classes and of common words, are compared with references of the languages by the
Jensen-Shannon distance (the square root of the divergence to base 2, from 0 to 1). A reference is the total of all
documents of a language that pass the base rules. A document is refused when even the nearest reference is farther than
the threshold and the document is long enough for its histogram to mean something; base rules refuse by themselves.

Defined results: null text has no words, so it fails the base rules; without any reference (no row with a language that
passes) only the base rules count; a table must have the column of languages (``lang_col``), null where unknown; repeated rows
each get a row; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import let, whole_text, written

MIN_WORDS, REPEAT_PERCENT = 50, 50
#: Verdict: least characters and words for a comparison, greatest distances to the nearest language. A text without a common
#: word is only about 0.34 from references with a fifth of them.
GUARD_CHARS, GUARD_WORDS, CHAR_DISTANCE, WORD_DISTANCE = 400, 80, 0.31, 0.30
#: Languages whose references are broadcast together; more of them come in several blocks.
BLOCK = 2048
#: Windows found twice are looked up one by one up to so many; beyond, windows are sorted.
FEW = 24

#: Character classes, in this order; what is left is the class of all other letters and signs.
CLASSES = (r"[a-z]", r"[A-Z]", r"[0-9]", r"[\x20\x09-\x0D]", r"[.,;:!?'\"()\-]", r"[#*$%&|<>]", r"[^\x00-\x7F]")
#: Fixed list: common words of English, French, German and Spanish.
COMMON = (
    "the", "of", "and", "to", "in", "is", "that", "for", "it", "with", "was", "on",
    "le", "la", "les", "et", "des", "une", "un", "que", "dans", "est", "pour", "qui",
    "der", "die", "das", "und", "den", "von", "mit", "ist", "nicht", "ein", "eine", "zu",
    "el", "los", "las", "de", "y", "en", "por", "para", "con", "del", "se", "su",
)  # fmt: skip


def words_of(text: Column) -> Column:
    """Words of a text: its trimmed form split at runs of the six spaces."""
    trimmed = F.btrim(text, F.lit(" \t\n\x0b\x0c\r"))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, r"[\x20\x09-\x0D]+", -1))


def _covered(starts: Column) -> Column:
    """Positions in the union of the 3-word windows at these ascending starts."""
    return let(starts, lambda p: F.aggregate(F.transform(p, lambda x, i: F.least(F.lit(3), F.coalesce(F.get(p, i + 1) - x, F.lit(3)))), F.lit(0), lambda a, x: a + x))


def repeated_words(words: Column) -> Column:
    """Words that lie in a 3-word window which the text has twice or more, the first one included."""
    hashed = F.transform(words, lambda w: F.xxhash64(w))

    def windows(h: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(h) - 3), lambda i: F.xxhash64(F.get(h, i), F.get(h, i + 1), F.get(h, i + 2)))

    def twice(v: Column) -> Column:
        return let(F.sort_array(v), lambda s: F.array_distinct(F.filter(s, lambda x, i: (i > 0) & (x == F.get(s, i - 1)))))

    def by_look_up(v: Column, d: Column) -> Column:
        return F.filter(F.transform(v, lambda x, i: F.when(F.array_contains(d, x), i).otherwise(-1)), lambda i: i >= 0)

    def by_sorting(v: Column) -> Column:
        pairs = F.sort_array(F.transform(v, lambda x, i: F.struct(x.alias("x"), i.alias("i"))))
        same = lambda s, k, e: F.coalesce(F.get(s, k)["x"] == e["x"], F.lit(False))  # noqa: E731
        found = let(pairs, lambda s: F.transform(F.filter(F.transform(s, lambda e, k: F.when(same(s, k - 1, e) | same(s, k + 1, e), e["i"]).otherwise(-1)), lambda i: i >= 0), lambda i: i))
        return F.sort_array(found)

    def count(v: Column) -> Column:
        return let(twice(v), lambda d: F.when(F.size(d) == 0, 0).when(F.size(d) <= FEW, _covered(by_look_up(v, d))).otherwise(_covered(by_sorting(v))))

    return let(hashed, lambda h: F.when(F.size(h) < 4, F.lit(0)).otherwise(let(windows(h), count)))


def common_counts(words: Column) -> Column:
    """How often each common word occurs, lower-cased and without punctuation at its end; the last number is all other words."""
    listed = F.array(*map(F.lit, COMMON))
    found = F.filter(F.transform(words, lambda w: F.rtrim(F.lower(w), F.lit(".,;:!?"))), lambda w: w.isin(*COMMON))
    per = let(found, lambda c: F.transform(listed, lambda w: F.size(c) - F.size(F.array_remove(c, w))))
    return let(per, lambda p: F.concat(p, F.array(F.size(words) - F.aggregate(p, F.lit(0), lambda a, x: a + x))))


def class_counts(text: Column) -> Column:
    per = F.array(*(F.regexp_count(text, F.lit(c)) for c in CLASSES))
    return let(per, lambda p: F.concat(p, F.array(F.length(text) - F.aggregate(p, F.lit(0), lambda a, x: a + x))))


def duplicate_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.rlike(x, F.lit(r"[^\x20\x09-\x0D]")))
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x)))


def shares(counts: Column) -> Column:
    """Counts over their total; of a total of 0, zeros."""
    return let(F.aggregate(counts, F.lit(0.0), lambda a, x: a + x), lambda n: F.transform(counts, lambda x: F.when(n > 0, x / n).otherwise(0.0)))


def js_distance(p: Column, q: Column) -> Column:
    def part(x: Column, m: Column) -> Column:
        return F.when(x > 0, x * F.log2(x / m)).otherwise(0.0)

    both = F.zip_with(p, q, lambda x, y: (part(x, (x + y) / 2) + part(y, (x + y) / 2)) / 2)
    return F.sqrt(F.greatest(F.lit(0.0), F.aggregate(both, F.lit(0.0), lambda a, x: a + x)))


def features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Base figures and histograms of each document."""
    text = F.col("_text")
    read = docs.select(F.col(id_col).alias("doc_id"), F.col(lang_col).alias("_lang"), whole_text(text_col).alias("_text"))
    figures = read.select(
        "doc_id",
        "_lang",
        F.length("_text").cast("long").alias("_chars"),
        F.regexp_count(text, F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.length("_text") - F.regexp_count(text, F.lit(r"[\x20\x09-\x0D]"))).cast("long").alias("word_chars"),
        duplicate_lines(text).cast("long").alias("n_dup_lines"),
        class_counts(text).alias("_classes"),
        let(words_of(text), lambda w: F.struct(F.size(w).cast("long").alias("n"), repeated_words(w).cast("long").alias("r"), common_counts(w).alias("c"))).alias("_w"),
    )
    figures = figures.select("*", F.col("_w.n").alias("n_words"), F.col("_w.r").alias("n_repeat_words"), F.col("_w.c").alias("_common")).drop("_w")
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))
    return figures.withColumn("base_failed", failed)


def references(figures: DataFrame) -> DataFrame:
    """One row per language: class shares and common-word shares of all its documents that pass the base rules; language_no from 0."""
    totals = [F.sum(F.col("_classes")[i]).alias(f"k{i}") for i in range(len(CLASSES) + 1)] + [F.sum(F.col("_common")[i]).alias(f"c{i}") for i in range(len(COMMON) + 1)]
    per = figures.where("_lang is not null and not base_failed").groupBy("_lang").agg(*totals)
    array = lambda k, n: shares(F.array(*(F.col(f"{k}{i}") for i in range(n))))  # noqa: E731
    number = (F.row_number().over(Window.orderBy("_lang")) - 1).alias("language_no")
    return per.select(number, array("k", len(CLASSES) + 1).alias("k"), array("c", len(COMMON) + 1).alias("c"))


def judge(docs: DataFrame, **columns: str) -> DataFrame:
    """One row per document: base figures, base_failed, the distances to the nearest language, kept."""
    figures = written(features(docs, **columns), "figures")
    refs = written(references(figures), "references")
    nearest = lambda counts, refs: let(shares(counts), lambda p: F.array_min(F.transform(refs, lambda q: js_distance(p, q))))  # noqa: E731
    told = figures.withColumns({"char_distance": F.lit(None).cast("double"), "word_distance": F.lit(None).cast("double")})
    for b in range(-(-refs.count() // BLOCK)):
        block = refs.where(F.floor(F.col("language_no") / BLOCK) == b).agg(F.collect_list("k").alias("_kinds"), F.collect_list("c").alias("_words"))
        told = told.join(F.broadcast(block), how="cross")  # one row
        told = told.withColumns({"char_distance": F.least("char_distance", nearest(F.col("_classes"), F.col("_kinds"))), "word_distance": F.least("word_distance", nearest(F.col("_common"), F.col("_words")))}).drop("_kinds", "_words")
        if b % 8 == 7:
            told = written(told, f"distances{b}")
    odd = ((F.col("_chars") >= GUARD_CHARS) & (F.col("char_distance") > CHAR_DISTANCE)) | ((F.col("n_words") >= GUARD_WORDS) & (F.col("word_distance") > WORD_DISTANCE))
    verdict = ~F.col("base_failed") & ~F.coalesce(odd, F.lit(False))
    return told.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", verdict.alias("kept"), "char_distance", "word_distance")


def told(docs: DataFrame) -> DataFrame:
    """judge with the distances to six places, as SQL gives them too."""
    return judge(docs).withColumns({c: F.round(c, 6) for c in ("char_distance", "word_distance")})


def _listed(words: tuple[str, ...]) -> str:
    return "[" + ", ".join(f"'{w}'" for w in words) + "]"


_COUNTS = ", ".join("length(t) - length(regexp_replace(t, '{}', '', 'g'))".format(c.replace("'", "''")) for c in CLASSES)
_SHARES = "list_transform({0}, lambda x: CASE WHEN list_sum({0}) > 0 THEN x / list_sum({0}) ELSE 0.0::DOUBLE END)"
_DISTANCE = (
    "sqrt(greatest(0.0::DOUBLE, list_sum(list_transform(list_zip({0}, {1}), lambda z: ((CASE WHEN z[1] > 0 THEN z[1] * log2(2 * z[1] / (z[1] + z[2])) ELSE 0 END)"
    " + (CASE WHEN z[2] > 0 THEN z[2] * log2(2 * z[2] / (z[1] + z[2])) ELSE 0 END)) / 2))))"
)
OP5_SQL = rf"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
w AS MATERIALIZED (SELECT r, unnest(l) AS w, generate_subscripts(l, 1) AS i FROM (SELECT r, regexp_extract_all(t, '[^ 	-]+') AS l FROM d)),
v AS (SELECT r, i, w, lead(w) OVER p AS w1, lead(w, 2) OVER p AS w2 FROM w WINDOW p AS (PARTITION BY r ORDER BY i)),
twice AS (SELECT r, i FROM v WHERE w2 IS NOT NULL QUALIFY count(*) OVER (PARTITION BY r, w, w1, w2) > 1),
n_rep AS (SELECT r, count(DISTINCT i + k) AS n_repeat_words FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY r),
lines AS (SELECT r, count(*) - count(DISTINCT x) AS n_dup_lines FROM (SELECT r, unnest(string_split(t, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^ 	-]') GROUP BY r),
per AS (SELECT r, count(*) AS n_words, sum(length(w)) AS word_chars FROM w GROUP BY r),
c AS (SELECT r, rtrim(lower(w), '.,;:!?') AS w, count(*) AS n FROM w GROUP BY ALL HAVING list_contains({_listed(COMMON)}, rtrim(lower(w), '.,;:!?'))),
cm AS (SELECT r, map(list(w), list(n)) AS m, sum(n) AS n FROM (SELECT r, w, sum(n) AS n FROM c GROUP BY ALL) GROUP BY r),
k AS (SELECT r, [{_COUNTS}] AS k, length(t) AS chars FROM d),
f AS MATERIALIZED (
  SELECT d.r, doc_id, lang, k.chars, coalesce(per.n_words, 0) AS n_words, CAST(coalesce(word_chars, 0) AS BIGINT) AS word_chars, k.k[6] AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines,
         coalesce(n_repeat_words, 0) AS n_repeat_words, list_append(k.k, k.chars - list_sum(k.k)) AS kinds,
         list_append(list_transform({_listed(COMMON)}, lambda x: coalesce(cm.m[x], 0)), coalesce(per.n_words, 0) - coalesce(cm.n, 0)) AS words
  FROM d JOIN k USING (r) LEFT JOIN per USING (r) LEFT JOIN lines USING (r) LEFT JOIN n_rep USING (r) LEFT JOIN cm USING (r)),
b AS MATERIALIZED (SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > {REPEAT_PERCENT} * n_words AS base_failed FROM f),
q AS MATERIALIZED (SELECT lang, {", ".join(f"sum(kinds[{i + 1}])" for i in range(len(CLASSES) + 1)).join(("[", "]"))} AS kinds, {", ".join(f"sum(words[{i + 1}])" for i in range(len(COMMON) + 1)).join(("[", "]"))} AS words FROM b WHERE lang IS NOT NULL AND NOT base_failed GROUP BY lang),
p AS MATERIALIZED (SELECT r, {_SHARES.format("kinds")} AS kinds, {_SHARES.format("words")} AS words FROM b),
s AS MATERIALIZED (SELECT {_SHARES.format("kinds")} AS kinds, {_SHARES.format("words")} AS words FROM q),
near AS (SELECT r, min({_DISTANCE.format("p.kinds", "s.kinds")}) AS cd, min({_DISTANCE.format("p.words", "s.words")}) AS wd FROM p, s GROUP BY r)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT coalesce((chars >= {GUARD_CHARS} AND cd > {CHAR_DISTANCE}) OR (n_words >= {GUARD_WORDS} AND wd > {WORD_DISTANCE}), false) AS kept,
       round(cd, 6) AS char_distance, round(wd, 6) AS word_distance
FROM b LEFT JOIN near USING (r)
"""
