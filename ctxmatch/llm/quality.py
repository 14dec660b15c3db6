r"""Quality rules by distribution divergence, in DataFrame functions only.

A document's histogram over character classes and its histogram over common words (the twenty commonest of each language, without the points around them; the
rest in one bin) are compared with the references of four languages by the Jensen-Shannon distance (base 2, so 0 to 1). The references are the
corpus' own sums over all documents of a language that pass the base rules. A document is rejected if its nearest
character reference is further than ``most_chars`` or its nearest word reference further than ``most_words``; each test has a
minimum length below which it abstains, since short histograms are noise: prose of some 100 words lies at 0.22 (median) to 0.28 (99 %) from its language, of
400 words at 0.08 to 0.13, and a text without any common word at 0.38, whatever its length.

Base rules: fewer than 20 words, or over 30 % of the words in 8-word windows found twice or more.

Defined cases: null or empty text has no words and fails the base rules; without any reference (an empty table, unknown languages only) only the base
rules count, and a document without a ``lang`` (or a table without that column) is judged like any other but adds to no reference; rows that repeat an id and rows
with a null id are judged like any others; words are runs of other characters than space and tab to carriage return; very long texts are taken whole (repeated
windows are found by sorting 64-bit hashes of theirs, never by comparing all pairs: two different windows of a million-word text agree by chance with a probability of 3e-8);
other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of, written

#: Very common words of each language; fixed values.
COMMON = {
    "en": "the of and to a in is that it for was on with as be by are this at from".split(),
    "fr": "de la le et les en des un du une que est pour par dans avec qui pas sur au".split(),
    "de": "der die und in den von zu das sich mit des auf für ist im nicht dem ein eine als".split(),
    "es": "de la que el en y los las se del un por con no una su para es al lo".split(),
}
_WORDS = list(dict.fromkeys(w for words in COMMON.values() for w in words))
_LETTERS = [chr(0x2F + i) for i in range(len(_WORDS))]  # one byte each
_FORMS = sorted({f for w in _WORDS for f in (w, w.capitalize(), w.upper())})
#: What is cut from both ends of a word before it is looked up.
POINTS = ".,;:!?'\"()-"
SYMBOLS = "[#*$%&|<>]"
WINDOW = 8


def words_of(text: Column) -> Column:
    inner = F.btrim(text, F.lit(" \t\n\x0b\x0c\r"))
    return F.when(inner == "", F.array().cast("array<string>")).otherwise(F.split(inner, r"[\x20\x09-\x0D]+"))


def _bind(value: Column, body) -> Column:
    """``body`` of ``value``, which is computed once."""
    return F.transform(F.array(value), body)[0]


def window_hashes(hashes: Column) -> Column:
    """One for each window of words, from the hashes of ``WINDOW`` words or more."""
    return F.transform(F.sequence(F.lit(1), F.size(hashes) - WINDOW + 1), lambda i: F.xxhash64(F.slice(hashes, i, WINDOW)))


def repeated_words(hashes: Column) -> Column:
    """How many words lie in windows whose hash is found twice or more; ``hashes``: one per window, in order."""

    def covered(at: Column) -> Column:
        return F.aggregate(
            F.sequence(F.lit(0), F.size(at) - 1), F.lit(0).cast("long"), lambda acc, k: acc + F.when(k == F.size(at) - 1, WINDOW).otherwise(F.least(F.lit(WINDOW), F.get(at, k + 1) - F.get(at, k))).cast("long")
        )

    def twice(rows: Column) -> Column:
        same = lambda k, d: F.coalesce(F.get(rows, k).getField("h") == F.get(rows, k + d).getField("h"), F.lit(False))
        at = F.transform(F.sequence(F.lit(0), F.size(rows) - 1), lambda k: F.when(same(k, 1) | ((k > 0) & same(k, -1)), F.get(rows, k).getField("i")))
        return _bind(F.sort_array(F.filter(at, lambda i: i.isNotNull())), covered)

    rows = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0).cast("long")).otherwise(_bind(rows, twice))


def measures(docs: DataFrame) -> DataFrame:
    """Counts of each document: the base columns, six character classes and the common words."""
    text = text_of()
    df = docs.select("doc_id", F.col("lang").cast("string").alias("lang") if "lang" in docs.columns else F.lit(None).cast("string").alias("lang"), text.alias("text"))
    df = df.withColumn("words", words_of(F.col("text")))
    n = F.size("words")
    df = df.select(
        "doc_id", "lang", "text", "words",
        F.when(n >= WINDOW, _bind(F.transform("words", lambda w: F.xxhash64(w)), window_hashes)).otherwise(F.array().cast("array<bigint>")).alias("hashes"),
        F.filter(F.split("text", "\n"), lambda s: F.length(F.btrim(s, F.lit(" \t\n\x0b\x0c\r"))) > 0).alias("lines"),
        F.array_join(F.transform(F.filter(F.transform("words", lambda w: F.btrim(w, F.lit(POINTS))), lambda w: w.isin(_FORMS)), lambda w: F.substring(F.lit("".join(_LETTERS)), F.array_position(F.array(*map(F.lit, _WORDS)), F.lower(w)).cast("int"), F.lit(1))), "").alias("common"),
    )
    left_out = lambda keep: F.length(F.regexp_replace("text", f"[^{keep}]+", "")).cast("long")
    n_words = F.size("words").cast("long")
    df = df.select(
        "doc_id", "lang", n_words.alias("n_words"), F.length("text").cast("long").alias("n_chars"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"), left_out(SYMBOLS[1:-1]).alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"), repeated_words(F.col("hashes")).alias("n_repeat_words"),
        left_out(r"\\p{Lu}".replace("\\\\", "\\")).alias("upper"), left_out("0-9").alias("digits"), left_out(r".,;:!?'\"()\\-").alias("points"), "common",
    )
    df = df.withColumn("spaces", F.col("n_chars") - F.col("word_chars"))
    rest = F.greatest(F.lit(0).cast("long"), F.col("word_chars") - F.col("upper") - F.col("digits") - F.col("points") - F.col("n_symbols"))
    counts = [F.octet_length("common") - F.octet_length(F.replace("common", F.lit(c), F.lit(""))) for c in _LETTERS]
    return df.select(
        "doc_id", "lang", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        F.array("upper", "digits", "points", "n_symbols", "spaces", rest).cast("array<bigint>").alias("chars"),
        F.array(*counts, F.col("n_words") - F.octet_length("common")).cast("array<bigint>").alias("common"),
    )


def shares(counts: Column) -> Column:
    """The bins in use, as (i, p); null if there are none."""
    total = F.aggregate(counts, F.lit(0.0), lambda a, c: a + c)
    used = lambda total: F.filter(F.transform(counts, lambda c, i: F.struct(i.alias("i"), (c / total).alias("p"))), lambda x: x["p"] > 0)
    return _bind(total, lambda total: F.when(total > 0, used(total)))


def distance_of(used: Column, reference: list[float]) -> Column:
    """Jensen-Shannon distance between :func:`shares` and a reference that sums to 1; null for null. A bin that is not in use adds its whole share of the reference."""
    q_at = F.array(*map(F.lit, reference))

    def term(p: Column, q: Column) -> Column:
        return p * F.log2(2 * p / (p + q)) + F.when(q > 0, q * F.log2(2 * q / (p + q)) - q).otherwise(0.0)

    twice = F.aggregate(used, F.lit(1.0), lambda a, x: a + term(x["p"], F.get(q_at, x["i"])))
    return F.when(used.isNotNull(), F.sqrt(F.greatest(F.lit(0.0), twice / 2)))


def distance(counts: Column, reference: list[float]) -> Column:
    """The same for a histogram of counts; null for an empty one."""
    return _bind(shares(counts), lambda used: distance_of(used, reference))


def references(rows: DataFrame) -> dict[str, tuple[list[float], list[float]]]:
    """language -> (character shares, common-word shares), summed over all documents of the listed languages that pass the base rules."""
    n_chars, n_words = 6, len(_WORDS) + 1
    sums = [F.sum(F.get("chars", F.lit(i))).alias(f"c{i}") for i in range(n_chars)] + [F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(n_words)]
    found = rows.filter(~F.col("base_failed") & F.col("lang").isin(list(COMMON))).groupBy("lang").agg(*sums).collect()  # a row for each listed language
    share = lambda xs: [x / sum(xs) for x in xs]
    return {r["lang"]: (share([r[f"c{i}"] for i in range(n_chars)]), share([r[f"w{i}"] for i in range(n_words)])) for r in sorted(found, key=lambda r: r["lang"])}


def judge(docs: DataFrame, *, most_chars: float = 0.3, most_words: float = 0.3, least_chars: int = 200, least_words: int = 80, refs: dict | None = None) -> DataFrame:
    """One row per document: doc_id, n_words, the base counts, base_failed, kept, char_distance and word_distance (null where a guard abstains)."""
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    rows = measures(docs).withColumn("base_failed", failed)
    if refs is None:
        rows = written(rows, "quality")
        refs = references(rows)
    nearest = lambda name, k: _bind(shares(F.col(name)), lambda used: F.least(*[distance_of(used, r[k]) for r in refs.values()], F.lit(None).cast("double"))) if refs else F.lit(None).cast("double")
    rows = rows.withColumn("char_distance", F.when(F.col("word_chars") >= least_chars, nearest("chars", 0))).withColumn("word_distance", F.when(F.col("n_words") >= least_words, nearest("common", 1)))
    kept = ~F.col("base_failed") & (F.coalesce("char_distance", F.lit(0.0)) <= most_chars) & (F.coalesce("word_distance", F.lit(0.0)) <= most_words)
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), F.round("char_distance", 6).alias("char_distance"), F.round("word_distance", 6).alias("word_distance"))


def oracle() -> str:
    """The same verdicts in DuckDB's SQL, with the default limits."""
    words = ", ".join(f"'{w}'" for w in _WORDS)
    forms = ", ".join(f"'{w}'" for w in _FORMS)
    points = POINTS.replace("'", "''")
    kept_of = lambda keep: f"length(regexp_replace(t, '[^{keep}]+', '', 'g'))"
    js = lambda c: f"sqrt(greatest(0.0::DOUBLE, sum(CASE WHEN p > 0 THEN p * log2(2 * p / (p + q)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(2 * q / (p + q)) ELSE 0 END) / 2)) AS {c}"
    side = lambda c: (
        f"{c}_doc AS (SELECT doc_id, generate_subscripts({c}, 1) AS i, unnest({c}) / nullif(list_sum({c}), 0)::DOUBLE AS p FROM h),"
        f" {c}_sum AS (SELECT lang, i, sum(n)::DOUBLE AS n FROM (SELECT lang, generate_subscripts({c}, 1) AS i, unnest({c}) AS n FROM h WHERE NOT base_failed AND lang IN ('en', 'fr', 'de', 'es')) GROUP BY ALL),"
        f" {c}_ref AS (SELECT lang, i, n / sum(n) OVER (PARTITION BY lang) AS q FROM {c}_sum),"
        f" {c}_near AS (SELECT doc_id, min(d) AS d FROM (SELECT doc_id, lang, {js('d')} FROM {c}_doc JOIN {c}_ref USING (i) WHERE p IS NOT NULL GROUP BY ALL) GROUP BY doc_id)"
    )
    return (
        "WITH d AS (SELECT doc_id, lang, coalesce(text, '') AS t FROM documents),"
        " w AS (SELECT *, list_filter(regexp_split_to_array(t, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM d),"
        " win AS (SELECT doc_id, i, array_to_string(ws[i:i + 7], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w WHERE len(ws) >= 8)),"
        " twice AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS n FROM win) WHERE n > 1),"
        " rep AS (SELECT doc_id, count(DISTINCT i + k.k) AS r FROM twice, range(0, 8) AS k(k) GROUP BY doc_id),"
        " lines AS (SELECT doc_id, count(*) - count(DISTINCT l) AS dup FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS l FROM d) WHERE length(regexp_replace(l, '[\\x20\\x09-\\x0D]+', '', 'g')) > 0 GROUP BY doc_id),"
        f" m AS (SELECT w.doc_id, lang, len(ws)::BIGINT AS n_words, length(t) AS nc, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars, {kept_of(SYMBOLS[1:-1])}::BIGINT AS n_symbols, coalesce(dup, 0)::BIGINT AS n_dup_lines, coalesce(r, 0)::BIGINT AS n_repeat_words,"
        f" {kept_of('\\p{Lu}')} AS upper, {kept_of('0-9')} AS digits, length(t) - length(translate(t, '.,;:!?''\"()-', '')) AS points, list_transform(list_filter(list_transform(ws, lambda x: trim(x, '{points}')), lambda x: list_contains([{forms}], x)), lambda x: lower(x)) AS common"
        " FROM w LEFT JOIN rep USING (doc_id) LEFT JOIN lines USING (doc_id)),"
        f" h AS (SELECT doc_id, lang, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed, [upper, digits, points, n_symbols, nc - word_chars, greatest(0, word_chars - upper - digits - points - n_symbols)] AS chars, list_append(list_transform([{words}], lambda x: len(list_filter(common, lambda y: y = x))), n_words - len(common)) AS common FROM m),"
        f" {side('chars')}, {side('common')}"
        " SELECT h.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND coalesce(CASE WHEN word_chars >= 200 THEN a.d END, 0) <= 0.3 AND coalesce(CASE WHEN n_words >= 80 THEN b.d END, 0) <= 0.3 AS kept,"
        " round(CASE WHEN word_chars >= 200 THEN a.d END, 6) AS char_distance, round(CASE WHEN n_words >= 80 THEN b.d END, 6) AS word_distance"
        " FROM h LEFT JOIN chars_near a USING (doc_id) LEFT JOIN common_near b USING (doc_id)"
    )


def js_distance(p: list[float], q: list[float]) -> float:
    """The same distance of two share lists, on the driver."""
    half = lambda a, b: sum(x * math.log2(2 * x / (x + y)) for x, y in zip(a, b, strict=True) if x)
    return math.sqrt(max(0.0, (half(p, q) + half(q, p)) / 2))
