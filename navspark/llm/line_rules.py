"""Line-first quality rules.

Each line with a word is judged by itself: navigation, symbols, boilerplate, shouting, and
short lines without closing punctuation fail. Failing lines are removed, and a document that
loses more than ``MAX_LOST`` of its word characters is rejected. Document statistics (words,
symbols, repeated lines, words in repeated eight-word windows) are computed beside.

Only built-in functions run; a document never leaves its row, so no group can be hot.

Defined results: null text has no words and fails the base rule; repeated rows are judged
each; null ids are carried; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from navspark.llm.common import once
from navspark.llm.decontam import covered_words, with_window_hashes

MIN_WORDS = 20
MAX_REPEAT = 30  #: percent of words in repeated windows
WINDOW = 8
MAX_LOST = 0.5  #: share of word characters in removed lines
MAX_SYMBOLS = 10  #: percent of a line's word characters
SHORT = 3  #: words of a line that needs closing punctuation

_SPACE = r"[\x20\x09-\x0D]+"
_SYMBOL = r"[^#*$%&|<>]+"
#: Fixed phrases of page furniture, in several languages.
BOILERPLATE = r"(?i)(cookie|copyright|all rights reserved|terms of (use|service)|privacy policy|javascript|lorem ipsum|subscribe to|sign up|log in|alle rechte vorbehalten|tous droits réservés|todos los derechos)"
_CLOSED = r"[.!?:;…»”\"')\]]$"


def _left(c: Column, pattern: str) -> Column:
    return F.char_length(F.regexp_replace(c, pattern, ""))


def line_fails(line: Column) -> Column:
    """Whether a line (with a word) is to be removed."""
    bare = F.btrim(line, F.lit(" \t\n\x0b\x0c\r"))
    chars = _left(line, _SPACE)
    many_symbols = _left(line, _SYMBOL) * 100 > chars * MAX_SYMBOLS
    navigation = F.regexp_count(line, F.lit(r"[|>»·•]")) >= 3
    shouting = ~line.rlike("[a-z]") & (_left(line, "[^A-Z]+") >= 10)
    open_short = ~bare.rlike(_CLOSED) & (F.regexp_count(bare, F.lit(r"[^\x20\x09-\x0D]+")) < SHORT)
    return many_symbols | navigation | shouting | open_short | line.rlike(BOILERPLATE)


def judged(docs: DataFrame, keep_text: bool = False) -> DataFrame:
    """Statistics and verdict of each row; ``keep_text`` adds the cleaned text."""
    base = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    base = base.select("doc_id", "text", once(F.array_remove(F.split("text", _SPACE, -1), "")).alias("w"), once(F.filter(F.split("text", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))).alias("lines"))
    df = with_window_hashes(base, [WINDOW], "w", lambda w: w)
    h = f"h{WINDOW}"
    again = F.size(F.array_distinct(h)) < F.size(h)
    df = df.withColumn("s", once(F.when(again, F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i")))))))
    # Equal windows are neighbours in hash order; places of both come out sorted and distinct.
    m = F.size("s") - 1
    near = F.zip_with(F.slice("s", 1, m), F.slice("s", 2, m), lambda a, b: F.when(a.h == b.h, F.array(a.i, b.i)).otherwise(F.array().cast("array<int>")))
    places = F.array_sort(F.array_distinct(F.flatten(near)))
    repeat = F.when(F.col("s").isNull(), F.lit(0)).otherwise(covered_words(places, lambda x: x, lambda x: F.lit(WINDOW)))
    bad = F.filter("lines", line_fails)
    df = df.withColumn("bad_chars", F.char_length(F.regexp_replace(F.array_join(bad, "\n"), _SPACE, "")))
    out = df.select(
        "doc_id",
        "text",
        "lines",
        F.col("n").cast("long").alias("n_words"),
        _left(F.col("text"), _SPACE).cast("long").alias("word_chars"),
        _left(F.col("text"), _SYMBOL).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeat.cast("long").alias("n_repeat_words"),
        F.col("bad_chars").cast("long").alias("bad_chars"),
    )
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT * F.col("n_words"))
    out = out.withColumn("base_failed", failed).withColumn("kept", ~failed & (F.col("bad_chars") <= MAX_LOST * F.col("word_chars")))
    if keep_text:
        out = out.withColumn("text", F.array_join(F.filter("lines", lambda x: ~line_fails(x)), "\n"))
    return out.drop("lines") if keep_text else out.drop("lines", "text")


def cleaned(docs: DataFrame) -> DataFrame:
    """doc_id and text without failing lines, of the documents that stay."""
    return judged(docs, keep_text=True).where("kept").select("doc_id", "text")


def op6_result(docs: DataFrame) -> DataFrame:
    return judged(docs)


OP6_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM d),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM w WHERE len(w) >= 8)),
rep AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1) GROUP BY doc_id),
ln AS (SELECT doc_id, unnest(lines) AS l FROM w),
bad AS (SELECT doc_id, sum(length(regexp_replace(l, '[\x20\x09-\x0D]+', '', 'g'))) AS c FROM ln WHERE
    length(regexp_replace(l, '[^#*$%&|<>]+', '', 'g')) * 100 > length(regexp_replace(l, '[\x20\x09-\x0D]+', '', 'g')) * 10
    OR length(regexp_replace(l, '[^|>»·•]+', '', 'g')) >= 3
    OR (NOT regexp_matches(l, '[a-z]') AND length(regexp_replace(l, '[^A-Z]+', '', 'g')) >= 10)
    OR (NOT regexp_matches(trim(l, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), '[.!?:;…»”"'')\]]$') AND len(list_filter(regexp_split_to_array(l, '[\x20\x09-\x0D]+'), lambda x: x <> '')) < 3)
    OR regexp_matches(l, '(?i)(cookie|copyright|all rights reserved|terms of (use|service)|privacy policy|javascript|lorem ipsum|subscribe to|sign up|log in|alle rechte vorbehalten|tous droits réservés|todos los derechos)')
  GROUP BY doc_id),
s AS (SELECT w.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
  CAST(length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
  CAST(coalesce(rep.n, 0) AS BIGINT) AS n_repeat_words, CAST(coalesce(bad.c, 0) AS BIGINT) AS bad_chars
  FROM w LEFT JOIN rep ON w.doc_id = rep.doc_id LEFT JOIN bad ON w.doc_id = bad.doc_id)
SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed,
  NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AND bad_chars <= 0.5 * word_chars AS kept FROM s
"""
