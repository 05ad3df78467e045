"""Quality rules: a threshold table compiled into one Spark projection.

The measures are integer counts of a document (words, characters, symbols,
repeated lines and windows, stop words, line shapes).  A :class:`Rule` compares
``scale * measure`` with ``bound * base`` in whole numbers, so the verdict has
no rounding; :func:`compile_rules` turns a table of rules into boolean columns
of one projection.  Everything runs on whole texts inside one scan: no shuffle,
no user function.

Repeated three-word windows are found inside the row: window hashes (64 bit)
are sorted with their start, equal neighbours name the repeated starts, and the
union of the starts and the two places after each are the repeated words.

Defined results: null text counts as empty (no words, fails the base rule);
repeated rows are judged row by row; extra columns pass unread.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import WS, text_of

SYMBOLS = "#*$%&|<>"

# Frequent function words of English, French, Spanish and German.
STOP_WORDS = tuple(
    "the of and to in is that it was for on are as with be by this "
    "le la les de des et est un une que en du dans il "
    "el los las y un una por con para se "
    "der die das und ist ein eine von mit den nicht auf zu sich".split()
)


@dataclass(frozen=True)
class Rule:
    """``scale * measure (<= or >=) bound * base``; base ``one`` makes the bound absolute."""

    name: str
    measure: str
    op: str
    bound: int
    base: str = "one"
    scale: int = 1


BASE_RULES = (
    Rule("enough_words", "n_words", ">=", 50),
    Rule("few_repeated_words", "n_repeat_words", "<=", 50, "n_words", 100),
)

RULES = (
    Rule("word_length_low", "word_chars", ">=", 2, "n_words"),
    Rule("word_length_high", "word_chars", "<=", 14, "n_words"),
    Rule("few_symbols", "n_symbols", "<=", 10, "n_words", 100),
    Rule("few_repeated_lines", "n_dup_lines", "<=", 30, "n_lines", 100),
    Rule("some_stop_words", "n_stop_words", ">=", 2, "n_words", 100),
    Rule("few_bullet_lines", "n_bullet_lines", "<=", 90, "n_lines", 100),
    Rule("few_ellipsis_lines", "n_ellipsis_lines", "<=", 30, "n_lines", 100),
)


def _without(c: Column, chars: str) -> Column:
    return F.translate(c, chars, "")


def measures(docs: DataFrame, stop_words: tuple[str, ...] = STOP_WORDS) -> DataFrame:
    """doc_id and the counts that rules can name."""
    text = docs.select(docs["doc_id"].alias("doc_id"), text_of(docs).alias("body"))
    parts = text.select(
        "doc_id",
        F.length("body").alias("n_chars_all"),
        F.length(_without(F.col("body"), WS)).alias("word_chars"),
        F.length(_without(F.col("body"), SYMBOLS)).alias("n_plain"),
        F.array_remove(F.split("body", "[\\x20\\x09-\\x0D]+", -1), "").alias("words"),
        F.filter(F.split("body", "\n", -1), lambda x: F.btrim(x, F.lit(WS)) != "").alias("lines"),
    )
    n = F.size("words")
    windows = F.when(
        n >= 3,
        F.transform(
            F.sequence(F.lit(0), n - 3),
            lambda i: F.struct(F.xxhash64(F.get("words", i), F.get("words", i + 1), F.get("words", i + 2)).alias("h"), i.alias("i")),
        ),
    )
    by_hash = parts.select("*", F.sort_array(windows).alias("w"))
    m = F.size("w")
    hash_at = lambda k: F.get("w", k)["h"]
    starts = F.filter(
        F.transform(F.sequence(F.lit(0), m - 1), lambda k: F.when((hash_at(k) == hash_at(k - 1)) | (hash_at(k) == hash_at(k + 1)), F.get("w", k)["i"])),
        lambda x: x.isNotNull(),
    )
    marked = by_hash.select("doc_id", "n_chars_all", "word_chars", "n_plain", "words", "lines", F.when(m > 1, starts).otherwise(F.array().cast("array<int>")).alias("starts"))
    shifted = lambda d: F.transform("starts", lambda i: i + d)
    bullet = lambda x: F.btrim(x, F.lit(WS)).rlike("^[-*•]")
    ellipsis = lambda x: F.rtrim(x).rlike("(\\.\\.\\.|…)$")
    lower_in = lambda x: F.lower(x).isin(*dict.fromkeys(stop_words))
    long = lambda c: c.cast("long")
    return marked.select(
        "doc_id",
        long(F.size("words")).alias("n_words"),
        long(F.col("word_chars")).alias("word_chars"),
        long(F.col("n_chars_all") - F.col("n_plain")).alias("n_symbols"),
        long(F.size("lines") - F.size(F.array_distinct("lines"))).alias("n_dup_lines"),
        long(F.size(F.array_union(F.array_union("starts", shifted(1)), shifted(2)))).alias("n_repeat_words"),
        long(F.size("lines")).alias("n_lines"),
        long(F.size(F.filter("words", lower_in))).alias("n_stop_words"),
        long(F.size(F.filter("lines", bullet))).alias("n_bullet_lines"),
        long(F.size(F.filter("lines", ellipsis))).alias("n_ellipsis_lines"),
    )


def holds(rule: Rule) -> Column:
    left = F.lit(rule.scale) * F.col(rule.measure)
    right = F.lit(rule.bound) * (F.lit(1) if rule.base == "one" else F.col(rule.base))
    return left <= right if rule.op == "<=" else left >= right


def compile_rules(rules: tuple[Rule, ...]) -> list[Column]:
    """One boolean column per rule."""
    return [holds(r).alias(f"ok_{r.name}") for r in rules]


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES, base: tuple[Rule, ...] = BASE_RULES) -> DataFrame:
    """The measures, a boolean per rule, ``base_failed`` and ``kept``."""
    table = measures(docs).select("*", *compile_rules(base), *compile_rules(rules))
    every = lambda rs: F.array_min(F.array(F.lit(True), *[F.col(f"ok_{r.name}") for r in rs]))
    return table.select("*", (~every(base)).alias("base_failed"), every(base + rules).alias("kept"))


def digest(docs: DataFrame) -> DataFrame:
    return judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _sql_rule(r: Rule) -> str:
    right = str(r.bound) if r.base == "one" else f"{r.bound} * {r.base}"
    return f"{r.scale} * {r.measure} {r.op} {right}"


ORACLE_SQL = (
    r"""
WITH w AS (
  SELECT doc_id, coalesce(text, '') AS body,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words
  FROM documents),
win AS (
  SELECT doc_id, unnest(range(len(words) - 2)) AS i, words FROM w WHERE len(words) >= 3),
keyed AS (SELECT doc_id, i, [words[i + 1], words[i + 2], words[i + 3]] AS gram FROM win),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, gram) AS n FROM keyed) WHERE n >= 2),
covered AS (SELECT doc_id, count(DISTINCT j)::BIGINT AS n_repeat_words
            FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM rep) GROUP BY doc_id),
ln AS (SELECT doc_id, line FROM (SELECT doc_id, unnest(string_split(body, chr(10))) AS line FROM w)
       WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
lstat AS (SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) - count(DISTINCT line))::BIGINT AS n_dup_lines,
                 (count(*) FILTER (WHERE regexp_matches(line, '^[\x20\x09-\x0D]*[-*•]')))::BIGINT AS n_bullet_lines,
                 (count(*) FILTER (WHERE regexp_matches(line, '(\.\.\.|…) *$')))::BIGINT AS n_ellipsis_lines
          FROM ln GROUP BY doc_id),
st AS (SELECT doc_id, count(*)::BIGINT AS n_stop_words FROM (SELECT doc_id, unnest(words) AS word FROM w)
       WHERE lower(word) IN ("""
    + ", ".join(f"'{x}'" for x in dict.fromkeys(STOP_WORDS))
    + r""") GROUP BY doc_id),
m AS (
  SELECT w.doc_id, len(words)::BIGINT AS n_words,
         length(regexp_replace(body, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
         (length(body) - length(regexp_replace(body, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
         coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words,
         coalesce(n_lines, 0) AS n_lines, coalesce(n_stop_words, 0) AS n_stop_words,
         coalesce(n_bullet_lines, 0) AS n_bullet_lines, coalesce(n_ellipsis_lines, 0) AS n_ellipsis_lines
  FROM w LEFT JOIN covered c ON w.doc_id = c.doc_id LEFT JOIN lstat l ON w.doc_id = l.doc_id
         LEFT JOIN st ON w.doc_id = st.doc_id)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       NOT ("""
    + " AND ".join(_sql_rule(r) for r in BASE_RULES)
    + ") AS base_failed, ("
    + " AND ".join(_sql_rule(r) for r in BASE_RULES + RULES)
    + """) AS kept
FROM m
"""
)
