"""Line deduplication over the whole corpus, in DataFrame expressions only.

A text is split at ``\\n``; a line's key is the line stripped of ASCII white
space with A-Z lower-cased.  Keys are carried as 128 hash bits (two 64-bit
hashes, the second over the key with a prefix).  A first pass counts, per key,
the documents that hold it (keys are made distinct inside the row, so the count
combines on the map side) and finds the largest ``doc_id``; a second pass joins
the lines to the keys over the threshold.  Only hashes and positions travel in
both; texts move once, when the dropped positions come back to their document.

The join's hot side (a line that a third of all documents hold) meets one row
per key, so adaptive execution can split it.

Defined results: null or empty text is one empty line; every row is a document,
so rows that repeat a ``doc_id`` count one by one and get the same decision for
the same text; a null ``doc_id`` sorts before every other; extra columns pass
unread; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import WS, ascii_lower, stored, text_of

MIN_KEY_CHARS = 20
MIN_DOCUMENTS = 3


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(WS)))


def _identity(key: Column) -> list[Column]:
    return [F.xxhash64(key).alias("h1"), F.xxhash64(F.lit("line"), key).alias("h2")]


def line_counts(docs: DataFrame, min_chars: int = MIN_KEY_CHARS) -> DataFrame:
    """h1, h2, n_docs, keeper (largest doc_id) of every line key."""
    keys = F.array_distinct(F.transform(F.split(text_of(docs), "\n", -1), line_key))
    return (
        docs.select(docs["doc_id"].alias("doc_id"), F.explode(keys).alias("key"))
        .filter(F.length("key") >= min_chars)
        .select("doc_id", *_identity(F.col("key")))
        .groupBy("h1", "h2")
        .agg(F.count(F.lit(1)).alias("n_docs"), F.max("doc_id").alias("keeper"))
    )


def line_positions(docs: DataFrame, min_chars: int = MIN_KEY_CHARS) -> DataFrame:
    """doc_id, row_hash, pos, h1, h2 of every line long enough to count."""
    text = text_of(docs)
    return (
        docs.select(docs["doc_id"].alias("doc_id"), F.xxhash64(text).alias("row_hash"), F.posexplode(F.split(text, "\n", -1)).alias("pos", "line"))
        .select("doc_id", "row_hash", "pos", line_key(F.col("line")).alias("key"))
        .filter(F.length("key") >= min_chars)
        .select("doc_id", "row_hash", "pos", *_identity(F.col("key")))
    )


def drop_repeated_lines(docs: DataFrame, min_chars: int = MIN_KEY_CHARS, min_docs: int = MIN_DOCUMENTS) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_text."""
    # stored, so that the join's sides are plain exchanges, whose hot partitions adaptive execution can split
    counted = stored(docs.sparkSession, line_counts(docs, min_chars).filter(F.col("n_docs") >= min_docs).select("h1", "h2", "keeper"), "line-keys")
    hits = (
        line_positions(docs, min_chars)
        .join(counted, ["h1", "h2"])
        .filter(~F.col("doc_id").eqNullSafe(F.col("keeper")))
        .groupBy("doc_id", "row_hash")
        .agg(F.collect_set("pos").alias("gone"))
        .withColumnRenamed("doc_id", "hit_id")
        .withColumnRenamed("row_hash", "hit_hash")
    )
    text = text_of(docs)
    rows = docs.select(docs["doc_id"].alias("doc_id"), text.alias("body"), F.xxhash64(text).alias("row_hash"))
    joined = rows.join(hits.hint("shuffle_hash"), F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("row_hash") == F.col("hit_hash")), "left")
    cut = joined.select("doc_id", "body", "gone", F.split("body", "\n", -1).alias("lines"))
    left = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("gone"))
    kept = F.array_join(F.transform(left, lambda i: F.get("lines", i)), "\n")
    return cut.select(
        "doc_id",
        F.size("lines").cast("long").alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_dropped"),
        F.when(F.col("gone").isNull(), F.col("body")).otherwise(kept).alias("kept_text"),
    )


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns of :func:`drop_repeated_lines`."""
    return drop_repeated_lines(docs).select("doc_id", "n_lines", F.greatest("n_dropped", F.lit(0)).alias("n_dropped"), F.sha2(F.encode("kept_text", "UTF-8"), 256).alias("kept_sha256"))


ORACLE_SQL = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS pos
  FROM documents),
keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                   'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM lines),
counted AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 20
  GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
marked AS (
  SELECT k.doc_id, k.pos, k.line, c.keeper IS NOT NULL AND c.keeper <> k.doc_id AS gone
  FROM keyed k LEFT JOIN counted c ON k.key = c.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE gone))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
