"""Language identification: multinomial naive Bayes over hashed character n-grams.

Training counts the n-grams (1 to 3 characters, hashed to ``BUCKETS``) of
labelled training documents per language, on the executors, and sums them there;
only the languages x buckets matrix reaches the driver.  The smoothed
log-probability matrix is broadcast (languages x ``BUCKETS`` 32-bit floats; the
number of languages is checked) and scoring multiplies it with the sparse matrix of
a batch's n-gram counts (documents x buckets) in numpy, a bounded block at a time.

The training sample is bounded: of the labelled training documents those with
the smallest hashes, about ``MAX_TRAIN`` of them.  A document is a training
document when crc32 of its ``doc_id`` as text is not 0 modulo 5.

Defined results: null text, or text without a letter, is ``und`` with score 0;
without any training document every row is ``und``; repeated rows are scored row
by row; a null ``doc_id`` counts as held out; extra columns pass unread; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .base import ship, slices, spread, unit_hash

BUCKETS = 1 << 15
ORDERS = (1, 2, 3)
MAX_TRAIN = 20_000
MAX_LANGUAGES = 512
#: Numbers in a block of counts times log-probabilities.
BLOCK = 1 << 22
PAD = "\n\n"


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")) % 5 == 0, F.lit(True))


def gram_buckets(texts: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
    """Bucket of the n-gram at each place, per order, and each text's first place.

    Two line ends stand before each text, so no n-gram holds characters of two texts.
    """
    lowered = [PAD + t.lower() for t in texts]
    sizes = np.fromiter(map(len, lowered), dtype=np.int64, count=len(lowered))
    code = np.frombuffer(("".join(lowered) + PAD).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    n = len(code) - len(PAD)
    grams, h = [], np.zeros(n, dtype=np.uint32)
    for k in ORDERS:
        h = (h ^ code[k - 1 : k - 1 + n]) * np.uint32(0x9E3779B1)
        grams.append(((h ^ (h >> np.uint32(15))) * np.uint32(0x85EBCA6B)) >> np.uint32(17))
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]) if len(sizes) else np.zeros(0, dtype=np.int64)
    return grams, starts


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: dict[str, np.ndarray] = {}
    for batch in slices(batches, "text"):
        langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
        for lang in sorted(set(langs)):
            grams, _ = gram_buckets([t for x, t in zip(langs, texts) if x == lang])
            seen = counts.setdefault(lang, np.zeros(BUCKETS, dtype=np.int64))
            for g in grams:
                seen += np.bincount(g, minlength=BUCKETS)
    for lang, seen in counts.items():
        at = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at), pa.array(seen[at])], names=["lang", "bucket", "n"])


def _dense(table: pa.Table) -> pa.Table:
    out = np.zeros(BUCKETS, dtype="<i8")
    out[table["bucket"].to_numpy()] = table["n"].to_numpy()
    return pa.table({"lang": table["lang"].slice(0, 1), "counts": pa.array([out.tobytes()], pa.binary())})


def train(spark: SparkSession, docs: DataFrame, max_train: int = MAX_TRAIN, alpha: float = 0.5, partitions: int = 12) -> tuple[list[str], np.ndarray]:
    """(languages, log-probability matrix of buckets x languages)."""
    ship(spark)
    labelled = docs.filter(docs["lang"].isNotNull() & docs["text"].isNotNull() & ~held_out(docs["doc_id"]))
    total = labelled.count()
    share = min(1.0, max_train / max(1, total))
    sample = labelled.filter(unit_hash(docs["doc_id"], 8) < share).select(F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    counts = sample.repartition(partitions).mapInArrow(_count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n"))
    rows = counts.groupBy("lang").applyInArrow(_dense, "lang string, counts binary").limit(MAX_LANGUAGES + 1).collect() if total else []  # a row of BUCKETS numbers per language
    if len(rows) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages; raise MAX_LANGUAGES and BUCKETS together")
    rows.sort(key=lambda r: r.lang)
    langs = [r.lang for r in rows]
    seen = np.stack([np.frombuffer(r.counts, dtype="<i8") for r in rows], axis=1).astype(np.float64) if rows else np.zeros((BUCKETS, 1))
    seen += alpha
    return langs, np.log(seen / seen.sum(axis=0)).astype(np.float32)


def score_texts(texts: list[str], log_prob: np.ndarray) -> np.ndarray:
    """Summed log-probability of each text (rows) in each language (columns)."""
    grams, starts = gram_buckets(texts)
    total = np.zeros((len(texts), log_prob.shape[1]), dtype=np.float64)
    if not texts:
        return total
    owner = np.repeat(np.arange(len(texts), dtype=np.uint64), np.diff(np.append(starts, len(grams[0])))) * np.uint64(BUCKETS)
    cell, n = np.unique(np.concatenate([owner + g for g in grams]), return_counts=True)
    doc, bucket = (cell // np.uint64(BUCKETS)).astype(np.int64), (cell % np.uint64(BUCKETS)).astype(np.int64)
    step = max(1, BLOCK // log_prob.shape[1])
    for lo in range(0, len(cell), step):  # cells are in order of their document
        part = slice(lo, lo + step)
        first = np.flatnonzero(np.diff(doc[part], prepend=-1))
        total[doc[part][first]] += np.add.reduceat(log_prob[bucket[part]] * n[part, None], first, axis=0)
    return total


def _has_letter(t: str | None) -> bool:
    return bool(t) and any(map(str.isalpha, t))


def predict(spark: SparkSession, docs: DataFrame, model: tuple[list[str], np.ndarray]) -> DataFrame:
    """doc_id, held_out, lang_pred, score (posterior probability of the prediction)."""
    ship(spark)
    langs, matrix = model
    shared = spark.sparkContext.broadcast(matrix)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text", 1 << 20):
            texts = batch.column(2).to_pylist()
            best, score = ["und"] * len(texts), [0.0] * len(texts)
            use = [i for i, t in enumerate(texts) if _has_letter(t)] if langs else []
            if use:
                total = score_texts([texts[i] for i in use], shared.value)
                top = total.argmax(axis=1)
                posterior = 1 / np.exp(total - total.max(axis=1, keepdims=True)).sum(axis=1)
                for i, k, p in zip(use, top, posterior):
                    best[i], score[i] = langs[k], float(p)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(best), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), held_out(docs["doc_id"]).alias("held_out"), docs["text"].cast("string").alias("text"))
    return spread(rows).mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def identify(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return predict(spark, docs, train(spark, docs))
