"""Exact deduplication as a stateful stream, in DataFrame expressions only.

Documents are equal when their texts agree after every ASCII white-space
character is deleted.  The stream carries a fingerprint of each document:
SHA-256 digest of the normalised text, stable identifier (``doc_id``), length
and content locator (source file and row, where the source has them).  State is
keyed by digest, lives on disk (RocksDB provider), has no watermark and so never
expires; per digest it holds the survivor's identifier and locator and the
number of documents seen.  Each micro-batch's changed keys go to a table in the
shared folder; the newest version of a key is its state.

Equal digests are only a hit.  The full normalised bytes under each digest that was
seen twice or more are compared as the smallest and the largest text it holds: the
two agree exactly when all of them do, and both combine on the map side, so a group
of copies that holds a third of the corpus sends one text per task.  Texts of digests
seen once stay where they are: the hits' hashes are set in a bitmap of ``HIT_BITS``
bits (its size does not grow), which is broadcast to the scan.  The bitmap may let a
text pass that is no hit, never the reverse.  Digests that fail the comparison are
grouped by their bytes instead.

Survivor: most code points in the original text, then smallest ``doc_id``.
Defined results: null text counts as empty; a null ``doc_id`` sorts after every
other; rows that repeat a ``doc_id`` are each a member of their group, and the
first by locator stays; extra columns pass unread; an empty table gives an empty
result.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .base import WS, drop_dir, fresh, stored, work_dir

#: Bits of the bitmap of hits: 4 MB, a row of 4 KB per 32,768 of them.
HIT_BITS = 1 << 25
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def normal_text(text: Column) -> Column:
    return F.translate(text, WS, "")


def sha_key(norm: Column) -> Column:
    return F.unhex(F.sha2(F.encode(norm, "UTF-8"), 256))


def with_locator(docs: DataFrame, name: str = "_locator") -> DataFrame:
    """Add the locator: file and row where the source is files, else a row number of this plan."""
    try:
        meta = docs.metadataColumn("_metadata")
        place = F.concat_ws("#", meta.getField("file_path"), F.lpad(meta.getField("row_index").cast("string"), 12, "0"))
        return docs.select("*", place.alias(name))
    except AnalysisException:
        return docs.select("*", F.lpad(F.monotonically_increasing_id().cast("string"), 20, "0").alias(name))


def filed(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The same rows from files: locators must name the same row in every pass."""
    try:
        docs.select(docs.metadataColumn("_metadata").getField("row_index"))
        return docs
    except AnalysisException:
        return stored(spark, docs, "documents")


def fingerprints(docs: DataFrame, key=sha_key) -> DataFrame:
    """digest, doc_id, chars, locator (and sha256 where ``key`` is another digest); batch or streaming."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    norm = normal_text(text)
    extra = [] if key is sha_key else [sha_key(norm).alias("sha256")]
    own = fresh(docs, "_locator")
    return with_locator(docs, own).select(
        key(norm).alias("digest"), F.col("doc_id").cast("long").alias("doc_id"), F.length(text).cast("long").alias("chars"), F.col(own).alias("locator"), *extra
    )


def _first() -> Column:
    """The survivor sorts first."""
    return F.struct((-F.col("chars")).alias("less"), F.col("doc_id").isNull().alias("null_last"), F.col("doc_id").alias("doc_id"), F.col("locator").alias("locator"))


SURVIVOR = T.StructType([T.StructField("less", T.LongType()), T.StructField("null_last", T.BooleanType()), T.StructField("doc_id", T.LongType()), T.StructField("locator", T.StringType())])
CHANGED = T.StructType([T.StructField("digest", T.BinaryType()), T.StructField("survivor", SURVIVOR), T.StructField("seen", T.LongType()), T.StructField("batch", T.LongType())])


def keyed_state(fingerprint_stream: DataFrame) -> DataFrame:
    """The stateful operator: one row per digest with survivor and count, no expiry."""
    return fingerprint_stream.groupBy("digest").agg(F.min(_first()).alias("survivor"), F.count(F.lit(1)).alias("seen"))


def run_stream(spark: SparkSession, fingerprint_stream: DataFrame, folder: str) -> DataFrame:
    """Drain the stream into the disk-backed state; return digest, survivor, seen.

    ``folder`` holds the checkpoint (offsets, state) and the versions of changed
    keys; running again with the same folder resumes and sees only new files.
    """
    conf = fingerprint_stream.sparkSession.conf
    conf.set("spark.sql.streaming.stateStore.providerClass", ROCKS)
    conf.set("spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled", "true")
    conf.set("spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage", "true")
    conf.set("spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB", "256")
    conf.set("spark.sql.streaming.stateStore.rocksdb.allowFAllocate", "false")
    conf.set("spark.sql.streaming.noDataMicroBatches.enabled", "false")
    query = (
        keyed_state(fingerprint_stream)
        .writeStream.outputMode("update")
        .option("checkpointLocation", f"{folder}/state")
        .foreachBatch(lambda rows, batch: rows.write.mode("overwrite").parquet(f"{folder}/changed/batch={batch}"))
        .trigger(availableNow=True)
        .start()
    )
    query.awaitTermination()
    versions = _children(spark, f"{folder}/changed")
    if not versions:
        return spark.createDataFrame([], CHANGED).drop("batch")
    changed = spark.read.schema(CHANGED).parquet(f"{folder}/changed")
    if len(versions) == 1:
        return changed.drop("batch")
    return changed.groupBy("digest").agg(F.max_by("survivor", "batch").alias("survivor"), F.max("seen").alias("seen"))


def _children(spark: SparkSession, path: str) -> list[str]:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []


def drain(spark: SparkSession, docs: DataFrame, key=sha_key, max_files_per_batch: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(fingerprints, state) of a batch table.

    Fingerprints are written to the shared folder once and streamed from there,
    so any table works as a source and the locators stay fixed.
    """
    folder = work_dir(spark, "exact-dedup")
    slim = fingerprints(docs, key)  # reads doc_id and text only
    slim.write.parquet(f"{folder}/fingerprints")
    session = spark.newSession()
    session.conf.set("spark.sql.shuffle.partitions", spark.conf.get("spark.sql.shuffle.partitions"))
    reader = session.readStream.schema(slim.schema)
    if max_files_per_batch:
        reader = reader.option("maxFilesPerTrigger", max_files_per_batch)
    state = run_stream(spark, reader.parquet(f"{folder}/fingerprints"), folder)
    drop_dir(spark, f"{folder}/state")
    return spark.read.schema(slim.schema).parquet(f"{folder}/fingerprints"), state


def _slot(digest: Column) -> Column:
    return F.pmod(F.xxhash64(digest), F.lit(HIT_BITS)) + 1


def hit_bitmap(hits: DataFrame) -> DataFrame:
    """(bucket, bits): the slots of the digests as at most ``HIT_BITS / 32768`` rows of 4 KB."""
    slot = hits.select(_slot(F.col("digest")).alias("slot"))
    return slot.groupBy(F.bitmap_bucket_number("slot").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits"))


def unequal_digests(spark: SparkSession, docs: DataFrame, hits: DataFrame, key=sha_key) -> DataFrame:
    """Digests under which the full normalised texts are not all the same; ``hits`` are those seen twice or more."""
    norm = normal_text(F.coalesce(F.col("text").cast("string"), F.lit("")))
    bitmap = stored(spark, hit_bitmap(hits), "hit-bitmap")
    texts = docs.select(norm.alias("norm")).select(key(F.col("norm")).alias("digest"), "norm").withColumn("slot", _slot(F.col("digest")))
    near = texts.join(F.broadcast(bitmap), F.bitmap_bucket_number(F.col("slot")) == F.col("bucket"))
    at = F.bitmap_bit_position(F.col("slot"))
    byte = F.conv(F.hex(F.substr("bits", F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    bytes_under = near.filter(F.pmod(F.floor(byte / F.pow(F.lit(2.0), F.pmod(at, F.lit(8)))), F.lit(2)) == 1)
    return bytes_under.groupBy("digest").agg(F.min("norm").alias("low"), F.max("norm").alias("high")).filter("low <> high").select("digest")


def exact_groups(spark: SparkSession, docs: DataFrame, key=sha_key, max_files_per_batch: int | None = None) -> DataFrame:
    """Every row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256, locator, keep_locator."""
    docs = filed(spark, docs)
    slim, state = drain(spark, docs, key, max_files_per_batch)
    sha = F.lower(F.hex(F.col("digest" if key is sha_key else "sha256")))
    unequal = stored(spark, unequal_digests(spark, docs, state.filter("seen > 1").select("digest"), key), "unequal-digests")

    def rows(members: DataFrame) -> DataFrame:
        return members.select(
            "doc_id",
            F.col("survivor.doc_id").alias("keep_id"),
            F.col("seen").alias("group_size"),
            (F.col("locator") == F.col("survivor.locator")).alias("kept"),
            sha.alias("text_sha256"),
            "locator",
            F.col("survivor.locator").alias("keep_locator"),
        )

    if unequal.isEmpty():
        return rows(slim.join(state, "digest"))
    by_bytes = slim.join(unequal, "digest", "left_semi")
    # Under a digest that failed, SHA-256 of the text and the text's own bytes tell the groups apart.
    own = fresh(docs, "_locator")
    place = with_locator(docs, own).select(F.col(own).alias("locator"), normal_text(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("norm"))
    full = by_bytes.join(place, "locator")
    regrouped = full.groupBy("digest", "norm").agg(F.min(_first()).alias("survivor"), F.count(F.lit(1)).alias("seen"))
    return rows(slim.join(unequal, "digest", "left_anti").join(state, "digest")).unionByName(rows(full.join(regrouped, ["digest", "norm"])))


def deduplicate(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, all columns."""
    docs = filed(spark, docs)
    mine = fresh(docs, "_locator")
    other = fresh(docs, "_kept_locator")
    kept = exact_groups(spark, docs).filter("kept").select(F.col("locator").alias(other))
    return with_locator(docs, mine).join(kept, F.col(mine) == F.col(other), "left_semi").select(*[F.col(f"`{c}`") for c in docs.columns])


def digest(spark: SparkSession, docs: DataFrame) -> DataFrame:
    return exact_groups(spark, docs).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


ORACLE_SQL = r"""
WITH n AS (
  SELECT doc_id, length(coalesce(text, '')) AS chars,
         regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS norm
  FROM documents),
r AS (
  SELECT doc_id, norm, chars,
         first_value(doc_id) OVER (PARTITION BY norm ORDER BY chars DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY norm) AS group_size
  FROM n)
SELECT doc_id, keep_id, group_size::BIGINT AS group_size, doc_id = keep_id AS kept, sha256(norm) AS text_sha256
FROM r
"""
