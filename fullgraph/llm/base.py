"""What the text operators share: inputs, the shared work folder, code shipping, Arrow slicing."""

from __future__ import annotations

import atexit
import io
import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space as the contracts define it: space and \t to \r.
WS = " \t\n\x0b\x0c\r"
WS_CLASS = "[\\x20\\x09-\\x0D]"
WORD_CLASS = "[^\\x20\\x09-\\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: A batch of rows on its way to a Python worker: long texts must not add up to the default of 256 MB.
BATCH_BYTES, MAX_BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 16 << 20

_made: list[tuple[SparkSession, str]] = []


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def work_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder below the cluster's shared checkpoint folder.

    ``spark.checkpoint.dir`` is used where the session has it; where it is unset a
    temporary folder stands in only if the driver's own threads do all work.
    Folders made here are removed when the driver ends.
    """
    sc = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not root:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = tempfile.mkdtemp(prefix="corpus-work-")
        sc.setCheckpointDir(root)
    if not _made:
        atexit.register(_clean)
    path = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def _clean() -> None:
    for spark, path in _made:
        try:
            drop_dir(spark, path)
        except Exception:  # noqa: BLE001  the gateway may be gone at exit
            return


def drop_dir(spark: SparkSession, path: str) -> None:
    """Remove a work folder whose rows no later step reads."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def write_table(spark: SparkSession, df: DataFrame, path: str) -> DataFrame:
    """Write rows below ``path`` and read them back; the write's shuffle files go when it ends."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(key, before) if before is not None else spark.conf.unset(key)
    return spark.read.schema(df.schema).parquet(path)


def stored(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """A lineage cut that survives lost executors: rows go to the shared folder and are read back."""
    path = work_dir(spark, name)
    out = write_table(spark, df, path)
    out._work_path = path
    return out


def discard(spark: SparkSession, *tables: DataFrame) -> None:
    """Remove tables made by :func:`stored` that nothing reads any more."""
    for t in tables:
        drop_dir(spark, t._work_path)


def ship(spark: SparkSession) -> None:
    """Send this subpackage's source to the executors, once per application; bound a batch's bytes."""
    sc = spark.sparkContext
    plain = re.fullmatch(r"(\d+)b?", spark.conf.get(BATCH_BYTES))  # a value with a unit was set by hand
    if plain and int(plain[1]) > MAX_BATCH_BYTES:
        spark.conf.set(BATCH_BYTES, str(MAX_BATCH_BYTES))
    if getattr(sc, "_corpus_shipped", False):
        return
    here = os.path.dirname(os.path.abspath(__file__))
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w") as z:
        z.writestr("fullgraph/__init__.py", "")
        for f in sorted(os.listdir(here)):
            if f.endswith(".py"):
                z.write(os.path.join(here, f), f"fullgraph/llm/{f}")
    folder = tempfile.mkdtemp(prefix="ship-")
    path = os.path.join(folder, "corpus_ops.zip")
    with open(path, "wb") as out:
        out.write(buf.getvalue())
    sc.addPyFile(path)
    sc._corpus_shipped = True


def ascii_lower(c: Column) -> Column:
    """A-Z to a-z and nothing else; pure ASCII strings take the fast built-in."""
    return F.when(F.length(c) == F.octet_length(c), F.lower(c)).otherwise(F.translate(c, UPPER, LOWER))


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def spread(df: DataFrame) -> DataFrame:
    """Deal rows over the cores where a scan has fewer tasks than them (a small table in one row group)."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


#: Rows of one key from which on a join deals them over ``SALTS`` tasks.
HOT, SALTS = 20_000, 64


def split_join(spark: SparkSession, rows: DataFrame, facts: DataFrame, keys: list[str], count: str, hot: int | None = None) -> DataFrame:
    """``rows`` joined with ``facts`` (a row per key, with the key's number of rows in ``count``).

    Keys above ``hot`` rows are few (at most the rows over ``hot``): their fact is repeated once per
    salt, so one key's rows are dealt over many tasks.  ``count`` is not part of the result.
    """
    hot_keys = stored(spark, facts.filter(F.col(count) > (HOT if hot is None else hot)).select(*keys, F.lit(True).alias("_hot")), "hot-keys")
    if hot_keys.isEmpty():
        return rows.join(facts.drop(count), keys)
    copies = F.sequence(F.lit(0), F.when(F.col("_hot"), SALTS - 1).otherwise(0))
    dealt = facts.drop(count).join(hot_keys, keys, "left").select("*", F.explode(copies).alias("_salt")).drop("_hot")
    lane = F.pmod(F.xxhash64(*rows.columns), F.lit(SALTS)).cast("int")  # by value: a task that runs again deals alike
    salted = rows.withColumn("_lane", lane).join(hot_keys, keys, "left").withColumn("_salt", F.when(F.col("_hot"), F.col("_lane")).otherwise(0)).drop("_hot", "_lane")
    return salted.join(dealt, [*keys, "_salt"]).drop("_salt")


def text_of(df: DataFrame, column: str = "text") -> Column:
    """The text, null as empty."""
    return F.coalesce(df[column].cast("string"), F.lit(""))


def slices(batches: Iterator[pa.RecordBatch], column: str, max_bytes: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that the text of a slice stays near ``max_bytes`` (or is one document)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.binary_length(batch.column(batch.schema.get_field_index(column)))
        start = total = 0
        for i, n in enumerate(sizes.to_pylist()):
            n = n or 0
            if total and total + n > max_bytes:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        yield batch.slice(start)


def unit_hash(c: Column, seed: int) -> Column:
    """A uniform number in [0, 1) from a value: the first 52 bits of an md5."""
    word = F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(c.cast("string"), F.lit("")))), 1, 13)
    return F.conv(word, 16, 10).cast("double") / F.lit(float(1 << 52))
