"""A session with the settings the engine is designed for, and code shipping to executors."""

from __future__ import annotations

import atexit
import io
import os
import tempfile
import time
import uuid
import zipfile

from py4j.protocol import Py4JJavaError
from pyspark import SparkContext
from pyspark.sql import DataFrame, SparkSession

SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    # bucketed inputs keep their layout in joins on more keys than the bucket key
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.session.timeZone": "UTC",
}


def get_spark(app: str = "fullgraph", **conf: str) -> SparkSession:
    builder = SparkSession.builder.appName(app)
    for k, v in (SETTINGS | conf).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def ship(spark: SparkSession) -> None:
    """Send the package's source to the executors, once per application."""
    sc = spark.sparkContext
    if getattr(sc, "_engine_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w") as z:
        for folder, _, names in os.walk(root):
            for f in sorted(names):
                if f.endswith(".py"):
                    full = os.path.join(folder, f)
                    z.write(full, os.path.join("fullgraph", os.path.relpath(full, root)))
    path = os.path.join(tempfile.mkdtemp(prefix="ship-"), "fullgraph_engine.zip")
    with open(path, "wb") as out:
        out.write(buf.getvalue())
    sc.addPyFile(path)
    sc._engine_shipped = True


_made: list[tuple[SparkSession, str]] = []


def checkpoint_root(sc: SparkContext) -> str:
    """The shared checkpoint folder.

    A temporary folder stands in only where none is set and the driver's own threads do all work;
    on a cluster a folder of one machine would not be seen by the others.
    """
    root = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not root:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        root = tempfile.mkdtemp(prefix="fullgraph-work-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(root)
    return root


def work_path(spark: SparkSession, name: str) -> str:
    """A fresh folder below the shared checkpoint folder; removed when the driver ends."""
    root = spark.conf.get("spark.checkpoint.dir", None) or checkpoint_root(spark.sparkContext)
    path = f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not _made:
        atexit.register(_clean)
    _made.append((spark, path))
    return path


def drop(spark: SparkSession, path: str | None) -> None:
    """Remove a folder that nothing reads any more."""
    if path:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def _clean() -> None:
    for spark, path in _made:
        try:
            drop(spark, path)
        except Exception:  # noqa: BLE001  the gateway may be gone at exit
            return


BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"
#: Bytes of a row group of large rows.
ROW_GROUP = 32 << 20


def cut(spark: SparkSession, df: DataFrame, name: str = "cut", narrow: bool = False, batch_bytes: int | None = None) -> DataFrame:
    """Write rows to the shared folder and read them back: ends the lineage, survives lost executors.

    ``narrow`` rows go to Python in batches bounded by their number alone: with a bound on bytes Spark
    adds up all columns' buffers again for every row, which took most of the time of passes over edges.
    ``batch_bytes`` is that bound for rows that are large, which also stand in smaller row groups: a reader holds a whole one.
    """
    path = work_path(spark, name)
    before = spark.conf.get(BATCH_BYTES, None)
    if narrow:
        batch_bytes = (1 << 31) - 1
    if batch_bytes:
        spark.conf.set(BATCH_BYTES, str(batch_bytes))
    try:
        (df.write.option("parquet.block.size", str(ROW_GROUP)) if batch_bytes and not narrow else df.write).parquet(path)
    finally:
        if batch_bytes:
            spark.conf.set(BATCH_BYTES, before) if before is not None else spark.conf.unset(BATCH_BYTES)
    out = spark.read.schema(df.schema).parquet(path)
    out._path = path
    return out


def spread(df: DataFrame) -> DataFrame:
    """Deal rows over the cores where a scan has fewer tasks than them (a small table in one row group)."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


class traffic:
    """Shuffle bytes that the jobs inside a ``with`` block wrote, from Spark's stage metrics.

    ``write_ms`` and ``wait_ms`` are the tasks' times to write shuffle files and to wait for fetched ones.
    """

    def __init__(self, spark: SparkSession):
        self.sc, self.tag, self.bytes = spark.sparkContext, f"traffic-{uuid.uuid4().hex}", 0
        self.write_ms = self.wait_ms = 0.0

    def __enter__(self) -> traffic:
        self.sc.addJobTag(self.tag)
        return self

    def __exit__(self, kind, *_) -> None:
        self.sc.removeJobTag(self.tag)
        if kind is not None:
            return
        jsc = self.sc._jsc.sc()
        store, stages = jsc.statusStore(), set()
        for job in jsc.statusTracker().getJobIdsForTag(self.tag):
            info = store.job(job)
            deadline = time.time() + 5
            while str(info.status()) == "RUNNING" and time.time() < deadline:  # the listener is a little behind
                time.sleep(0.01)
                info = store.job(job)
            ids = info.stageIds()
            stages |= {ids.apply(i) for i in range(ids.size())}
        read = [self._read(store, s) for s in stages]
        self.bytes, self.write_ms, self.wait_ms = (sum(r[i] for r in read) for i in range(3))

    @staticmethod
    def _read(store, stage: int) -> tuple[int, float, float]:
        try:
            s = store.lastStageAttempt(stage)
            return s.shuffleWriteBytes(), s.shuffleWriteTime() / 1e6, float(s.shuffleFetchWaitTime())
        except Py4JJavaError as gone:
            if "No stage with id" not in str(gone):
                raise
            return 0, 0.0, 0.0  # a skipped stage, which wrote nothing; Spark keeps only so many of them
