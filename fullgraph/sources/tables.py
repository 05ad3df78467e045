"""Readers, writers and views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> None:
    for n in names or TABLES:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def read_edge_list(spark: SparkSession, path: str, sep: str = r"\s+") -> DataFrame:
    """Edges from text lines ``src dst [w]``; lines that start with # are comments."""
    from pyspark.sql import functions as F

    parts = F.split(F.trim("value"), sep)
    lines = spark.read.text(path).filter(~F.col("value").startswith("#") & (F.trim("value") != ""))
    return lines.select(F.get(parts, F.lit(0)).cast("long").alias("src"), F.get(parts, F.lit(1)).cast("long").alias("dst"), F.coalesce(F.get(parts, F.lit(2)).cast("double"), F.lit(1.0)).alias("w"))


def read(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "overwrite", **options) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*by) if by else writer).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str, sort: list[str]) -> None:
    """A catalog table clustered and sorted for joins that repeat every epoch."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(*sort).saveAsTable(table)


def drain(df: DataFrame) -> None:
    """Run a plan without keeping its rows (for timing)."""
    df.write.format("noop").mode("overwrite").save()
