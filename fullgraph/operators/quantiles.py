"""Exact quantiles of a column without a sort of all rows in one task."""

from __future__ import annotations

from collections.abc import Iterable
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import cut


def exact(df: DataFrame, column: Column, shares: Iterable[float]) -> list:
    """The value of rank ceil(n * share), 1 at least, for every share; nulls do not count, no rows give [].

    Values are counted first, so a frequent one is one row, and dealt by ranges.  The driver gets a
    row per range and a value per share; ranks are worked out inside the ranges that hold them.
    """
    spark = df.sparkSession
    values = df.select(column.alias("x")).filter("x is not null").groupBy("x").agg(F.count(F.lit(1)).alias("c"))
    dealt = cut(spark, values.repartitionByRange("x").withColumn("part", F.spark_partition_id()), "values")
    sizes = sorted((r.part, r.n) for r in dealt.groupBy("part").agg(F.sum("c").alias("n")).collect())
    total = sum(n for _, n in sizes)
    if not total:
        return []
    places = []
    for share in shares:
        rank = max(1, -(-total * Fraction(str(share)) // 1))  # as a decimal: 0.8 of 5 rows is 4
        for part, n in sizes:
            if rank <= n:
                break
            rank -= n
        places.append((part, int(rank)))
    upto = dealt.filter(F.col("part").isin(sorted({p for p, _ in places}))).withColumn("upto", F.sum("c").over(Window.partitionBy("part").orderBy("x")))
    asked = None
    for part, rank in set(places):
        one = (F.col("part") == part) & (F.col("upto") >= rank) & (F.col("upto") - F.col("c") < rank)
        asked = one if asked is None else asked | one
    got = upto.filter(asked).collect()
    return [next(r.x for r in got if r.part == part and r.upto - r.c < rank <= r.upto) for part, rank in places]
