"""Masked label propagation: shown training nodes carry their label into the features, the others give the loss."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import M31, mix_uniform


def shown(id_: Column, rate: float, epoch: int, seed: int = 0) -> Column:
    return mix_uniform(id_, F.lit(epoch), seed) < F.lit(float(rate))


def shown_rows(ids: np.ndarray, rate: float, epoch: int, seed: int = 0) -> np.ndarray:
    """The same choice for an array of ids."""
    step = lambda h: (h * 1103515245 + 12345) % M31
    h = step((ids % M31 * 1000003 + epoch * 7919 + seed * 104729) % M31)
    return step(h ^ (h >> 15)) / M31 < rate


def mask(nodes: DataFrame, rate: float = 0.5, epoch: int = 0, seed: int = 0) -> DataFrame:
    """(id, epoch, shown) of labelled training nodes; those not shown give the epoch's loss."""
    t = nodes.filter("split = 'train' and label is not null")
    return t.select("id", F.lit(epoch).alias("epoch"), shown(F.col("id"), rate, epoch, seed).alias("shown"))


def inject(nodes: DataFrame, visible: DataFrame | None, embed: list[list[float]], mode: str = "train") -> DataFrame:
    """Features plus the label's vector for visible nodes.

    ``visible`` has the ids shown this epoch; with ``mode='infer'`` every training
    label is shown.  A label outside the training split is never used.
    """
    t = nodes.filter("split = 'train' and label is not null").select("id", F.col("label").alias("_l"))
    if mode != "infer":
        t = t.join(visible.select("id"), "id", "left_semi")
    # one row per class: a table whose size is the number of classes
    table = F.array(*[F.array(*[F.lit(float(x)) for x in row]) for row in embed])
    added = F.when(F.col("_l").isNotNull(), F.zip_with("feat", F.get(table, F.col("_l")), lambda a, b: a + b)).otherwise(F.col("feat"))
    return nodes.join(t, "id", "left").select("id", added.alias("feat"), "label", "split")


def linearity_gap(edges: DataFrame, nodes: DataFrame, embed: list[list[float]], hops: int = 2) -> DataFrame:
    """(gap): largest difference between A^k (X + Y E) and A^k X + A^k Y E; zero up to rounding."""
    from ..functions.vectors import from_block, to_block, to_long
    from .aggregate import spmm

    def chain(x: DataFrame) -> DataFrame:
        b = to_block(x, v="v")
        for _ in range(hops):
            b = spmm(edges, b, weighted=True).withColumnRenamed("dst", "id")
        return to_long(from_block(b))

    width = len(embed[0])
    full = inject(nodes, None, embed, "infer")
    zero = F.array_repeat(F.lit(0.0), width)
    only = inject(nodes.withColumn("feat", zero), None, embed, "infer")
    a = chain(full.select("id", F.col("feat").alias("v"))).withColumnRenamed("x", "together")
    b = chain(nodes.select("id", F.col("feat").alias("v"))).withColumnRenamed("x", "features")
    c = chain(only.select("id", F.col("feat").alias("v"))).withColumnRenamed("x", "labels")
    return a.join(b, ["id", "k"]).join(c, ["id", "k"]).agg(F.max(F.abs(F.col("together") - F.col("features") - F.col("labels"))).alias("gap"))
