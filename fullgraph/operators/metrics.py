"""Volumes, balance, reduction, quantization error, accuracy."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .remote import PAIR, shipped


def comm_matrix(routed: DataFrame, width: int, bits: int = 32) -> DataFrame:
    """sp, dp, vectors, elements, bits of one layer's exchange."""
    return shipped(routed).select(*PAIR, "vectors", (F.col("vectors") * width).alias("elements"), (F.col("vectors") * width * bits).alias("bits"))


def comm_volume(routed: DataFrame, width: int, bits: int = 32, group_rows: int = 1) -> DataFrame:
    """Bytes of data and of parameters (two 32-bit numbers per row group) of one layer."""
    rows = F.ceil(F.col("vectors") / group_rows) if bits < 32 else F.lit(0)
    per = F.ceil(F.lit(width * bits) / 8)
    return shipped(routed).agg(F.sum("vectors").alias("vectors"), F.sum(F.col("vectors") * per).cast("long").alias("data_bytes"), F.sum(rows * 8).cast("long").alias("param_bytes"))


def imbalance(comm: DataFrame) -> DataFrame:
    """Largest and mean volume that a part sends, and their ratio."""
    sent = comm.groupBy("sp").agg(F.sum("vectors").alias("v"))
    return sent.agg(F.max("v").alias("most"), F.avg("v").alias("mean")).select("most", "mean", (F.col("most") / F.col("mean")).alias("ratio"))


def partition_quality(located: DataFrame) -> DataFrame:
    """Edges, cut edges, cut ratio, and the busiest pair."""
    pairs = located.groupBy(*PAIR).agg(F.count(F.lit(1)).alias("e"))
    remote = F.when(F.col("sp") != F.col("dp"), F.col("e")).otherwise(0)
    return pairs.agg(F.sum("e").alias("edges"), F.sum(remote).alias("cut_edges"), F.max(remote).alias("busiest_pair")).select("edges", "cut_edges", (F.col("cut_edges") / F.col("edges")).alias("cut_ratio"), "busiest_pair")


def part_load(nodes: DataFrame, parts: DataFrame, weights: DataFrame) -> DataFrame:
    """Nodes and weight of every part."""
    return nodes.select("id").join(parts, "id").join(weights, "id").groupBy("part").agg(F.count(F.lit(1)).alias("nodes"), F.sum("weight").alias("weight"))


def reduction(volumes: DataFrame, hybrid: DataFrame) -> DataFrame:
    """Totals of each strategy and what the cover saves against the best single one."""
    h = hybrid.agg(F.sum("vectors").alias("hybrid"))
    v = volumes.agg(*[F.sum(c).alias(c) for c in ("edges", "pre", "post", "best_of_two")])
    return v.crossJoin(h).select("*", (F.least("pre", "post") / F.col("hybrid")).alias("gain"))


def quant_error(vectors: DataFrame, back: DataFrame, params: DataFrame) -> DataFrame:
    """Largest error in units of the scale, mean error, over all elements."""
    j = vectors.join(back.withColumnRenamed("v", "u"), "id").join(params.select("id", "sc"), "id")
    cells = j.select("sc", F.explode(F.zip_with("u", "v", lambda a, b: a - b)).alias("e"))
    return cells.agg(F.max(F.when(F.col("sc") > 0, F.abs("e") / F.col("sc")).otherwise(0.0)).alias("worst_in_scales"), F.avg("e").alias("bias"), F.stddev("e").alias("spread"))


def accuracy(pred: DataFrame, nodes: DataFrame) -> DataFrame:
    """split, nodes, correct, accuracy over labelled nodes; the majority rate stands beside it."""
    j = pred.join(nodes.filter("label is not null").select("id", "label", "split"), "id")
    top = nodes.filter("label is not null").groupBy("split", "label").count().groupBy("split").agg(F.max("count").alias("m"), F.sum("count").alias("n")).select("split", (F.col("m") / F.col("n")).alias("majority"))
    return j.groupBy("split").agg(F.count(F.lit(1)).alias("nodes"), F.sum((F.col("pred") == F.col("label")).cast("long")).alias("correct")).join(top, "split").select("split", "nodes", "correct", (F.col("correct") / F.col("nodes")).alias("accuracy"), "majority")


def neighbour_vote(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Majority label of a node's training neighbours (ties: smallest label)."""
    known = nodes.filter("split = 'train' and label is not null").select(F.col("id").alias("src"), "label")
    votes = edges.join(known, "src").groupBy("dst", "label").agg(F.count(F.lit(1)).alias("c"))
    return votes.groupBy("dst").agg(F.max_by("label", F.struct("c", -F.col("label"))).alias("pred")).select(F.col("dst").alias("id"), "pred")
