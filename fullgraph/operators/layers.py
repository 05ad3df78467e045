"""Layer pieces: numpy kernels for blocks of rows, and DataFrame forms of the row-wise ones."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import block_sums, packed
from ..session import ship

EPS = 1e-5


def layer_norm(v: Column, eps: float = EPS) -> Column:
    """Row-wise normalization to mean 0 and variance 1 (expressions, no shuffle)."""
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    bind = lambda value, f: F.get(F.transform(F.array(value), f), F.lit(0))  # noqa: E731  evaluates ``value`` once per row
    n = F.size(v).cast("double")

    def centred(c: Column) -> Column:
        spread = F.sqrt(total(F.transform(c, lambda x: x * x)) / n + F.lit(eps))
        return bind(spread, lambda s: F.transform(c, lambda x: x / s))

    return bind(total(F.transform(v, lambda x: x.cast("double"))) / n, lambda m: bind(F.transform(v, lambda x: x - m), centred))


def norm_rows(x: np.ndarray, gain: np.ndarray, bias: np.ndarray) -> tuple[np.ndarray, tuple]:
    mean = x.mean(axis=1, keepdims=True)
    inv = 1 / np.sqrt(x.var(axis=1, keepdims=True) + EPS)
    z = (x - mean) * inv
    return z * gain + bias, (z, inv)


def norm_rows_back(d: np.ndarray, gain: np.ndarray, saved: tuple) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(gradient of the input, of the gain, of the bias)."""
    z, inv = saved
    dz = d * gain
    dx = inv * (dz - dz.mean(axis=1, keepdims=True) - z * (dz * z).mean(axis=1, keepdims=True))
    return dx, (d * z).sum(axis=0), d.sum(axis=0)


def softmax_loss(logits: np.ndarray, labels: np.ndarray, rows: np.ndarray) -> tuple[float, np.ndarray]:
    """(summed cross-entropy of ``rows``, gradient of that sum)."""
    z = logits - logits.max(axis=1, keepdims=True)
    p = np.exp(z)
    p /= p.sum(axis=1, keepdims=True)
    at = np.flatnonzero(rows)
    grad = np.zeros_like(p)
    grad[at] = p[at]
    grad[at, labels[at]] -= 1
    return float(-np.log(p[at, labels[at]] + 1e-30).sum()), grad


def dense(df: DataFrame, w_self: np.ndarray, w_nbr: np.ndarray, bias: np.ndarray, relu: bool = True) -> DataFrame:
    """(id, v): relu(v W_self + nbr W_nbr + bias) of rows (id, v, nbr), one matrix product per Arrow batch."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast((w_self, w_nbr, bias))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ws, wn, b = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            mat = lambda i: np.asarray(batch.column(i).flatten(), dtype=np.float64).reshape(batch.num_rows, -1)
            z = mat(1) @ ws + mat(2) @ wn + b
            z = np.maximum(z, 0) if relu else z
            off = pa.array(np.arange(0, z.size + 1, z.shape[1], dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(off, pa.array(z.ravel()))], names=["id", "v"])

    return df.select("id", "v", "nbr").mapInArrow(run, "id long, v array<double>")


def with_gcn_weights(edges: DataFrame) -> DataFrame:
    """Edges with self-loops, weighted by 1 / sqrt(deg(src) deg(dst)) of the looped graph."""
    ids = edges.select(F.col("src").alias("n")).unionByName(edges.select(F.col("dst").alias("n"))).distinct()
    looped = edges.filter("src <> dst").select("src", "dst").unionByName(ids.select(F.col("n").alias("src"), F.col("n").alias("dst")))
    deg = looped.groupBy(F.col("dst").alias("n")).agg(F.count(F.lit(1)).alias("d"))
    at = lambda c: deg.select(F.col("n").alias(c), F.col("d").alias(f"d_{c}"))
    return looped.join(at("src"), "src").join(at("dst"), "dst").select("src", "dst", (1 / F.sqrt(F.col("d_src") * F.col("d_dst"))).alias("w"))


def attention_weights(edges: DataFrame, scores: DataFrame, slope: float = 0.2) -> DataFrame:
    """Edges weighted by a softmax over each destination's in-edges.

    ``scores`` has id, as_src, as_dst: one number per node and role.  Only these
    numbers travel; the weighted sum that follows is again a sum of rows, so it can
    be routed (numerator and denominator are both sums).
    """
    e = edges.join(scores.select(F.col("id").alias("src"), "as_src"), "src").join(scores.select(F.col("id").alias("dst"), "as_dst"), "dst")
    raw = F.col("as_src") + F.col("as_dst")
    e = e.select("src", "dst", F.when(raw > 0, raw).otherwise(raw * slope).alias("s"))
    top = e.groupBy("dst").agg(F.max("s").alias("top"))
    part = e.join(top, "dst").select("src", "dst", F.exp(F.col("s") - F.col("top")).alias("x"))
    return part.join(part.groupBy("dst").agg(F.sum("x").alias("z")), "dst").select("src", "dst", (F.col("x") / F.col("z")).alias("w"))


def attention(edges: DataFrame, blocks: DataFrame, scores: DataFrame) -> DataFrame:
    """(dst, blk, v): attention-weighted sums of the in-neighbours' blocks."""
    from .aggregate import spmm

    return spmm(attention_weights(edges, scores), blocks, weighted=True)


def gin(edges: DataFrame, blocks: DataFrame, eps: float = 0.0) -> DataFrame:
    """(id, blk, v): (1 + eps) own block plus the neighbours' sum."""
    own = blocks.select("id", "blk", F.transform("v", lambda x: x * F.lit(1.0 + eps)).alias("v"))
    nbr = edges.join(blocks, edges["src"] == blocks["id"]).select(F.col("dst").alias("id"), "blk", "v")
    return own.unionByName(nbr).groupBy("id", "blk").agg(*block_sums()).select("id", "blk", packed())
