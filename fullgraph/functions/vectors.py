"""Vector columns, their physical layouts, exact sums and reproducible random numbers.

Layouts of one logical table of vectors: ``array`` (id, v), ``block`` (id, blk, v
of 16 elements), ``wide`` (id, x0..), ``long`` (id, k, x).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BLOCK = 16
SCALE = 1 << 20
M31 = 1 << 31


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_scale(a: Column, s: Column | float) -> Column:
    return F.transform(a, lambda x: x * s)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_argmax(a: Column) -> Column:
    """Place of the first largest element, from 0."""
    return (F.array_position(a, F.array_max(a)) - 1).cast("int")


def fixed_point(x: Column) -> Column:
    """A whole number at scale 2^20: sums of it do not depend on their order."""
    return F.floor(x.cast("double") * SCALE).cast("long")


def mix_uniform(id_: Column, k: Column, seed: int | Column) -> Column:
    """A uniform number in [0, 1) from (id, k, seed): three steps of an integer mixer modulo 2^31."""
    step = lambda h: F.pmod(h * 1103515245 + 12345, F.lit(M31))
    h0 = F.pmod(F.pmod(id_.cast("long"), F.lit(M31)) * 1000003 + k.cast("long") * 7919 + (F.lit(seed) if isinstance(seed, int) else seed).cast("long") * 104729, F.lit(M31))
    h1 = step(h0)
    return step(h1.bitwiseXOR(F.shiftright(h1, 15))) / F.lit(float(M31))


def uniforms(ids: np.ndarray, k: int, seed: int) -> np.ndarray:
    """The same numbers for an array of ids."""
    step = lambda h: (h * 1103515245 + 12345) % M31
    h1 = step((ids.astype(np.int64) % M31 * 1000003 + (k * 7919 + seed * 104729)) % M31)
    return step(h1 ^ (h1 >> 15)) / float(M31)


def mix_uniform_sql(id_: str, k: str, seed: str) -> str:
    """The same number as SQL text (DuckDB)."""
    h0 = f"(({id_}) * 1000003 + ({k}) * 7919 + ({seed}) * 104729) % {M31}"
    h1 = f"(({h0}) * 1103515245 + 12345) % {M31}"
    return f"(((xor({h1}, ({h1}) >> 15)) * 1103515245 + 12345) % {M31}) / {float(M31)}"


def to_block(df: DataFrame, id_: str = "id", v: str = "v", size: int = BLOCK) -> DataFrame:
    """(id, blk, v of ``size`` elements); the last block is filled with zeros."""
    n = F.ceil(F.size(v) / F.lit(size)).cast("int")
    zero = F.lit(0).cast(df.schema[v].dataType.elementType)
    cells = F.transform(F.sequence(F.lit(0), n - 1), lambda b: F.struct(b.alias("blk"), F.concat(F.slice(F.col(v), b * size + 1, F.lit(size)), F.array_repeat(zero, (b + 1) * size - F.least((b + 1) * size, F.size(v)))).alias("v")))
    return df.filter(F.size(v) > 0).select(F.col(id_), F.explode(cells).alias("_c")).select(id_, F.col("_c.blk").alias("blk"), F.col("_c.v").alias("v"))


def from_block(df: DataFrame, id_: str = "id", width: int | None = None) -> DataFrame:
    out = df.groupBy(id_).agg(F.sort_array(F.collect_list(F.struct("blk", "v"))).alias("_b"))
    v = F.flatten(F.transform("_b", lambda b: b["v"]))
    return out.select(id_, (F.slice(v, 1, width) if width else v).alias("v"))


def to_long(df: DataFrame, id_: str = "id", v: str = "v") -> DataFrame:
    return df.select(F.col(id_), F.posexplode(v).alias("k", "x"))


def from_long(df: DataFrame, id_: str = "id") -> DataFrame:
    return df.groupBy(id_).agg(F.transform(F.sort_array(F.collect_list(F.struct("k", "x"))), lambda c: c["x"]).alias("v"))


def to_wide(df: DataFrame, width: int, id_: str = "id", v: str = "v") -> DataFrame:
    return df.select(F.col(id_), *[F.get(F.col(v), F.lit(i)).alias(f"x{i}") for i in range(width)])


def from_wide(df: DataFrame, width: int, id_: str = "id") -> DataFrame:
    return df.select(F.col(id_), F.array(*[F.col(f"x{i}") for i in range(width)]).alias("v"))


def block_sums(width: int = BLOCK, v: str = "v", weight: Column | None = None) -> list[Column]:
    """Sums of a block's elements, one aggregate each: they stay in generated code."""
    cell = lambda i: F.get(F.col(v), F.lit(i))
    return [F.sum(cell(i) if weight is None else cell(i) * weight).alias(f"s{i}") for i in range(width)]


def packed(width: int = BLOCK) -> Column:
    return F.array(*[F.col(f"s{i}") for i in range(width)]).alias("v")


def register(spark: SparkSession) -> None:
    """SQL names for the vector functions."""
    for body in (
        "vec_add(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x + y)",
        "vec_scale(a ARRAY<DOUBLE>, s DOUBLE) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x * s)",
        "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        "vec_argmax(a ARRAY<DOUBLE>) RETURNS INT RETURN CAST(array_position(a, array_max(a)) - 1 AS INT)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")
