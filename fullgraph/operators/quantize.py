"""Integer quantization of vectors for the exchange: parameters, codes, packing.

Every row (or group of rows) has its own zero point (minimum) and scale, so
nothing is agreed on globally: no action and no broadcast precede an exchange.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.vectors import mix_uniform
from ..session import ship
from . import quantiles

BITS = (2, 4, 8)


def params(df: DataFrame, bits: int, group_rows: int = 1, v: str = "v", id_: str = "id") -> DataFrame:
    """Add zp and sc: minimum and (maximum - minimum) / (2^bits - 1) of the row, or of its group of ``group_rows`` ids."""
    lo, hi = F.array_min(v).cast("double"), F.array_max(v).cast("double")
    if group_rows > 1:
        w = Window.partitionBy(F.floor(F.col(id_) / group_rows))
        lo, hi = F.min(lo).over(w), F.max(hi).over(w)
    return df.select("*", lo.alias("zp"), ((hi - lo) / F.lit(float(2**bits - 1))).alias("sc"))


def bound(value: Column, body) -> Column:
    """``body`` of a value that is computed once a row, also where projections are merged into one."""
    return F.transform(F.array(value), body).getItem(0)


def codes(v: Column, zp: Column, sc: Column, bits: int, rounding: str = "nearest", id_: Column | None = None, seed: int = 0, reciprocal: bool = False) -> Column:
    """Codes of a vector's elements; a scale of zero gives code zero."""
    def one(x: Column, k: Column, zp: Column, sc: Column) -> Column:
        t = (x.cast("double") - zp) * (1.0 / sc) if reciprocal else (x.cast("double") - zp) / sc
        up = F.lit(0.5) if rounding == "nearest" else mix_uniform(id_, k, seed)
        return F.when(sc == 0, 0).otherwise(F.least(F.greatest(F.floor(t + up), F.lit(0)), F.lit(2**bits - 1))).cast("int")

    return bound(F.struct(zp.alias("zp"), sc.alias("sc")), lambda p: F.transform(v, lambda x, k: one(x, k, p["zp"], p["sc"])))


def encode(df: DataFrame, bits: int, rounding: str = "nearest", seed: int = 0, group_rows: int = 1, reciprocal: bool = False) -> DataFrame:
    """(id, q ARRAY<INT>, zp, sc) of rows (id, v), in expressions only."""
    p = params(df, bits, group_rows)
    return p.select("id", codes(F.col("v"), F.col("zp"), F.col("sc"), bits, rounding, F.col("id"), seed, reciprocal).alias("q"), "zp", "sc")


def decode(df: DataFrame) -> DataFrame:
    return df.select("id", F.transform("q", lambda q: q * F.col("sc") + F.col("zp")).alias("v"))


def pack(q: Column, bits: int) -> Column:
    """Codes as bytes, ``8 / bits`` per byte, first code lowest."""
    per = 8 // bits

    def packed(q: Column) -> Column:
        n = F.ceil(F.size(q) / F.lit(per)).cast("int")
        code = lambda b, j: F.coalesce(F.get(q, b * per + j), F.lit(0))
        byte = lambda b: sum((F.shiftleft(code(b, j), j * bits) for j in range(per)), F.lit(0))
        hexed = F.transform(F.sequence(F.lit(0), n - 1), lambda b: F.lpad(F.hex(byte(b)), 2, "0"))
        return F.unhex(F.array_join(hexed, ""))

    return bound(q, packed)


def unpack(codes_: Column, bits: int, size: Column | int) -> Column:
    per = 8 // bits
    n = F.lit(size) if isinstance(size, int) else size

    def unpacked(text: Column) -> Column:
        byte = lambda k: F.conv(F.substr(text, (F.floor(k / per) * 2 + 1).cast("int"), F.lit(2)), 16, 10).cast("int")
        return F.transform(F.sequence(F.lit(0), n - 1), lambda k: F.pmod(F.floor(byte(k) / F.pow(F.lit(2.0), F.pmod(k, F.lit(per)) * bits)), F.lit(2**bits)).cast("int"))

    return bound(F.hex(codes_), unpacked)


# ---------------------------------------------------------------- numpy kernels (fused pass, training)


def quantize_rows(x: np.ndarray, bits: int, rng: np.random.Generator | None = None, group_rows: int = 1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(packed codes, zero points, scales) of the rows of ``x``; ``rng`` rounds stochastically, None to the nearest."""
    n, width = x.shape
    lo, hi = x.min(axis=1), x.max(axis=1)
    if group_rows > 1 and n:
        start = np.arange(0, n, group_rows)
        lo, hi = np.repeat(np.minimum.reduceat(lo, start), group_rows)[:n], np.repeat(np.maximum.reduceat(hi, start), group_rows)[:n]
    top = (1 << bits) - 1
    sc = (hi - lo) / top
    t = (x - lo[:, None]) * np.divide(1.0, sc, out=np.zeros_like(sc), where=sc > 0)[:, None]
    q = np.clip(np.floor(t + (rng.random(x.shape) if rng else 0.5)), 0, top).astype(np.uint8)
    per = 8 // bits
    padded = np.zeros((n, -(-width // per) * per), dtype=np.uint8)
    padded[:, :width] = q
    cells = padded.reshape(n, -1, per)
    out = np.zeros(cells.shape[:2], dtype=np.uint8)
    for j in range(per):
        out |= cells[:, :, j] << np.uint8(j * bits)
    return out, lo.astype(np.float32), sc.astype(np.float32)


def dequantize_rows(packed: np.ndarray, zp: np.ndarray, sc: np.ndarray, bits: int, width: int) -> np.ndarray:
    per = 8 // bits
    q = np.stack([(packed >> np.uint8(j * bits)) & np.uint8((1 << bits) - 1) for j in range(per)], axis=2).reshape(len(packed), -1)[:, :width]
    return q * sc[:, None].astype(np.float64) + zp[:, None]


HEAD = struct.Struct("<IHB")


def to_message(x: np.ndarray, bits: int, rng: np.random.Generator | None = None, group_rows: int = 1) -> tuple[bytes, int, int]:
    """(rows as bytes, bytes of data, bytes of parameters): a short head, then 32-bit floats or codes, zero points and scales."""
    head = HEAD.pack(len(x), x.shape[1], bits)
    if bits == 32:
        data = np.ascontiguousarray(x, dtype="<f4").tobytes()
        return head + data, len(data), 0
    q, zp, sc = quantize_rows(x, bits, rng, group_rows)
    params = zp[::group_rows].astype("<f4").tobytes() + sc[::group_rows].astype("<f4").tobytes()
    return head + params + q.tobytes(), q.nbytes, len(params)


def from_message(blob: bytes, group_rows: int = 1) -> np.ndarray:
    """The rows as their receiver sees them."""
    n, width, bits = HEAD.unpack_from(blob)
    at = HEAD.size
    if bits == 32:
        return np.frombuffer(blob, "<f4", n * width, at).astype(np.float64).reshape(n, width)
    groups = -(-n // group_rows)
    zp, sc = np.frombuffer(blob, "<f4", 2 * groups, at).reshape(2, groups).repeat(group_rows, axis=1)[:, :n]
    q = np.frombuffer(blob, np.uint8, offset=at + 8 * groups).reshape(n, -1)
    return dequantize_rows(q, zp, sc, bits, width)


def fused(df: DataFrame, bits: int, rounding: str = "nearest", seed: int = 0, group_rows: int = 1) -> DataFrame:
    """(id, codes, bits, zp, sc): parameters, codes and packing in one pass over Arrow batches."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x = np.asarray(b.column(1).flatten(), dtype=np.float64).reshape(b.num_rows, -1)
            rng = np.random.default_rng([seed, int(np.asarray(b.column(0))[0]) & 0x7FFFFFFF]) if rounding == "stochastic" else None
            q, zp, sc = quantize_rows(x, bits, rng, group_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in q], pa.binary()), pa.array(np.full(b.num_rows, bits, np.int32)), pa.array(zp), pa.array(sc)], names=["id", "codes", "bits", "zp", "sc"])

    return df.select("id", "v").mapInArrow(run, "id long, codes binary, bits int, zp float, sc float")


def unfused(df: DataFrame, width: int) -> DataFrame:
    """Vectors back from :func:`fused` rows."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), b.column(4).to_pylist())
            v = [dequantize_rows(np.frombuffer(c, np.uint8)[None], np.array([z]), np.array([s]), k, width)[0].tolist() for c, k, z, s in rows]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(v, pa.list_(pa.float64()))], names=["id", "v"])

    return df.select("id", "codes", "bits", "zp", "sc").mapInArrow(run, "id long, v array<double>")


def through(bits: int, rounding: str = "nearest", seed: int = 0):
    """A function for :func:`aggregate.neighbour`: messages as their receiver sees them after int transfer."""

    def run(sent: DataFrame) -> DataFrame:
        p = params(sent, bits)
        k = F.xxhash64("sp", "dp", "kind", "key", "blk")
        q = codes(F.col("v"), F.col("zp"), F.col("sc"), bits, rounding, F.pmod(k, F.lit(1 << 30)), seed)
        coded = p.select("sp", "dp", "kind", "key", "blk", pack(q, bits).alias("codes"), F.size("v").alias("size"), "zp", "sc", "n")
        back = bound(F.struct("zp", "sc"), lambda p: F.transform(unpack(F.col("codes"), bits, F.col("size")), lambda c: c * p["sc"] + p["zp"]))
        return coded.select("sp", "dp", "kind", "key", "blk", back.alias("v"), "n")

    return run


def adaptive(df: DataFrame, shares: tuple[float, float] = (0.5, 0.3)) -> DataFrame:
    """Add ``bits``: rows of small spread get 2 bits, of middling spread 4, the rest 8."""
    spread = F.array_max("v").cast("double") - F.array_min("v").cast("double")
    low, middle = quantiles.exact(df, spread, [shares[0], round(shares[0] + shares[1], 12)]) or (None, None)
    return df.select("id", "v", F.when(spread <= low, 2).when(spread <= middle, 4).otherwise(8).alias("bits"))
