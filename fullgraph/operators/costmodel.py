"""Time of an exchange with and without quantization, and the expected speedup.

Volumes are counted in elements (vectors x width); bandwidth and throughput in
bits per second; latency in seconds per pair.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FP32 = 32


def pair_seconds(elements: Column, bandwidth: float, latency: float, bits: int = FP32, params: Column | int = 0) -> Column:
    """Transfer time of one pair: payload and 32-bit parameters over the bandwidth, plus latency."""
    p = F.lit(params) if isinstance(params, int) else params
    return (elements * bits + p * FP32) / F.lit(float(bandwidth)) + F.lit(float(latency))


def slowest(pairs: DataFrame, seconds: Column) -> DataFrame:
    """The sender whose pairs take longest sets the time: (seconds)."""
    return pairs.select("sp", seconds.alias("t")).groupBy("sp").agg(F.sum("t").alias("t")).agg(F.max("t").alias("seconds"))


def exchange_time(comm: DataFrame, bandwidth: float, latency: float) -> DataFrame:
    return slowest(comm, pair_seconds(F.col("elements"), bandwidth, latency))


def prequant_seconds(elements: float, throughput: float) -> float:
    """Label injection and normalization of a part's own elements."""
    return elements * FP32 / throughput


def codec_seconds(elements: Column, bits: int, throughput: float) -> Column:
    """Quantizing (or dequantizing) reads one form and writes the other."""
    return elements * (FP32 + bits) / F.lit(float(throughput))


def quant_total(comm: DataFrame, own: DataFrame, bits: int, width: int, bandwidth: float, latency: float, throughput: float) -> DataFrame:
    """(seconds): slowest part's preparation plus, over its pairs, quantize, transfer, dequantize.

    ``own`` has sp and elements of each part; a row of ``width`` elements carries two parameters.
    """
    params = F.col("elements") / width * 2
    each = codec_seconds(F.col("elements"), bits, throughput) * 2 + pair_seconds(F.col("elements"), bandwidth, latency, bits, params)
    sent = comm.select("sp", each.alias("t")).groupBy("sp").agg(F.sum("t").alias("t"))
    mine = own.select("sp", (F.col("elements") * FP32 / F.lit(float(throughput))).alias("p"))
    return mine.join(sent, "sp", "left").agg(F.max(F.col("p") + F.coalesce("t", F.lit(0.0))).alias("seconds"))


def ratios(elements: float, params: float, throughput: float, bandwidth: float, bits: int, latency: float) -> dict[str, float]:
    """alpha, beta, gamma, delta of one pair."""
    return {"alpha": elements / params, "beta": throughput / bandwidth, "gamma": FP32 / bits, "delta": latency / (elements * bits / bandwidth)}


def speedup(alpha: float, beta: float, gamma: float, delta: float, exact: bool = True) -> float:
    """Plain over quantized exchange time; the approximation lets alpha and beta grow without bound."""
    if not exact:
        return (gamma + delta) / (1 + delta)
    # times in units of the quantized payload's transfer
    plain = gamma + delta
    quantized = 1 + delta + gamma / alpha + 2 * (1 + gamma) / beta
    return plain / quantized


def curve(comm: DataFrame, bandwidth: float, latency: float, bits: Iterable[int] = (2, 4, 8), alpha: float = 100.0, beta: float = 100.0) -> DataFrame:
    """sp, dp, bits, delta, speedup, approx of every pair: near gamma where bandwidth binds, near 1 where latency does."""
    grid = comm.select("sp", "dp", "elements", F.explode(F.array(*[F.lit(int(b)) for b in bits])).alias("bits"))
    delta = F.lit(float(latency)) / ((F.col("elements") * F.col("bits")).cast("double") / F.lit(float(bandwidth)))
    g, d = F.lit(32.0) / F.col("bits"), F.col("delta")
    exact = (g + d) / (F.lit(1.0) + d + g / F.lit(alpha) + F.lit(2.0) * (F.lit(1.0) + g) / F.lit(beta))
    return grid.select("sp", "dp", "bits", delta.alias("delta")).select("sp", "dp", "bits", "delta", exact.alias("speedup"), ((g + d) / (F.lit(1.0) + d)).alias("approx"))


def crossover_saving(parts: int, fewer: int, latency: float) -> float:
    """Latency saved per sender when ``fewer`` parts reach the volume that ``parts`` needed."""
    return (parts - fewer) * latency


def convergence_bound(first_loss: float, best_loss: float, epochs: int, rate: float, smoothness: float, noise: float) -> float:
    """Upper bound on the mean squared gradient: a term that falls with the epochs and one set by the gradient noise."""
    falling = 2 * (first_loss - best_loss) / (epochs * (2 * rate - smoothness * rate**2))
    return falling + rate * smoothness / (2 - rate * smoothness) * noise**2
