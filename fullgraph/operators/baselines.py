"""The methods that training is compared with, as settings of the same engine."""

from __future__ import annotations

from dataclasses import replace

from .train import TrainConfig


def plain(cfg: TrainConfig) -> TrainConfig:
    """The engine without cover routing and quantization: every source once, 32 bits."""
    return replace(cfg, route="post", bits=32, lp=False)


def complete(cfg: TrainConfig) -> TrainConfig:
    """Everything: cover routing, 2-bit messages, normalization, label propagation."""
    return replace(cfg, route="hybrid", bits=2, lp=True, layer_norm=True)


def unreduced(cfg: TrainConfig) -> TrainConfig:
    """Synchronous exchange at full precision with a vector per cut edge."""
    return replace(cfg, route="edge", bits=32, lp=False)


def delayed(cfg: TrainConfig, every: int = 5) -> TrainConfig:
    """Remote sums are exchanged every ``every`` epochs and reused between; one is the synchronous method."""
    return replace(cfg, route="post", bits=32, refresh_every=every)


def stale(cfg: TrainConfig) -> TrainConfig:
    """An epoch computes with the remote sums and gradients of the epoch before; the exchange is off the critical path."""
    return replace(cfg, route="post", bits=32, stale_lag=1)


def boundary_sample(cfg: TrainConfig, rate: float = 0.5) -> TrainConfig:
    """A random share of the boundary vectors is sent each epoch, scaled up by its inverse."""
    return replace(cfg, route="post", bits=32, boundary_rate=rate)


def adaptive_bits(cfg: TrainConfig) -> TrainConfig:
    """Every message chooses 2, 4 or 8 bits from the spread of its rows."""
    return replace(cfg, route="post", bits=8, adaptive=True, lp=False)


def pre_only(cfg: TrainConfig) -> TrainConfig:
    return replace(cfg, route="pre", bits=32)


def post_only(cfg: TrainConfig) -> TrainConfig:
    return replace(cfg, route="post", bits=32)


def hybrid(cfg: TrainConfig, bits: int = 32) -> TrainConfig:
    return replace(cfg, route="hybrid", bits=bits)
