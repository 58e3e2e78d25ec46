"""Regularisers of a party's offset: values, proximal maps, Moreau envelopes. Columns, and NumPy twins over the last axis.

With penalty sigma and smoothing delta the kinds are
    sq        sigma delta / 2 |v|^2     mean aggregation, scaled offsets
    l2        sigma delta |v|           smoothed geometric median
    l1        sigma delta |v|_1         smoothed coordinate median
    consensus 0 at 0, else infinite     mean aggregation, no offsets
    free      0                         no tie
and every proximal map is taken with step 1/sigma.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from parley.functions.vectors import norm

KINDS = ("sq", "l2", "l1", "consensus", "free")


@dataclass(frozen=True)
class Regulariser:
    """kind "user" takes functions of arrays (any leading axes): its map with step 1/sigma, and its value."""

    kind: str
    delta: float = 0.1
    user_prox: Callable[[np.ndarray, float], np.ndarray] | None = None
    user_value: Callable[[np.ndarray], np.ndarray] | None = None

    def __post_init__(self) -> None:
        if self.kind not in (*KINDS, "user"):
            raise ValueError(f"unknown regulariser {self.kind}")
        if self.kind == "user" and self.user_prox is None:
            raise ValueError("a user's regulariser needs a proximal map")

    def prox(self, x: np.ndarray, sigma: float = 1.0) -> np.ndarray:
        return self.user_prox(x, sigma) if self.kind == "user" else prox_np(self.kind, x, self.delta)

    def value(self, v: np.ndarray, sigma: float = 1.0) -> np.ndarray:
        return self.user_value(v) if self.kind == "user" else value_np(self.kind, v, self.delta, sigma)

    @property
    def mean_centre(self) -> bool:
        """The aggregate is the mean whatever the models are."""
        return self.kind in ("sq", "consensus")


def unscaled(kind: str, sigma: float) -> Regulariser:
    """The plain |v|_1, |v| and |v|^2 as members of the scaled family."""
    return Regulariser(kind, 2 / sigma if kind == "sq" else 1 / sigma)


def prox(kind: str, x: Column, delta: float) -> Column:
    d = float(delta)
    if kind == "sq":
        return F.transform(x, lambda a: a / (1 + d))
    if kind == "l2":
        keep = F.when(norm(x) > d, 1 - d / norm(x)).otherwise(0.0)
        return F.transform(x, lambda a: a * keep)
    if kind == "l1":
        return F.transform(x, lambda a: F.signum(a) * F.greatest(F.abs(a) - d, F.lit(0.0)))
    if kind == "consensus":
        return F.transform(x, lambda a: F.lit(0.0))
    if kind == "free":
        return x
    raise ValueError(kind)


def value(kind: str, v: Column, delta: float, sigma: float) -> Column:
    k = float(sigma * delta)
    if kind == "sq":
        return F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x) * (k / 2)
    if kind == "l2":
        return norm(v) * k
    if kind == "l1":
        return F.aggregate(v, F.lit(0.0), lambda s, x: s + F.abs(x)) * k
    if kind == "consensus":
        return F.when(F.exists(v, lambda x: x != 0), F.lit(float("inf"))).otherwise(0.0)
    if kind == "free":
        return F.lit(0.0)
    raise ValueError(kind)


def _huber(r: Column, d: float) -> Column:
    return F.when(r <= d, r * r / 2).otherwise(d * r - d * d / 2)


def envelope(kind: str, x: Column, delta: float, sigma: float) -> Column:
    """Least value of Psi(v) + sigma / 2 |x - v|^2: sigma times a Huber function for the medians."""
    d, s = float(delta), float(sigma)
    if kind == "sq":
        return F.aggregate(x, F.lit(0.0), lambda t, a: t + a * a) * (s * d / (2 * (1 + d)))
    if kind == "l2":
        return _huber(norm(x), d) * s
    if kind == "l1":
        return F.aggregate(F.transform(x, lambda a: _huber(F.abs(a), d)), F.lit(0.0), lambda t, a: t + a) * s
    if kind == "consensus":
        return F.aggregate(x, F.lit(0.0), lambda t, a: t + a * a) * (s / 2)
    if kind == "free":
        return F.lit(0.0)
    raise ValueError(kind)


def prox_np(kind: str, x: np.ndarray, delta: float) -> np.ndarray:
    if kind == "sq":
        return x / (1 + delta)
    if kind == "l2":
        n = np.linalg.norm(x, axis=-1, keepdims=True)
        return x * np.where(n > delta, 1 - delta / np.where(n > 0, n, 1), 0.0)
    if kind == "l1":
        return np.sign(x) * np.maximum(np.abs(x) - delta, 0)
    if kind == "consensus":
        return np.zeros_like(x)
    if kind == "free":
        return x.copy()
    raise ValueError(kind)


def value_np(kind: str, v: np.ndarray, delta: float, sigma: float) -> np.ndarray:
    if kind == "sq":
        return sigma * delta / 2 * (v * v).sum(-1)
    if kind == "l2":
        return sigma * delta * np.linalg.norm(v, axis=-1)
    if kind == "l1":
        return sigma * delta * np.abs(v).sum(-1)
    if kind == "consensus":
        return np.where((v != 0).any(-1), np.inf, 0.0)
    return np.zeros(v.shape[:-1])


def envelope_np(kind: str, x: np.ndarray, delta: float, sigma: float) -> np.ndarray:
    v = prox_np(kind, x, delta)
    return value_np(kind, v, delta, sigma) + sigma / 2 * ((x - v) ** 2).sum(-1)
