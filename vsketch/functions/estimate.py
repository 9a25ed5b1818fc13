"""Cardinality from registers: bias constants and estimators as Column arithmetic over two sums.

All estimators need only the number of nonzero registers and the sum of 2**-rank over them: absent
registers are zeros and add 2**0 each, so sparse and dense sketches give the same answer."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .constants import BETA
from .spec import SketchSpec

HOW = ("raw", "linear", "beta", "large", "geo")


@lru_cache
def alpha(r: int) -> float:
    """Bias constant of the harmonic mean, by quadrature over s = log2((2 + u) / (1 + u))."""
    x, w = np.polynomial.legendre.leggauss(400)
    edges = np.linspace(0, 1, 41)
    s = np.concatenate([(b - a) / 2 * x + (a + b) / 2 for a, b in zip(edges, edges[1:], strict=False)])
    w = np.concatenate([(b - a) / 2 * w for a, b in zip(edges, edges[1:], strict=False)])
    slope = math.log(2) * np.exp2(s) / np.expm1(s * math.log(2)) ** 2
    return float(1 / (r * (w * s**r * slope).sum()))


def std_error(p: int) -> float:
    return 1.04 / math.sqrt(1 << p)


def beta_polynomial(z: np.ndarray, weights) -> np.ndarray:
    log = np.log(np.asarray(z, float) + 1)
    out = np.zeros_like(log)
    for w in reversed(weights[1:]):
        out = (out + w) * log
    return out + weights[0] * np.asarray(z, float)


def fit_beta(p: int, trials: int = 100, seed: int = 1, spread: float = 6.0) -> tuple[float, ...]:
    """Weights of the bias polynomial: linear in z and of degree 7 in log(z + 1), least squares on simulated sketches."""
    rng, r, a = np.random.default_rng(seed), 1 << p, alpha(1 << p)
    most = int(spread * r)
    marks = np.unique(np.concatenate([np.geomspace(1, most, 60).astype(int), np.linspace(1, most, 60).astype(int)]))
    rows, goals, weight = [], [], []
    for _ in range(trials):
        index = rng.integers(0, r, most)
        rank = rng.geometric(0.5, most)
        regs, at = np.zeros(r, np.int64), 0
        for n in marks:
            np.maximum.at(regs, index[at:n], rank[at:n])
            at = n
            z = int((regs == 0).sum())
            if z == 0:
                continue
            log = math.log(z + 1)
            total = np.exp2(-regs.astype(float)).sum()
            rows.append([z, *(log**i for i in range(1, 8))])
            goals.append(a * r * (r - z) / n - total)
            weight.append(n / (a * r * (r - z)))  # error relative to the estimate's denominator
    x, y, w = np.array(rows), np.array(goals), np.array(weight)
    scale = np.abs(x).max(0)
    sol = np.linalg.lstsq(x / scale * w[:, None], y * w, rcond=None)[0] / scale
    return tuple(float(f"{v:.12g}") for v in sol)


def estimate(total: Column, filled: Column, spec: SketchSpec, how: str = "beta") -> Column:
    """total: sum of 2**-rank over nonzero registers, filled: their number (0 and 0: empty, estimate 0)."""
    r = float(spec.r)
    zeros = F.lit(r) - filled
    raw = F.lit(alpha(spec.r) * r * r) / (total + zeros)
    if how == "raw":
        return raw
    if how in ("linear", "large"):
        small = F.when((raw <= 2.5 * r) & (zeros > 0), F.lit(r) * F.log(F.lit(r) / zeros)).otherwise(raw)
        if how == "large":
            space = float(2**spec.width)
            small = F.when(small > space / 30, -F.lit(space) * F.log1p(-small / F.lit(space))).otherwise(small)
        return small
    if how == "beta":
        log = F.log(zeros + 1)
        weights = BETA[spec.p]
        bias = F.lit(0.0)
        for w in reversed(weights[1:]):
            bias = (bias + F.lit(w)) * log
        bias = bias + F.lit(weights[0]) * zeros
        return F.lit(alpha(spec.r) * r) * (F.lit(r) - zeros) / (bias + total + zeros)
    raise ValueError(f"unknown estimator {how}; {HOW} are known (geo has its own function)")


#: Bias constant of the geometric-mean estimator for many registers.
GEO = 0.39701


def estimate_geo(rank_sum: Column, spec: SketchSpec) -> Column:
    """From the mean of all ranks (zeros included): r times 2**mean times a constant."""
    return F.lit(GEO * spec.r) * F.pow(F.lit(2.0), rank_sum / F.lit(float(spec.r)))


_POWERS = np.exp2(-np.arange(256.0))


def estimate_array(regs: np.ndarray, how: str = "beta") -> np.ndarray:
    """The same for dense registers in NumPy, one row a sketch."""
    r = regs.shape[1]
    zeros, total = (regs == 0).sum(1).astype(float), _POWERS[regs].sum(1)
    if how == "beta":
        return alpha(r) * r * (r - zeros) / (beta_polynomial(zeros, BETA[r.bit_length() - 1]) + total)
    raw = alpha(r) * r * r / total
    if how == "raw":
        return raw
    return np.where((raw <= 2.5 * r) & (zeros > 0), r * np.log(r / np.maximum(zeros, 1)), raw)
