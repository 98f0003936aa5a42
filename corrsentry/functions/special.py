"""Gamma-family functions on numpy arrays, and the beta density built from them."""

from __future__ import annotations

import math

import numpy as np

PSI_ONE = -0.5772156649015329


def _shifted(x: np.ndarray, least: float = 8.0) -> tuple[np.ndarray, np.ndarray]:
    """(x moved up by whole steps to at least `least`, steps)."""
    steps = np.maximum(0, np.ceil(least - x)).astype(int)
    return x + steps, steps


def _carried(x: np.ndarray, steps: np.ndarray, term) -> np.ndarray:  # noqa: ANN001
    out = np.zeros_like(x)
    for j in range(int(steps.max(initial=0))):
        out = out + np.where(j < steps, term(x + j), 0.0)
    return out


def lgamma(x) -> np.ndarray:  # noqa: ANN001
    x = np.asarray(x, float)
    y, steps = _shifted(x)
    z = 1 / (y * y)
    series = (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + (1 / 12 - z * (1 / 360 - z * (1 / 1260 - z / 1680))) / y
    return series - _carried(x, steps, np.log)


def digamma(x) -> np.ndarray:  # noqa: ANN001
    x = np.asarray(x, float)
    y, steps = _shifted(x)
    z = 1 / (y * y)
    return np.log(y) - 0.5 / y - z * (1 / 12 - z * (1 / 120 - z * (1 / 252 - z / 240))) - _carried(x, steps, lambda v: 1 / v)


def trigamma(x) -> np.ndarray:  # noqa: ANN001
    x = np.asarray(x, float)
    y, steps = _shifted(x)
    z = 1 / (y * y)
    return 1 / y + z / 2 + z / y * (1 / 6 - z * (1 / 30 - z * (1 / 42 - z / 30))) + _carried(x, steps, lambda v: 1 / (v * v))


def inv_digamma(y) -> np.ndarray:  # noqa: ANN001
    """x with digamma(x) = y, by Newton's method from a start that is close on either branch."""
    y = np.asarray(y, float)
    x = np.where(y >= -2.22, np.exp(np.minimum(y, 700)) + 0.5, -1 / (np.minimum(y, -1.0) - PSI_ONE))
    for _ in range(7):
        x = np.maximum(x - (digamma(x) - y) / trigamma(x), x / 10)
    return x


def log_beta(a, b) -> np.ndarray:  # noqa: ANN001
    return lgamma(a) + lgamma(b) - lgamma(np.asarray(a, float) + b)


def beta_logpdf(x, a, b, clamp: float = 1e-3) -> np.ndarray:  # noqa: ANN001
    x = np.clip(np.asarray(x, float), clamp, 1 - clamp)
    return (np.asarray(a, float) - 1) * np.log(x) + (np.asarray(b, float) - 1) * np.log1p(-x) - log_beta(a, b)


# ---- the same for single numbers, without array overhead, for fits in inner loops


def digamma1(x: float) -> float:
    out = 0.0
    while x < 8.0:
        out -= 1 / x
        x += 1
    z = 1 / (x * x)
    return out + math.log(x) - 0.5 / x - z * (1 / 12 - z * (1 / 120 - z * (1 / 252 - z / 240)))


def trigamma1(x: float) -> float:
    out = 0.0
    while x < 8.0:
        out += 1 / (x * x)
        x += 1
    z = 1 / (x * x)
    return out + 1 / x + z / 2 + z / x * (1 / 6 - z * (1 / 30 - z * (1 / 42 - z / 30)))


def inv_digamma1(y: float) -> float:
    x = math.exp(min(y, 700.0)) + 0.5 if y >= -2.22 else -1 / (y - PSI_ONE)
    for _ in range(7):
        step = (digamma1(x) - y) / trigamma1(x)
        x = max(x - step, x / 10)
        if abs(step) < 1e-12 * x:
            break
    return x


def log_beta1(a: float, b: float) -> float:
    return math.lgamma(a) + math.lgamma(b) - math.lgamma(a + b)
