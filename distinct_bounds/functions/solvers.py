"""Roots of the engine's equations: certified brackets, and iterations of cubic, quadratic and linear rate."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from distinct_bounds.functions.special import EULER, hp, psi1


@dataclass(frozen=True)
class Trace:
    """A root, how it was reached and the bracket it was searched in."""

    root: float
    iterations: int
    evaluations: int
    bracket: tuple[float, float]


def _safeguarded(f: Callable, low: float, high: float, start: float | None, step: Callable, tolerance: float, most: int) -> Trace:
    """Iterate from start; an iterate that leaves the bracket is replaced by the bracket's middle.

    f(x) returns value and derivatives and must increase over the bracket.
    """
    first, x = (low, high), low + (high - low) / 2 if start is None else min(max(start, low), high)
    for i in range(1, most + 1):
        value = f(x)
        if value[0] == 0:
            return Trace(x, i, i, first)
        if value[0] > 0:
            high = min(high, x)
        else:
            low = max(low, x)
        new = step(x, *value)
        if not (math.isfinite(new) and low <= new <= high):
            new = low + (high - low) / 2
        if abs(new - x) <= tolerance * max(abs(new), 1e-300) or high - low <= 4e-16 * abs(high):
            return Trace(new, i, i, first)
        x = new
    return Trace(x, most, most, first)


def halley(f, low, high, start=None, tolerance=1e-13, most=200) -> Trace:
    """Cubic rate; f returns value, first and second derivative."""

    def step(x, v, d, dd):
        below = 2 * d * d - v * dd
        return x - 2 * v * d / below if below else math.nan

    return _safeguarded(f, low, high, start, step, tolerance, most)


def newton(f, low, high, start=None, tolerance=1e-13, most=200) -> Trace:
    """Quadratic rate; the same f."""
    return _safeguarded(f, low, high, start, lambda x, v, d, dd: x - v / d if d else math.nan, tolerance, most)


def bisect(f, low, high, start=None, tolerance=1e-13, most=400) -> Trace:
    """Linear rate; only the sign of f's value is used."""
    first = (low, high)
    for i in range(1, most + 1):
        x = low + (high - low) / 2
        if f(x)[0] > 0:
            high = x
        else:
            low = x
        if high - low <= tolerance * max(abs(high), 1e-300):
            break
    return Trace(low + (high - low) / 2, i, i, first)


METHODS = {"halley": halley, "newton": newton, "bisect": bisect}


def psi_bracket(y: float) -> tuple[float, float]:
    """Holds the x with digamma(x) = y: exponential bounds, sharpened for x below 1."""
    low, high = math.exp(y), math.exp(y) + 0.5
    if y + EULER < 0:
        low, high = max(low, 1 / (1 - EULER - y)), min(-1 / (y + EULER), 1.0)
    return low, high


def psi_inverse_trace(y: float, method: str = "halley") -> Trace:
    low, high = psi_bracket(y)
    start = high if y + EULER < 0 else low + 0.5 * (high - low)
    return METHODS[method](lambda x: (psi1(x) - y, psi1(x, 1), psi1(x, 2)), low, high, start)


def psi_inverse(y: float) -> float:
    return psi_inverse_trace(y).root


def hp_bracket(y: float, p: float) -> tuple[float, float]:
    """Holds the x with hp(x, p) = y; the sharper lower end only where its condition and sign hold."""
    a = math.exp(y - EULER)
    high, low = a / p - 0.5, max(0.0, a - 1)
    if p < 1:
        d = math.log1p(-p)
        sharp = a / p - math.e + 1 / d
        if a > p * (0.5 - 1 / ((math.e - 1) * d)) and sharp > low and float(hp(sharp, p)[0]) <= y:
            low = sharp
    return low, max(high, low, 0.0)


def hp_inverse_trace(y: float, p: float, method: str = "halley") -> Trace:
    if y <= 0:
        return Trace(0.0, 0, 0, (0.0, 0.0))
    low, high = hp_bracket(y, p)
    return METHODS[method](lambda x: tuple(float(hp(x, p, k)[0]) - (y if k == 0 else 0) for k in range(3)), low, high, high)


def hp_inverse(y: float, p: float) -> float:
    return hp_inverse_trace(y, p).root


def hp_inverse_vec(y, p: float, tolerance: float = 1e-13, most: int = 100) -> np.ndarray:
    """hp_inverse of many values at once: the cubic step for all that have not settled yet. NaN stays NaN."""
    y = np.array(y, float, ndmin=1)
    a = np.exp(np.minimum(y, 700.0) - EULER)
    low, high = np.maximum(0.0, a - 1), np.maximum(a / p - 0.5, np.maximum(0.0, a - 1))
    x = high.copy()
    x[~(y > 0)] = 0.0
    x[np.isnan(y)] = np.nan
    todo = np.flatnonzero(y > 0)
    for _ in range(most):
        if not len(todo):
            break
        v, d, dd = hp(x[todo], p) - y[todo], hp(x[todo], p, 1), hp(x[todo], p, 2)
        high[todo] = np.where(v > 0, np.minimum(high[todo], x[todo]), high[todo])
        low[todo] = np.where(v <= 0, np.maximum(low[todo], x[todo]), low[todo])
        with np.errstate(all="ignore"):
            new = x[todo] - 2 * v * d / (2 * d * d - v * dd)
        bad = ~np.isfinite(new) | (new < low[todo]) | (new > high[todo])
        new[bad] = (low[todo] + high[todo])[bad] / 2
        moved = np.abs(new - x[todo]) > tolerance * np.maximum(np.abs(new), 1e-300)
        x[todo] = new
        todo = todo[moved & (high[todo] - low[todo] > 4e-16 * high[todo])]
    return x


def t_up(h: float) -> float:
    """Where the exponent of the upper side is largest."""
    return psi_inverse(h - EULER) - 1


def t_down(h: float) -> float:
    return 1 - psi_inverse(-h - EULER)


def exponent_up(h: float) -> tuple[float, float, float]:
    """Chernoff exponent of one slot for falling h below the mean, with its derivatives in h."""
    t = t_up(h)
    return (h - EULER) * t - math.lgamma(1 + t), t, 1 / psi1(1 + t, 1)


def exponent_down(h: float) -> tuple[float, float, float]:
    """The same for rising h above the mean, which bounds the truth from below."""
    t = t_down(h)
    return (h + EULER) * t - math.lgamma(1 - t), t, 1 / psi1(1 - t, 1)


def h_up_bracket(y: float) -> tuple[float, float]:
    if y < 3:
        return math.sqrt(y / 50), math.pi * math.sqrt(2 * y / 3)
    return 2 / 3 * (math.log(y + 0.5) + EULER), 2 * (math.log(4 * y / 3 + 1) + EULER)


def h_down_bracket(y: float) -> tuple[float, float]:
    a = (3 - math.pi**2 / 6) / 2
    b = y / 2 + 1 - a
    z = (math.sqrt(b * b + 4 * a) - b) / (2 * a)
    c = math.sqrt(max(0.0, 1 - z))
    return max(-math.log1p(-c) - EULER if c < 1 else 0.0, math.pi**2 / 6 * c), 2 * math.sqrt((y + 1) ** 2 - 1)


def _inverse(exponent, bracket, y: float, method: str) -> Trace:
    if y <= 0:
        return Trace(0.0, 0, 0, (0.0, 0.0))
    low, high = bracket(y)

    def f(h):
        value, first, second = exponent(h)
        return value - y, first, second

    return METHODS[method](f, low, high, math.sqrt(low * high))


def h_up_trace(y: float, method: str = "halley") -> Trace:
    return _inverse(exponent_up, h_up_bracket, y, method)


def h_down_trace(y: float, method: str = "halley") -> Trace:
    return _inverse(exponent_down, h_down_bracket, y, method)


def h_up(y: float) -> float:
    return h_up_trace(y).root


def h_down(y: float) -> float:
    return h_down_trace(y).root


def _least(f: Callable[[float], float], low: float, high: float) -> float:
    """The least value of a function with one valley, by golden sections."""
    ratio = (math.sqrt(5) - 1) / 2
    a, b = low, high
    c, d = b - ratio * (b - a), a + ratio * (b - a)
    fc, fd = f(c), f(d)
    for _ in range(200):
        if fc < fd:
            b, d, fd = d, c, fc
            c = b - ratio * (b - a)
            fc = f(c)
        else:
            a, c, fc = c, d, fd
            d = a + ratio * (b - a)
            fd = f(d)
    return min(fc, fd)


def h_up_dual(y: float) -> float:
    """h_up without nested roots: the largest exponent equals y where the least such slope is taken."""
    return EULER + _least(lambda s: (y + math.lgamma(1 + math.exp(s))) / math.exp(s), -25.0, 12.0)


def h_down_dual(y: float) -> float:
    def slope(s):  # t = 1 / (1 + exp(-s)), and 1 - t without cancellation
        t, rest = 1 / (1 + math.exp(-s)), 1 / (1 + math.exp(s))
        return (y + math.lgamma(rest)) / t

    return -EULER + _least(slope, -25.0, 30.0)
