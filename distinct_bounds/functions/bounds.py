"""Half-widths and levels of the intervals, and the finite forms that the limit law bounds from above."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np

from distinct_bounds.functions import solvers
from distinct_bounds.functions.special import EULER, LN2, normal_quantile, psi, psi1

VARIANCE = math.pi**2 / 6


def levels(h_down: float, h_up: float, slots: int) -> tuple[float, float, float]:
    """Levels of the lower bound, of the upper bound and of both together (by the union bound)."""
    lower = -math.expm1(-slots * solvers.exponent_down(h_down)[0]) if h_down > 0 else 0.0
    upper = -math.expm1(-slots * solvers.exponent_up(h_up)[0]) if h_up > 0 else 0.0
    return lower, upper, lower + upper - 1


def _half(tail: float, slots: int, side: str) -> float:
    y = -math.log(tail) / slots
    return solvers.h_down(y) if side == "lower" else solvers.h_up(y)


@lru_cache(maxsize=1024)
def budget(alpha: float, slots: int, side: str = "two", split: str | tuple[float, float] = "equal") -> tuple[float, float]:
    """(h_down, h_up) of an interval of level alpha; an absent side is infinite.

    side is "lower", "upper" or "two". split of a two-sided one: "equal", "shortest" (least
    h_down + h_up), or the levels (lower, upper), whose sum must be 1 + alpha.
    """
    if not 0 < alpha < 1:
        raise ValueError("0 < alpha < 1")
    if side == "lower":
        return _half(1 - alpha, slots, "lower"), math.inf
    if side == "upper":
        return math.inf, _half(1 - alpha, slots, "upper")
    if side != "two":
        raise ValueError(f"unknown side {side}")
    if split == "equal":
        x = (1 - alpha) / 2
    elif split == "shortest":
        x = shortest_share(alpha, slots).root
    else:
        if abs(sum(split) - 1 - alpha) > 1e-9:
            raise ValueError("the sides' levels must add up to 1 + alpha")
        x = 1 - split[0]
    return _half(x, slots, "lower"), _half(1 - alpha - x, slots, "upper")


def shortest_share(alpha: float, slots: int, method: str = "halley") -> solvers.Trace:
    """Tail of the lower bound at which the interval is shortest on the log scale, from (1 - alpha) / 2 on.

    At the least width both sides' tails times their tilts are equal; that difference rises
    through zero.
    """
    beta = 1 - alpha

    def f(x):
        t1, t2 = solvers.t_down(_half(x, slots, "lower")), solvers.t_up(_half(beta - x, slots, "upper"))
        k1, k2 = psi1(1 - t1, 1), psi1(1 + t2, 1)
        s1, s2 = psi1(1 - t1, 2), psi1(1 + t2, 2)
        d1, d2 = -1 / (slots * x * t1 * k1), 1 / (slots * (beta - x) * t2 * k2)
        first = t1 + x * d1 + t2 - (beta - x) * d2
        second = d1 * (1 + (k1 - t1 * s1) / (slots * (t1 * k1) ** 2)) + d2 * (1 + (k2 + t2 * s2) / (slots * (t2 * k2) ** 2))
        return x * t1 - (beta - x) * t2, first, second

    return solvers.METHODS[method](f, beta * 1e-9, beta * (1 - 1e-9), beta / 2, 1e-12)


def log_shortest(alpha: float, slots: int) -> tuple[float, float, float]:
    """(h_down, h_up, tail of the lower bound) of the shortest interval on the log scale."""
    x = shortest_share(alpha, slots).root
    return _half(x, slots, "lower"), _half(1 - alpha - x, slots, "upper"), x


def clt_half(alpha: float, slots: int) -> float:
    """Half-width of the central-limit interval on the scale of ln 2 times the mean."""
    return normal_quantile((1 + alpha) / 2) * math.sqrt(VARIANCE / slots)


def chebyshev_half(alpha: float, slots: int) -> float:
    return math.sqrt(VARIANCE / (slots * (1 - alpha)))


def gumbel_mgf(s: float) -> float:
    """Moment generating function, at s / ln 2, of the limit of a centred slot maximum."""
    return math.exp(math.lgamma(1 - s) - EULER * s)


def gumbel_exponent(h: float, side: str) -> float:
    """Chernoff exponent from the limit law; the same as exponent_down and exponent_up."""
    t = solvers.t_down(h) if side == "lower" else solvers.t_up(h)
    s = t if side == "lower" else -t
    return h * t - math.log(gumbel_mgf(s))


_lgamma = np.vectorize(math.lgamma, otypes=[float])
#: From here on the terms beyond m are summed instead of taking the difference of large log-gammas.
MANY = 512


def log_product(m, t, sign: int):
    """Log of the product over j <= m of exp(sign t/j) / (1 + sign t/j), for any m: by log-gamma where m is
    small, and as the limit less the series of the terms beyond m where it is not and t is no more than 8."""
    m, t = np.broadcast_arrays(np.asarray(m, float), np.asarray(t, float))
    out, many = np.empty(m.shape), (m >= MANY) & (t <= 8)
    a, s = m[many], t[many]
    if a.size:
        middle = a + 0.5
        beyond = s**2 / 2 * psi(a + 1, 1) + sign * s**3 / 6 * psi(a + 1, 2) + s**4 / (12 * middle**3) - sign * s**5 / (20 * middle**4)
        out[many] = _lgamma(1 + sign * s) + sign * EULER * s - beyond
    a, s = m[~many], t[~many]
    if a.size:
        out[~many] = sign * s * (psi(a + 1) + EULER) + _lgamma(1 + sign * s) + _lgamma(a + 1) - _lgamma(a + 1 + sign * s)
    return out


def product_ratio(m, t: float, sign: int):
    """Percentage that the finite product is of its limit Gamma(1 + sign t) exp(sign G t); at most 100."""
    return 100 * np.exp(log_product(m, t, sign) - math.lgamma(1 + sign * t) - sign * EULER * t)


def mgf_slot(s: float, m: int) -> float:
    """Moment generating function of the maximum of m exponentials of rate ln 2, at s < ln 2."""
    return math.exp(math.lgamma(1 - s / LN2) + math.lgamma(m + 1) - math.lgamma(m + 1 - s / LN2)) if m else 1.0


def mgf_mean(s: float, m_matrix) -> float:
    """The same of the mean over all slots, given their numbers of objects."""
    m = np.asarray(m_matrix).ravel()
    return math.exp(sum(math.log(mgf_slot(s / len(m), int(x))) for x in m))


def mean_given(m_matrix) -> float:
    """Mean of the slot maxima given their numbers of objects."""
    m = np.asarray(m_matrix, float).ravel()
    return float((psi(m + 1) + EULER).mean() / LN2)


def best_tilts(m: np.ndarray, h: float, side: str) -> np.ndarray:
    """For each row of numbers of objects, the tilt that minimises its finite Chernoff form.

    The logarithm is convex in the tilt, so its slope is brought to zero by Newton steps that
    stay within a bracket, from the limit's tilt on. Where the slope stays negative for any
    tilt of an upper bound, the form has infimum 0 and a very large tilt is returned.
    """
    sign = -1 if side == "lower" else 1
    filled = m > 0
    harmonic = np.where(filled, psi(m + 1.0) + EULER, 0.0).sum(axis=1)
    low, high = np.zeros(len(m)), np.full(len(m), 1 - 1e-15 if side == "lower" else np.inf)
    t = np.full(len(m), solvers.t_down(h) if side == "lower" else solvers.t_up(h))
    for _ in range(100):
        at = 1 + sign * t
        beyond = m + at[:, None]
        n = filled.sum(axis=1)
        slope = sign * (harmonic - np.where(filled, psi(beyond), 0.0).sum(axis=1) + n * psi(at)) - m.shape[1] * h
        bend = n * psi(at, 1) - np.where(filled, psi(beyond, 1), 0.0).sum(axis=1)
        low, high = np.where(slope <= 0, t, low), np.where(slope > 0, t, high)
        with np.errstate(divide="ignore", invalid="ignore"):
            step = t - slope / bend
        inside = np.isfinite(step) & (step > low) & (step < high)
        new = np.minimum(1e6, np.where(inside, step, np.where(np.isfinite(high), (low + np.where(np.isfinite(high), high, 0)) / 2, 2 * t + 1)))
        done = np.abs(new - t) <= 1e-8 * new  # the form is flat there: its own error is the square
        t = new
        if done.all():
            break
    return t


def finite_tails(m, h: float, side: str) -> np.ndarray:
    """finite_tail of each row of m, a matrix of numbers of objects."""
    m = np.atleast_2d(np.asarray(m, int))
    t = best_tilts(m, h, side)
    value = log_product(m, t[:, None], -1 if side == "lower" else 1).sum(axis=1) - m.shape[1] * h * t
    return np.exp(np.minimum(0.0, value))


def finite_tail(m, h: float, side: str) -> float:
    """Chernoff bound with the finite products of the given numbers of objects, least over the tilt; never above the limit form."""
    return float(finite_tails(np.asarray(m, int).ravel(), h, side)[0])
