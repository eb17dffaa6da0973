"""Special functions, on numpy arrays: polygamma, the modified harmonic function, incomplete gamma and beta."""

from __future__ import annotations

import math

import numpy as np

EULER = 0.5772156649015329
LN2 = math.log(2.0)
#: Below this product of p and x the modified harmonic function is integrated; above it, its tail is summed.
SMALL = 1.0
GONE = 40.0
_NODES, _WEIGHTS = np.polynomial.legendre.leggauss(16)

# Coefficients of the asymptotic series in even powers of 1/x.
PSI = (-1 / 12, 1 / 120, -1 / 252, 1 / 240, -1 / 132, 691 / 32760, -1 / 12)
PSI1 = (1 / 6, -1 / 30, 1 / 42, -1 / 30, 5 / 66, -691 / 2730, 7 / 6)
PSI2 = (-1 / 2, 1 / 6, -1 / 6, 3 / 10, -5 / 6, 691 / 210, -35 / 2)


def psi(x, order: int = 0):
    """Digamma, trigamma or tetragamma of positive x: recurrence up to 12, then the asymptotic series."""
    x = np.array(x, float, ndmin=1)
    shape, x, total = x.shape, x.ravel().copy(), 0.0
    total = np.zeros_like(x)
    for _ in range(12):
        low = x < 12
        if not low.any():
            break
        v = x[low]
        total[low] += (-1 / v, 1 / v**2, -2 / v**3)[order]
        x[low] = v + 1
    inverse = 1 / x
    square = inverse * inverse
    series, power = np.zeros_like(x), np.ones_like(x)
    for c in (PSI, PSI1, PSI2)[order]:
        power = power * square
        series += c * power
    if order == 0:
        total += np.log(x) - inverse / 2 + series
    elif order == 1:
        total += inverse + square / 2 + series * inverse
    else:
        total += -square - square * inverse + series * square
    return total.reshape(shape)


def psi1(x: float, order: int = 0) -> float:
    return float(psi(x, order)[0])


def lerch(z: float, s: int, a, terms: int | None = None):
    """Sum of z**n / (a + n)**s for 0 <= z < 1, to double precision."""
    a = np.array(a, float, ndmin=1)
    n = terms or max(1, int(math.ceil(-40 / math.log(z)))) if z > 0 else 1
    total = np.zeros_like(a)
    for at in range(0, n, 4096):
        k = np.arange(at, min(n, at + 4096))
        total += (z**k / (a[..., None] + k) ** s).sum(axis=-1)
    return total


def _quadrature(x: np.ndarray, p: float, order: int) -> np.ndarray:
    """Over s with u = p exp(-s): the integrand is 1 - (1-u)**x or its derivatives in x, and falls like exp(-s)."""
    out = np.empty_like(x)
    for i, v in enumerate(x):
        upto = math.log1p(p * v) + 42
        panels = max(1, int(math.ceil(upto)))
        s = ((np.arange(panels)[:, None] + (_NODES + 1) / 2) * (upto / panels)).ravel()
        log = np.log1p(-p * np.exp(-s))
        f = (-np.expm1(v * log), -log * np.exp(v * log), -log * log * np.exp(v * log))[order]
        out[i] = (f * np.tile(_WEIGHTS, panels)).sum() * upto / panels / 2
    return out


def hp_quad(x, p: float, order: int = 0):
    """The modified harmonic function, or a derivative of it, by integration; for p < 1."""
    x = np.array(x, float, ndmin=1)
    return _quadrature(x.ravel(), p, order).reshape(x.shape)


def hp_tail(x, p: float, s: int = 1):
    """(1-p)**(x+1) times the transcendent of order s at x+1: what is left of the closed form."""
    x = np.array(x, float, ndmin=1)
    out = np.zeros_like(x)
    some = p * x < GONE
    if p < 1 and some.any():
        out[some] = (1 - p) ** (x[some] + 1) * lerch(1 - p, s, x[some] + 1)
    return out


def e1_bound(x):
    """Upper bound of the exponential integral E1 at x > 0."""
    x = np.array(x, float, ndmin=1)
    return np.exp(-x) * np.log1p(1 / x)


def _closed(x: np.ndarray, p: float, order: int) -> np.ndarray:
    log = math.log1p(-p) if p < 1 else 0.0
    if order == 0:
        return psi(x + 1) + EULER + math.log(p) + hp_tail(x, p)
    if order == 1:
        return psi(x + 1, 1) + log * hp_tail(x, p) - hp_tail(x, p, 2)
    return psi(x + 1, 2) + log * log * hp_tail(x, p) - 2 * log * hp_tail(x, p, 2) + 2 * hp_tail(x, p, 3)


def hp(x, p: float, order: int = 0):
    """Expected maximum, times ln 2, of what reaches one of 1/p rows from x objects; order 1 and 2: derivatives.

    The closed form where its tail is gone or short; integration where it would cancel or
    take too many terms. p = 1 gives the harmonic numbers.
    """
    if not 0 < p <= 1:
        raise ValueError("0 < p <= 1")
    x = np.array(x, float, ndmin=1)
    if (x < 0).any():
        raise ValueError("x >= 0")
    flat = x.ravel()
    if p == 1:
        return (psi(flat + 1, order) + (EULER if order == 0 else 0)).reshape(x.shape)
    out, closed = np.empty_like(flat), (p * flat >= GONE) | ((p * flat >= SMALL) & (p >= 1 / 64))
    if closed.any():
        out[closed] = _closed(flat[closed], p, order)
    if not closed.all():
        out[~closed] = _quadrature(flat[~closed], p, order)
    return out.reshape(x.shape)


def gamma_product(t: float, terms: int, sign: int) -> float:
    """The first factors of Gamma(1 + sign t) exp(sign G t): exp(sign t/j) / (1 + sign t/j)."""
    j = np.arange(1, terms + 1)
    return float(np.exp((sign * t / j - np.log1p(sign * t / j)).sum()))


def gamma_upper(a: float, x: float) -> float:
    """Regularised upper incomplete gamma: the tail of a chi-square with 2a degrees of freedom at 2x."""
    if x <= 0:
        return 1.0
    front = math.exp(a * math.log(x) - x - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        k = a
        while abs(term) > 1e-17 * abs(total):
            k += 1
            term *= x / k
            total += term
        return 1 - front * total
    b, c = x + 1 - a, 1e300
    d = 1 / b
    h = d
    for i in range(1, 10_000):
        n = -i * (i - a)
        b += 2
        d = 1 / (n * d + b or 1e-300)
        c = b + n / c or 1e-300
        h *= c * d
        if abs(c * d - 1) < 1e-16:
            break
    return front * h


def beta_regular(x: float, a: float, b: float) -> float:
    """Regularised incomplete beta, by its continued fraction."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - beta_regular(1 - x, b, a)
    front = math.exp(a * math.log(x) + b * math.log1p(-x) + math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b)) / a
    c, d = 1.0, 1 / (1 - (a + b) * x / (a + 1))
    h = d
    for m in range(1, 10_000):
        for n in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + n * d or 1e-300)
            c = 1 + n / c or 1e-300
            h *= c * d
        if abs(c * d - 1) < 1e-16:
            break
    return front * h


def chi_square_tail(statistic: float, df: float) -> float:
    return gamma_upper(df / 2, statistic / 2)


def f_tail(statistic: float, df1: float, df2: float) -> float:
    return beta_regular(df2 / (df2 + df1 * statistic), df2 / 2, df1 / 2)


def normal_quantile(q: float) -> float:
    """The standard normal quantile, by Newton steps on math.erfc."""
    x = 0.0
    for _ in range(100):
        step = (0.5 * math.erfc(-x / math.sqrt(2)) - q) * math.sqrt(2 * math.pi) * math.exp(min(x * x / 2, 600))
        x -= max(-1.0, min(1.0, step))
        if abs(step) < 1e-15 * max(1, abs(x)):
            break
    return x
