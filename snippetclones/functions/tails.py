"""Tail probabilities of the normal, chi-square, t and F distributions, in plain Python (no SciPy), with log10 forms.

They run on the handful of rows that tests return, never on data rows.
"""

from __future__ import annotations

import math


def _gamma_q_log(a: float, x: float) -> float:
    """log of the regularised upper incomplete gamma function, by series or continued fraction."""
    if x <= 0:
        return 0.0
    scale = a * math.log(x) - x - math.lgamma(a)
    if x < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-16:
            n += 1
            term *= x / n
            total += term
        p = math.exp(scale + math.log(total))
        return math.log1p(-p) if p < 1 else -math.inf
    tiny = 1e-300
    b, c = x + 1 - a, 1 / tiny
    d = h = 1 / b
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / ((an * d + b) or tiny)
        c = (b + an / c) or tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return scale + math.log(h)


def _beta_log(a: float, b: float, x: float) -> float:
    """log of the regularised incomplete beta function by its continued fraction."""
    if x <= 0:
        return -math.inf
    if x >= 1:
        return 0.0
    front = math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)
    if x > (a + 1) / (a + b + 2):
        other = math.exp(_beta_log(b, a, 1 - x))
        return math.log1p(-other) if other < 1 else -math.inf
    tiny, c = 1e-300, 1.0
    d = h = 1 / ((1 - (a + b) * x / (a + 1)) or tiny)
    for m in range(1, 10_000):
        for k in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / ((1 + k * d) or tiny)
            c = (1 + k / c) or tiny
            h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return front + math.log(h / a)


def log_p(kind: str, statistic: float, df1: float = 0, df2: float = 0) -> float:
    """Natural log of the p-value: ``normal`` and ``t`` two-sided, ``chi2`` and ``f`` upper tail."""
    s = abs(statistic)
    if kind == "normal":
        return _gamma_q_log(0.5, s * s / 2)
    if kind == "chi2":
        return _gamma_q_log(df1 / 2, statistic / 2)
    if kind == "t":
        return _beta_log(df1 / 2, 0.5, df1 / (df1 + s * s))
    return _beta_log(df2 / 2, df1 / 2, df2 / (df2 + df1 * statistic)) if statistic > 0 else 0.0


def p_value(kind: str, statistic: float, df1: float = 0, df2: float = 0) -> float:
    return math.exp(max(-745.0, log_p(kind, statistic, df1, df2)))
