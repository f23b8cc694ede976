"""Normal and t distributions and digest uniforms, as Columns and as plain numbers."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

# Coefficients of the published polynomial for the normal tail (26.2.17 of the handbook of
# mathematical functions, error below 7.5e-8) and of Acklam's rational approximation of its inverse (error 1.15e-9).
TAIL_AT, TAIL = 0.2316419, (0.319381530, -0.356563782, 1.781477937, -1.821255978, 1.330274429)
INV_A = (-3.969683028665376e01, 2.209460984245205e02, -2.759285104469687e02, 1.383577518672690e02, -3.066479806614716e01, 2.506628277459239e00)
INV_B = (-5.447609879822406e01, 1.615858368580409e02, -1.556989798598866e02, 6.680131188771972e01, -1.328068155288572e01)
INV_C = (-7.784894002430293e-03, -3.223964580411365e-01, -2.400758277161838e00, -2.549732539343734e00, 4.374664141464968e00, 2.938163982698783e00)
INV_D = (7.784695709041462e-03, 3.224671290700398e-01, 2.445134137142996e00, 3.754408661907416e00)


def _poly(x, coefficients):
    out = coefficients[0]
    for c in coefficients[1:]:
        out = out * x + c
    return out


def phi(x: Column) -> Column:
    """P(Z <= x)."""
    a = F.abs(x)
    t = 1 / (1 + TAIL_AT * a)
    tail = F.exp(-a * a / 2) / math.sqrt(2 * math.pi) * (_poly(t, TAIL[::-1]) * t)
    return F.when(x >= 0, 1 - tail).otherwise(tail)


def phi_inv(p: Column) -> Column:
    """The x with P(Z <= x) = p, for 0 < p < 1."""
    low = F.sqrt(-2 * F.log(F.least(p, 1 - p)))
    tail = _poly(low, INV_C) / _poly(low, (*INV_D, 1.0))
    q = p - 0.5
    middle = _poly(q * q, INV_A) * q / _poly(q * q, (*INV_B, 1.0))
    return F.when(p < 0.02425, tail).when(p > 1 - 0.02425, -tail).otherwise(middle)


def t_quantile(p: float, df: Column) -> Column:
    """Upper quantile of Student's t by its expansion in 1/df (error below 1e-4 from 8 degrees of freedom on)."""
    z = normal_quantile(p)
    g1, g2 = (z**3 + z) / 4, (5 * z**5 + 16 * z**3 + 3 * z) / 96
    g3, g4 = (3 * z**7 + 19 * z**5 + 17 * z**3 - 15 * z) / 384, (79 * z**9 + 776 * z**7 + 1482 * z**5 - 1920 * z**3 - 945 * z) / 92160
    return z + g1 / df + g2 / df**2 + g3 / df**3 + g4 / df**4


def t_two_sided(t: Column, df: Column) -> Column:
    """Two-sided tail by the normal deviate of equal probability (close from 10 degrees of freedom on)."""
    return 2 * (1 - phi(F.abs(t) * (1 - 1 / (4 * df)) / F.sqrt(1 + t * t / (2 * df))))


def uniform(*parts: Column | str) -> Column:
    """A number in [0, 1) from the digest of the parts joined by colons; the same in any SQL engine."""
    text = F.concat_ws(":", *[(F.col(p) if isinstance(p, str) else p).cast("string") for p in parts])
    return F.conv(F.substring(F.sha2(text, 256), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def poisson_one(u: Column) -> Column:
    """Poisson(1) count at uniform ``u``, at most 12."""
    total, out = 0.0, F.lit(12)
    steps = []
    for k in range(12):
        total += math.exp(-1) / math.factorial(k)
        steps.append((k, total))
    for k, bound in reversed(steps):
        out = F.when(u < bound, F.lit(k)).otherwise(out)
    return out


# Plain numbers, for one-row results.


def normal_cdf(x: float) -> float:
    return 0.5 * math.erfc(-x / math.sqrt(2))


def normal_quantile(p: float) -> float:
    lo, hi = -40.0, 40.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if normal_cdf(mid) < p else (lo, mid)
    return (lo + hi) / 2


def beta_regularised(a: float, b: float, x: float) -> float:
    """I_x(a, b) by its continued fraction."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    if x > (a + 1) / (a + b + 2):
        return 1 - beta_regularised(b, a, 1 - x)
    c, d = 1.0, 1 / max(1e-300, 1 - (a + b) * x / (a + 1))
    out = d
    for m in range(1, 400):
        for k in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 / (1 + k * d or 1e-300)
            c = 1 + k / c or 1e-300
            out *= c * d
        if abs(c * d - 1) < 1e-15:
            break
    return front * out / a


def t_tail(t: float, df: float) -> float:
    """Two-sided P(|T| >= |t|), exact."""
    return beta_regularised(df / 2, 0.5, df / (df + t * t))
