"""Normal distribution and vector helpers as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A published rational approximation of the normal quantile
#: (relative error below 1.2e-9), centre and tails.
_A = (-3.969683028665376e1, 2.209460984245205e2, -2.759285104469687e2, 1.383577518672690e2, -3.066479806614716e1, 2.506628277459239)
_B = (-5.447609879822406e1, 1.615858368580409e2, -1.556989798598866e2, 6.680131188771972e1, -1.328068155288572e1, 1.0)
_C = (-7.784894002430293e-3, -3.223964580411365e-1, -2.400758277161838, -2.549732539343734, 4.374664141464968, 2.938163982698783)
_D = (7.784695709041462e-3, 3.224671290700398e-1, 2.445134137142996, 3.754408661907416, 1.0)
_TAIL = 0.02425


def _polynomial(x: Column, coefficients: tuple[float, ...]) -> Column:
    total = F.lit(coefficients[0])
    for c in coefficients[1:]:
        total = total * x + F.lit(c)
    return total


def probit(p: Column) -> Column:
    """Quantile of the standard normal distribution; null outside (0, 1)."""
    q = p - 0.5
    r = q * q
    centre = _polynomial(r, _A) * q / _polynomial(r, _B)
    low = F.sqrt(-2.0 * F.log(p))
    high = F.sqrt(-2.0 * F.log(1.0 - p))
    tail = lambda t: _polynomial(t, _C) / _polynomial(t, _D)
    return F.when((p <= 0) | (p >= 1), F.lit(None)).when(p < _TAIL, tail(low)).when(p > 1 - _TAIL, -tail(high)).otherwise(centre)


def normal_cdf(x: Column) -> Column:
    """Standard normal distribution function by a published rational
    approximation of the error function (absolute error below 1.5e-7)."""
    z = F.abs(x) / F.sqrt(F.lit(2.0))
    t = 1.0 / (1.0 + 0.3275911 * z)
    tail = _polynomial(t, (1.061405429, -1.453152027, 1.421413741, -0.284496736, 0.254829592)) * t * F.exp(-z * z)
    return F.when(x >= 0, 1.0 - tail / 2.0).otherwise(tail / 2.0)


def dot(a: Column, b: Column) -> Column:
    """Sum of products of two arrays of equal length."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda total, x: total + x)


def axpy(scale: Column, a: Column, b: Column) -> Column:
    """scale * a + b, element by element."""
    return F.zip_with(a, b, lambda x, y: scale * x + y)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def shift_append(a: Column, value: Column) -> Column:
    """Drop the first element and append a value."""
    return F.concat(F.slice(a, F.lit(2), F.size(a) - 1), F.array(value))
