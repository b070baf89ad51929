"""Deterministic noise that Spark and SQL engines compute alike.

A cell is named by its step, the rank of its series and a seed. An integer
congruence with squaring rounds maps the name to [0, 1); all products stay
below 2^63, so any engine with 64-bit integers gives the same number.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values of the generator.
MODULUS = 2147483647
STEP, SERIES, SEED = 7919, 104729, 1299709
FACTOR, SHIFT = 48271, 11


def _long(x: Column | int) -> Column:
    return (x if isinstance(x, Column) else F.lit(x)).cast("bigint")


def uniform(step: Column | int, series: Column | int, seed: Column | int) -> Column:
    x = (STEP * _long(step) + SERIES * _long(series) + SEED * _long(seed)) % MODULUS
    for _ in range(2):
        x = (FACTOR * x + SHIFT) % MODULUS
        x = (x * x) % MODULUS
    return ((FACTOR * x) % MODULUS) / F.lit(float(MODULUS))


def gauss(step: Column | int, series: Column | int, seed: int) -> Column:
    """Nearly normal with mean 0 and variance 1: twelve uniforms less six."""
    total = F.lit(-6.0)
    for k in range(12):
        total = total + uniform(step, series, 100 * seed + k)
    return total


def mask(step: Column | int, series: Column | int, seed: int, keep: Column | float) -> Column:
    return uniform(step, series, seed) < keep


def bernoulli(step: Column | int, series: Column | int, seed: int, p: Column) -> Column:
    return (uniform(step, series, seed) < p).cast("double")


def poisson(step: Column | int, series: Column | int, seed: int, rate: Column, most: int = 60) -> Column:
    """By inversion: the number of partial sums of the probabilities that the
    uniform exceeds (cut at ``most``)."""
    start = F.struct(F.exp(-rate).alias("p"), F.exp(-rate).alias("c"), F.lit(0).alias("k"))
    u = uniform(step, series, seed)
    grow = lambda a, i: F.struct(
        (a["p"] * rate / i).alias("p"), (a["c"] + a["p"] * rate / i).alias("c"), (a["k"] + (u > a["c"]).cast("int")).alias("k")
    )
    return F.aggregate(F.sequence(F.lit(1), F.lit(most)), start, grow, lambda a: a["k"].cast("double"))


def sql_uniform(step: str, series: str, seed: int | str) -> str:
    """The same number as an SQL expression."""
    x = f"(({STEP} * CAST({step} AS BIGINT) + {SERIES} * CAST({series} AS BIGINT) + {SEED} * CAST({seed} AS BIGINT)) % {MODULUS})"
    for _ in range(2):
        x = f"(({FACTOR} * {x} + {SHIFT}) % {MODULUS})"
        x = f"(({x} * {x}) % {MODULUS})"
    return f"((({FACTOR} * {x}) % {MODULUS}) / {float(MODULUS)})"
