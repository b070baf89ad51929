"""Which sub-model an observation belongs to, and when a model is retrained.

Sub-model j covers the half windows j and j + 1; neighbours share a half. Half
windows are whole numbers of pages, so pages never straddle two of them.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.plans.config import ModelConfig


def retrain_points(first: int, last: int, growth: float) -> list[int]:
    """Counts floor(first * (1 + growth)^l) up to ``last``, each once."""
    out, l = [], 0
    while (point := math.floor(first * (1 + growth) ** l)) <= last:
        if not out or point > out[-1]:
            out.append(point)
        l += 1
    return out


def active_model(count: int, capacity: int) -> int:
    return max(0, 2 * count // capacity - 1)


def action(count: int, before: int, config: ModelConfig) -> tuple[str, int]:
    """What a batch that raises the count from ``before`` to ``count`` asks for:
    ('average' | 'retrain' | 'update', sub-model). A retrain is due when a
    scheduled count is crossed."""
    if count < config.least:
        return "average", 0
    model = active_model(count, config.capacity)
    if count <= config.capacity:
        points = retrain_points(config.least, config.capacity, config.growth)
        due = any(before < p <= count for p in points)
    else:
        start = model * config.capacity // 2
        base = config.capacity // 2 if config.schedule == "half_window" else config.least
        most = config.capacity if config.schedule == "half_window" else 2 * config.least
        due = active_model(before, config.capacity) != model or any(before - start < p <= count - start for p in retrain_points(base, most, config.growth))
    return ("retrain" if due else "update"), model


def schedule(spark: SparkSession, counts: DataFrame, config: ModelConfig) -> DataFrame:
    """counts(count) -> (count, model_idx, origin, n_case) by Column arithmetic."""
    c, cap = F.col("count"), F.lit(config.capacity)
    model = F.greatest(F.lit(0), F.floor(2 * c / cap) - 1).cast("bigint")
    return counts.select("count", model.alias("model_idx"), F.floor(model * cap / 2).cast("bigint").alias("origin"), F.when(c < config.least, 1).when(c <= cap, 2).otherwise(3).alias("n_case"))


def models_of_half(half: Column, last_model: Column) -> Column:
    """Sub-models that contain a half window (one or two ids)."""
    return F.filter(F.array_distinct(F.array(half - 1, half)), lambda m: (m >= 0) & (m <= last_model))


def last_model(halves: Column) -> Column:
    """The newest sub-model when ``halves`` half windows hold data."""
    return F.greatest(F.lit(0), halves - 2)


def cohorts(long: DataFrame, how: str = "all", most: int = 64, attribute: DataFrame | None = None, reference: list[str] | None = None) -> DataFrame:
    """Assign series to cohorts that share a model.

    'all': one cohort; 'each': one per series; 'hash': about ``most`` series in
    each by a hash of the id; 'attribute': (series_id, cohort) given; 'correlation':
    the reference series that a series is most correlated with on common steps.
    """
    series = long.select("series_id").distinct()
    if how == "all":
        named = series.withColumn("to", F.lit("all"))
    elif how == "each":
        named = series.withColumn("to", F.col("series_id"))
    elif how == "hash":
        groups = max(1, -(-series.count() // most))
        named = series.withColumn("to", F.pmod(F.xxhash64("series_id"), F.lit(groups)).cast("string"))
    elif how == "attribute":
        named = attribute.select("series_id", F.col("cohort").alias("to"))
    elif how == "correlation":
        # the references of a step are one row, so a step's series meet one row each
        anchor = long.where(F.col("series_id").isin(reference)).groupBy("step").agg(*(F.max(F.when(F.col("series_id") == r, F.col("value"))).alias(f"_r{k}") for k, r in enumerate(reference)))
        scored = long.join(anchor, "step", "left").groupBy("series_id").agg(*(F.coalesce(F.corr("value", f"_r{k}"), F.lit(0.0)).alias(f"_r{k}") for k in range(len(reference))))
        best = F.array_max(F.array(*(F.struct(F.col(f"_r{k}").alias("r"), F.lit(r).alias("to")) for k, r in enumerate(reference))))
        named = scored.select("series_id", best["to"].alias("to"))
    else:
        raise ValueError(f"unknown way to form cohorts: {how}")
    return long.join(named, "series_id").select(F.col("to").alias("cohort"), "series_id", "step", "value")
