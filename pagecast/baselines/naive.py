"""Average, last value and seasonal repetition: the floor for any forecaster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def _ahead(per_series: DataFrame, horizon: int, value) -> DataFrame:
    flat = per_series.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(horizon))))
    return flat.select("cohort", "series_id", (F.col("now") + F.col("k")).alias("step"), value.alias("mean"))


def _now(long: DataFrame) -> DataFrame:
    return long.where("value is not null").groupBy("cohort").agg(F.max("step").alias("now"))


def average(long: DataFrame, horizon: int) -> DataFrame:
    one = long.groupBy("cohort", "series_id").agg(F.avg("value").alias("v")).join(_now(long), "cohort")
    return _ahead(one, horizon, F.col("v"))


def last(long: DataFrame, horizon: int) -> DataFrame:
    one = long.where("value is not null").groupBy("cohort", "series_id").agg(F.max_by("value", "step").alias("v")).join(_now(long), "cohort")
    return _ahead(one, horizon, F.col("v"))


def seasonal(long: DataFrame, horizon: int, period: int) -> DataFrame:
    """The newest observed value of the same phase (0 where there is none)."""
    phase = F.pmod(F.col("step"), F.lit(period))
    by_phase = long.where("value is not null").groupBy("cohort", "series_id", phase.alias("phase")).agg(F.max_by("value", "step").alias("v"))
    one = by_phase.groupBy("cohort", "series_id").agg(F.map_from_entries(F.collect_list(F.struct("phase", "v"))).alias("m")).join(_now(long), "cohort")
    return _ahead(one, horizon, F.coalesce(F.try_element_at("m", F.pmod(F.col("now") + F.col("k"), F.lit(period)).cast("bigint")), F.lit(0.0)))
