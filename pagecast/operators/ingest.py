"""From raw rows to regular series: cohort, series_id, step, value."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_UNITS = {"second": 1, "minute": 60, "hour": 3600, "day": 86400, "week": 604800}
_AGGREGATES = {
    "mean": F.avg, "avg": F.avg, "min": F.min, "max": F.max, "sum": F.sum, "median": F.median, "stddev": F.stddev_samp,
    "count": lambda c: F.count(c).cast("double"),
}


def seconds(interval: str) -> int:
    """'1 hour', 'day', '15 minutes' -> seconds."""
    parts = interval.lower().split()
    count, unit = (int(parts[0]), parts[1]) if len(parts) == 2 else (1, parts[0])
    unit = unit.rstrip("s")
    if unit not in _UNITS or count < 1:
        raise ValueError(f"unknown interval {interval!r}")
    return count * _UNITS[unit]


def is_number(text: str) -> bool:
    try:
        return float(text) is not None
    except ValueError:
        return False


def step_of(time: Column, origin: str, interval: str) -> Column:
    """Number of whole intervals between the origin and a time. An interval that
    is a bare number is for numeric time columns."""
    if is_number(interval):
        return F.floor((time.cast("double") - float(origin)) / float(interval)).cast("bigint")
    micros = lambda c: F.unix_micros(c.cast("timestamp_ntz").cast("timestamp"))
    return F.floor((micros(time) - micros(F.lit(origin))) / (seconds(interval) * 1_000_000)).cast("bigint")


def time_of(step: Column, origin: str, interval: str) -> Column:
    """Where a step's interval begins: timestamp, or number."""
    if is_number(interval):
        return float(origin) + step * float(interval)
    micros = F.unix_micros(F.lit(origin).cast("timestamp_ntz").cast("timestamp"))
    return F.timestamp_micros(micros + step * (seconds(interval) * 1_000_000)).cast("timestamp_ntz")


def first_interval(df: DataFrame, time_col: str, interval: str) -> str:
    """Origin that makes the earliest row's interval step 0 (of those counted
    from 1970 or zero); 1970 or zero for a table without times."""
    zero = "0" if is_number(interval) else "1970-01-01"
    lowest = df.agg(F.min(F.col(time_col)).alias("t"))
    row = lowest.select(time_of(step_of(F.col("t"), zero, interval), zero, interval).cast("string").alias("o")).first()
    return row["o"] or zero


def regularize(df: DataFrame, time_col: str, value_col: str, series_cols: list[str], interval: str, agg: str = "mean", origin: str = "1970-01-01", cohort: str = "all") -> DataFrame:
    """One value per series and interval. NaN and null values take no part; an
    interval without any is absent. Late rows simply belong to their interval."""
    value = F.col(value_col).cast("double")
    value = F.when(F.isnan(value), None).otherwise(value)
    rows = df.select(F.concat_ws("/", *(F.col(c).cast("string") for c in series_cols)).alias("series_id"), step_of(F.col(time_col), origin, interval).alias("step"), value.alias("value"), F.col(time_col).alias("_time"))
    rows = rows.where("value is not null and step is not null")
    if agg in ("first", "last"):
        out = F.min_by("value", "_time") if agg == "first" else F.max_by("value", "_time")
    else:
        out = _AGGREGATES[agg](F.col("value"))
    return rows.groupBy("series_id", "step").agg(out.alias("value")).select(F.lit(cohort).alias("cohort"), "series_id", "step", "value")


def densify(long: DataFrame, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """All steps of all series of a cohort, absent values null. The grid spans
    each cohort's own first and last step unless bounds are given."""
    span = long.groupBy("cohort").agg(F.min("step").alias("lo"), F.max("step").alias("hi"))
    if lo is not None:
        span = span.withColumn("lo", F.lit(lo).cast("bigint"))
    if hi is not None:
        span = span.withColumn("hi", F.lit(hi).cast("bigint"))
    grid = long.select("cohort", "series_id").distinct().join(span, "cohort").select("cohort", "series_id", F.explode(F.sequence("lo", "hi")).alias("step"))
    return grid.join(long, ["cohort", "series_id", "step"], "left").select("cohort", "series_id", "step", "value")


def to_long(df: DataFrame, step_col: str, cols: list[str], cohort: str = "all") -> DataFrame:
    """A wide relation (one column per series) as long rows; nulls are absent."""
    values = df.select(F.col(step_col).cast("bigint").alias("step"), *(F.col(c).cast("double").alias(c) for c in cols))
    return values.unpivot("step", cols, "series_id", "value").where("value is not null").select(F.lit(cohort).alias("cohort"), "series_id", "step", "value")


def to_wide(long: DataFrame, series: list[str]) -> DataFrame:
    return long.groupBy("step").pivot("series_id", series).agg(F.first("value"))


def statistics(long: DataFrame) -> DataFrame:
    """Mean and standard deviation of each series (deviation 1 where it is 0)."""
    sd = F.stddev_pop("value")
    return long.groupBy("cohort", "series_id").agg(F.avg("value").alias("mu"), F.when(sd > 0, sd).otherwise(1.0).alias("sd"))


def standardize(long: DataFrame, stats: DataFrame) -> DataFrame:
    return long.join(stats, ["cohort", "series_id"]).select("cohort", "series_id", "step", ((F.col("value") - F.col("mu")) / F.col("sd")).alias("value"))


def unscale(answers: DataFrame, stats: DataFrame, mean: str = "mean", deviation: str | None = None) -> DataFrame:
    """Answers on the standardised scale back in the series' own units."""
    out = answers.join(stats, ["cohort", "series_id"]).withColumn(mean, F.col(mean) * F.col("sd") + F.col("mu"))
    if deviation:
        out = out.withColumn(deviation, F.col(deviation) * F.col("sd"))
    return out.select(*answers.columns)
