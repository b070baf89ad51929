"""Accuracy and cost measures, as DataFrame expressions over result tables."""

from __future__ import annotations

import statistics as st
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEYS = ("cohort", "series_id", "step")


def nrmse(pred: DataFrame, truth: DataFrame, by: list[str] | None = None, predicted: str = "mean", true: str = "latent") -> DataFrame:
    """Root mean square error after each series is scaled by the mean and
    deviation of its true values (a constant series by 1)."""
    by = by or []
    keys = list(dict.fromkeys([*by, "cohort", "series_id"]))
    both = truth.select(*dict.fromkeys([*by, *KEYS]), F.col(true).alias("t")).join(pred.select(*dict.fromkeys([*by, *KEYS]), F.col(predicted).alias("p")), list(dict.fromkeys([*by, *KEYS])))
    sd = F.stddev_pop("t")
    series = both.groupBy(*keys).agg(F.sum((F.col("p") - F.col("t")) ** 2).alias("e"), F.count("*").alias("n"), F.when(sd > 0, sd * sd).otherwise(1.0).alias("v"))
    return series.groupBy(*by).agg(F.sqrt(F.sum(F.col("e") / F.col("v")) / F.sum("n")).alias("nrmse"))


def rmse_r2(pred: DataFrame, truth: DataFrame, by: list[str], predicted: str = "mean", true: str = "latent") -> DataFrame:
    both = truth.select(*dict.fromkeys([*by, *KEYS]), F.col(true).alias("t")).join(pred.select(*dict.fromkeys([*by, *KEYS]), F.col(predicted).alias("p")), list(dict.fromkeys([*by, *KEYS])))
    error = F.avg((F.col("p") - F.col("t")) ** 2)
    return both.groupBy(*by).agg(F.sqrt(error).alias("rmse"), (1 - error / F.nullif(F.var_pop("t"), F.lit(0.0))).alias("r2"))


def wbc(results: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Weighted Borda count: a rival's share of the error of each pair, averaged
    over rivals and experiments. results(experiment, method, nrmse, ...)."""
    by = by or []
    a, b = results.alias("a"), results.alias("b")
    pairs = a.join(b, (F.col("a.experiment") == F.col("b.experiment")) & (F.col("a.method") != F.col("b.method")))
    share = F.try_divide(F.col("b.nrmse"), F.col("a.nrmse") + F.col("b.nrmse"))
    return pairs.select(*(F.col(f"a.{c}").alias(c) for c in [*by, "method"]), F.coalesce(share, F.lit(0.5)).alias("share")).groupBy(*by, "method").agg(F.avg("share").alias("wbc"))


def mean_nrmse(results: DataFrame, by: list[str] | None = None) -> DataFrame:
    return results.groupBy(*(by or []), "method").agg(F.avg("nrmse").alias("mean_nrmse"))


def wins(results: DataFrame) -> DataFrame:
    """Per method: share of experiments won, share at least second, and the
    range of the best rival's error over its own."""
    place = F.rank().over(Window.partitionBy("experiment").orderBy("nrmse"))
    ranked = results.withColumn("place", place)
    rival = results.alias("b").join(results.alias("a"), (F.col("a.experiment") == F.col("b.experiment")) & (F.col("a.method") != F.col("b.method")))
    ratio = rival.groupBy(F.col("a.experiment").alias("experiment"), F.col("a.method").alias("method")).agg((F.min("b.nrmse") / F.nullif(F.first("a.nrmse"), F.lit(0.0))).alias("ratio"))
    out = ranked.join(ratio, ["experiment", "method"])
    share = lambda c: F.avg(c.cast("double"))
    return out.groupBy("method").agg(share(F.col("place") == 1).alias("won"), share(F.col("place") <= 2).alias("second_or_better"), F.min("ratio").alias("least_ratio"), F.max("ratio").alias("most_ratio"))


def coverage(pred: DataFrame, truth: DataFrame, value: str = "value") -> DataFrame:
    """Share of values inside the interval, and its mean width."""
    both = pred.join(truth.select(*KEYS, F.col(value).alias("y")), list(KEYS)).where("y is not null")
    return both.agg(F.avg(F.col("y").between(F.col("lower"), F.col("upper")).cast("double")).alias("coverage"), F.avg(F.col("upper") - F.col("lower")).alias("width"))


def relative_to_first(results: DataFrame, order: str, measures: list[str], by: list[str] | None = None) -> DataFrame:
    """Each measure over its value at the smallest ``order``."""
    w = Window.partitionBy(*(by or [F.lit(1)])).orderBy(order)
    return results.select(*(by or []), order, *((F.col(m) / F.first(m).over(w)).alias(m) for m in measures))


def speedups(times: DataFrame, own: str) -> DataFrame:
    """times(dataset, method, value) -> per rival the range and median of its
    value over that of ``own``."""
    base = times.where(F.col("method") == own).select("dataset", F.col("value").alias("own"))
    ratio = times.where(F.col("method") != own).join(base, "dataset").withColumn("ratio", F.col("value") / F.col("own"))
    return ratio.groupBy("method").agg(F.min("ratio").alias("least"), F.median("ratio").alias("middle"), F.max("ratio").alias("most"))


def timed(run: Callable[[], object]) -> tuple[float, object]:
    began = time.perf_counter()
    out = run()
    return time.perf_counter() - began, out


def latency(run: Callable[[], object], times: int = 5) -> dict[str, float]:
    """Milliseconds of repeated runs: median and extremes."""
    taken = [timed(run)[0] * 1000 for _ in range(times)]
    return {"median": st.median(taken), "least": min(taken), "most": max(taken)}


def relative(times: dict[str, float], base: str) -> dict[str, float]:
    """Every time over that of ``base``."""
    return {k: v / times[base] for k, v in times.items() if k != base}


def per_record(seconds: float, rows: int) -> float:
    """Microseconds per row."""
    return seconds * 1e6 / rows


def repeat(run: Callable[[int], DataFrame], times: int) -> DataFrame:
    """Union of runs with different draws, the draw's number added."""
    out = run(0).withColumn("draw", F.lit(0))
    for k in range(1, times):
        out = out.unionByName(run(k).withColumn("draw", F.lit(k)))
    return out
