"""Generated series with known mean and variance, and signals planted on the
steps of real tables. All randomness is ``functions.noise``, so any SQL engine
can reproduce the numbers."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.functions import noise


def planted_mean(step: Column, rank: Column, steps: int) -> Column:
    """Four recurrences shared by all series, mixed by the series' rank."""
    turn = lambda p: 2 * math.pi * step / p
    return (
        (1 + 0.2 * rank) * F.cos(turn(24.0))
        + (0.5 - 0.1 * rank) * F.sin(turn(24.0))
        + 0.3 * (rank % 3 - 1) * F.cos(turn(7.5))
        + 0.5 * (rank % 2) * step / float(steps)
    )


def plant(grid: DataFrame, steps: int, keep: float = 1.0, sigma: float = 0.0, seed: int = 1) -> DataFrame:
    """grid(cohort, series_id, rank, step) -> long rows with ``latent`` beside
    the noisy ``value``, null where the cell is masked."""
    f = planted_mean(F.col("step"), F.col("rank"), steps)
    value = F.col("latent")
    if sigma:
        value = value + sigma * noise.gauss(F.col("step"), F.col("rank"), seed)
    out = grid.withColumn("latent", f)
    if keep < 1.0:
        value = F.when(noise.mask(F.col("step"), F.col("rank"), seed + 7, keep), value)
    return out.withColumn("value", value)


def plant_grid(grid: DataFrame, steps: int, keeps: list[float], sigmas: list[float], seed: int = 1) -> DataFrame:
    """``plant`` for every pair of a share and a deviation, a cohort each. A cell's
    noise and its place in the mask are the same at all of them and made once."""
    one = lambda p, s: F.struct(F.lit(f"p{p:g}-s{s:g}").alias("cohort"), F.lit(float(p)).alias("keep"), F.lit(float(s)).alias("sigma"))
    step, rank = F.col("step"), F.col("rank")
    cells = grid.select("series_id", "rank", "step", planted_mean(step, rank, steps).alias("latent"), noise.gauss(step, rank, seed).alias("_noise"), noise.uniform(step, rank, seed + 7).alias("_place"))
    every = cells.withColumn("_at", F.explode(F.array(*(one(p, s) for p in keeps for s in sigmas))))
    value = F.when((F.col("_at.keep") >= 1.0) | (F.col("_place") < F.col("_at.keep")), F.col("latent") + F.col("_at.sigma") * F.col("_noise"))
    return every.select(F.col("_at.cohort").alias("cohort"), "series_id", "rank", "step", "latent", value.alias("value"))


def grid(spark: SparkSession, n_series: int, steps: int, cohort: str = "all") -> DataFrame:
    cells = spark.range(n_series * steps).select((F.col("id") / steps).cast("bigint").alias("rank"), (F.col("id") % steps).alias("step"))
    return cells.select(F.lit(cohort).alias("cohort"), F.format_string("s%04d", "rank").alias("series_id"), "rank", "step")


def dynamics(step: Column, rank: Column, steps: int, kind: str) -> Column:
    """'har', 'har+trend' or 'har+ar+trend', scaled to [0.2, 0.8] roughly."""
    turn = lambda p: 2 * math.pi * step / p
    weight = 0.5 + 0.05 * (rank % 10)
    base = 0.5 + 0.15 * weight * F.cos(turn(25.0)) + 0.1 * F.sin(turn(60.0) + 0.3 * (rank % 4))
    if "trend" in kind:
        base = base + 0.15 * (step / float(steps) - 0.5)
    if "ar" in kind.split("+"):
        # a damped recurrence that starts anew every 200 steps
        base = base + 0.1 * F.exp(-0.02 * (step % 200)) * F.cos(turn(15.0))
    return base


def observed(cells: DataFrame, steps: int, kind: str, model: str, keep: float = 1.0, seed: int = 1) -> DataFrame:
    """cells(cohort, series_id, rank, step) -> + latent, latent_variance, value,
    under 'gaussian', 'poisson' or 'bernoulli' observations."""
    f = dynamics(F.col("step"), F.col("rank"), steps, kind)
    out = cells.withColumn("p", f)
    step, rank = F.col("step"), F.col("rank")
    if model == "gaussian":
        sd = 0.1 + 0.2 * F.col("p")
        out = out.withColumns({"latent": F.col("p"), "latent_variance": sd * sd}).withColumn("value", F.col("p") + sd * noise.gauss(step, rank, seed))
    elif model == "poisson":
        out = out.withColumns({"latent": 8 * F.col("p"), "latent_variance": 8 * F.col("p")}).withColumn("value", noise.poisson(step, rank, seed, F.col("latent")))
    elif model == "bernoulli":
        out = out.withColumns({"latent": F.col("p"), "latent_variance": F.col("p") * (1 - F.col("p"))}).withColumn("value", noise.bernoulli(step, rank, seed, F.col("p")))
    else:
        raise ValueError(f"unknown observation model {model}")
    if keep < 1.0:
        out = out.withColumn("value", F.when(noise.mask(step, rank, seed + 7, keep), F.col("value")))
    return out.drop("p")


def harmonics(spark: SparkSession, steps: int, seed: int = 1) -> DataFrame:
    """One long series: four cosines of fixed amplitudes and noise of sd 0.1."""
    t = F.col("step")
    f = 1.2 * F.cos(t * 0.11) - 0.9 * F.cos(t * 0.023) + 0.7 * F.cos(t * 0.31) + 0.4 * F.cos(t * 0.0071)
    return spark.range(steps).select(F.lit("all").alias("cohort"), F.lit("s0000").alias("series_id"), F.col("id").alias("step")).withColumn("latent", f).withColumn("value", f + 0.1 * noise.gauss(t, F.lit(0), seed))
