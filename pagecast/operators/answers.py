"""Means, variances and intervals for past and future steps."""

from __future__ import annotations

from statistics import NormalDist

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagecast.functions.mathfn import dot, shift_append


def projectors(models: DataFrame) -> DataFrame:
    """(cohort, half, m1, m2): the left vectors and shares of the one or two
    sub-models that contain a half window, for both moments side by side."""
    spread = models.select("cohort", "model_idx", "moment", "share", "u", F.explode(F.array(F.col("model_idx"), F.col("model_idx") + 1)).alias("half"))
    of = F.struct("model_idx", "share", "u")
    pick = lambda m: F.array_sort(F.collect_list(F.when(F.col("moment") == m, of))).alias(f"m{m}")
    return spread.groupBy("cohort", "half").agg(pick(1), pick(2))


def _projected(z: Column, listed: Column) -> Column:
    """z projected on the left vectors of each listed sub-model, on average."""

    def one(model: Column) -> Column:
        inside = F.transform(model["u"], lambda u: dot(u, z) / model["share"])
        scaled = F.zip_with(model["u"], inside, lambda u, c: F.transform(u, lambda x: x * c))
        return F.aggregate(scaled, F.transform(z, lambda _: F.lit(0.0)), lambda total, u: F.zip_with(total, u, lambda a, b: a + b))

    each = F.transform(listed, one)
    total = F.aggregate(F.slice(each, 2, 1), F.element_at(each, 1), lambda a, b: F.zip_with(a, b, lambda x, y: x + y))
    return F.transform(total, lambda x: x / F.size(listed))


def denoise(pages: DataFrame, projecting: DataFrame, half_pages: int, second: bool = True) -> DataFrame:
    """The columns of ``pages`` (cohort, page, vals...) and est1 (, est2): each
    page's values (and squares) projected on the left vectors of the sub-models
    that cover it, averaged over them. A page is its own right vector, so
    nothing of the size of the data is stored for this; one equi-join by half
    window with ``projectors`` brings the vectors, and everything else is an
    expression of the row.
    """
    half = F.floor(F.col("page") / half_pages).cast("bigint")
    both = pages.withColumn("half", half).join(projecting, ["cohort", "half"])
    squares = F.transform("vals", lambda x: x * x)
    est = {"est1": _projected(F.col("vals"), F.col("m1"))} | ({"est2": _projected(squares, F.col("m2"))} if second else {})
    return both.withColumns(est).drop("m1", "m2", "half")


def clip(variance: Column) -> Column:
    return F.greatest(F.lit(0.0), variance)


def flattened(pages: DataFrame, w: int, keys: list[str], second: bool = True) -> DataFrame:
    """(keys, page, step, mean(, variance)) from est1 and est2: variance is the
    second moment minus the squared mean, never below zero."""
    zipped = F.arrays_zip("est1", "est2") if second else F.arrays_zip("est1")
    cells = pages.select(*keys, "page", F.posexplode(zipped).alias("row", "e"))
    mean = F.col("e.est1")
    more = [clip(F.col("e.est2") - mean * mean).alias("variance")] if second else []
    return cells.select(*keys, (F.col("page") * w + F.col("row")).alias("step"), mean.alias("mean"), *more)


def impute(pages: DataFrame, models: DataFrame, half_pages: int, w: int) -> DataFrame:
    """(cohort, series_id, step, mean, variance) of every step that has a page."""
    return flattened(denoise(pages, projectors(models), half_pages), w, ["cohort", "series_id"])


def lookup(asks: DataFrame, models: DataFrame, right: DataFrame, half_pages: int, w: int) -> DataFrame:
    """Point answers from stored factors: asks(cohort, series_id, step, ...) meet
    one row of the left vectors and one of the right, per covering sub-model, by
    equi-joins; the products are summed and averaged over the sub-models."""
    from pagecast.operators.factor import to_models

    page = F.floor(F.col("step") / w).cast("bigint")
    placed = to_models(asks.withColumn("page", page).withColumn("half", F.floor(page / half_pages).cast("bigint")))
    both = placed.join(right, ["cohort", "model_idx", "series_id", "page"]).join(models.select("cohort", "model_idx", "moment", "u", "s"), ["cohort", "model_idx", "moment"])
    row = (F.col("step") % w + 1).cast("int")
    left = F.transform("u", lambda u: F.element_at(u, row))
    value = dot(F.zip_with(left, "s", lambda a, b: a * b), F.col("v"))
    pick = lambda m: F.avg(F.when(F.col("moment") == m, F.col("x")))
    wide = both.select(*asks.columns, "moment", value.alias("x")).groupBy(*asks.columns).agg(pick(1).alias("mean"), pick(2).alias("second"))
    return wide.select(*asks.columns, "mean", clip(F.col("second") - F.col("mean") * F.col("mean")).alias("variance"))


def weight_view(models: DataFrame, average: int) -> DataFrame:
    """Weights averaged over each cohort's newest sub-models, oldest lag first."""
    recent = Window.partitionBy("cohort", "moment").orderBy(F.desc("model_idx"))
    kept = models.select("cohort", "moment", "weights", F.dense_rank().over(recent).alias("k")).where(F.col("k") <= average)
    flat = kept.select("cohort", "moment", F.posexplode("weights").alias("at", "x")).groupBy("cohort", "moment", "at").agg(F.avg("x").alias("x"), F.count("*").alias("n"))
    return flat.groupBy("cohort", "moment").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda e: e["x"]).alias("beta"), F.max("n").alias("n_models"))


def history(long: DataFrame, w: int, at: DataFrame) -> DataFrame:
    """(cohort, series_id, now, lags, lags2): the last w - 1 steps before and at
    ``at``(cohort, now) per series, absent ones zero, of values and squares."""
    recent = long.join(at, "cohort").where((F.col("step") <= F.col("now")) & (F.col("step") > F.col("now") - (w - 1)) & F.col("value").isNotNull())
    every = long.select("cohort", "series_id").distinct().join(at, "cohort")
    held = recent.groupBy("cohort", "series_id").agg(F.map_from_entries(F.collect_list(F.struct((F.col("step") - F.col("now") + (w - 2)).cast("int"), "value"))).alias("m"))
    lags = F.transform(F.sequence(F.lit(0), F.lit(w - 2)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0)))
    out = every.join(held, ["cohort", "series_id"], "left").withColumn("m", F.coalesce("m", F.create_map().cast("map<int,double>")))
    return out.select("cohort", "series_id", "now", lags.alias("lags"), F.transform(lags, lambda x: x * x).alias("lags2"))


def roll(lags: Column, beta: Column, horizon: int | Column) -> Column:
    """Predicted values of the next steps (at least one), each fed back, as an array."""
    start = F.struct(lags.alias("l"), F.array().cast("array<double>").alias("out"))

    def step(state: Column, _: Column) -> Column:
        value = dot(state["l"], beta)
        return F.struct(shift_append(state["l"], value).alias("l"), F.concat(state["out"], F.array(value)).alias("out"))

    return F.aggregate(F.sequence(F.lit(1).cast("bigint"), (F.lit(horizon) if isinstance(horizon, int) else horizon).cast("bigint")), start, step, lambda s: s["out"])


def forecast(long: DataFrame, weights: DataFrame, w: int, horizon: int, at: DataFrame | None = None) -> DataFrame:
    """(cohort, series_id, step, mean, variance) of the next ``horizon`` steps."""
    if at is None:
        at = long.where("value is not null").groupBy("cohort").agg(F.max("step").alias("now"))
    rows = history(long, w, at)
    pick = lambda m, name: weights.where(F.col("moment") == m).select("cohort", F.col("beta").alias(name))
    both = rows.join(pick(1, "b1"), "cohort").join(pick(2, "b2"), "cohort")
    paths = both.select("cohort", "series_id", "now", F.arrays_zip(roll(F.col("lags"), F.col("b1"), horizon).alias("mean"), roll(F.col("lags2"), F.col("b2"), horizon).alias("second")).alias("p"))
    flat = paths.select("cohort", "series_id", "now", F.posexplode("p").alias("k", "p"))
    return flat.select("cohort", "series_id", (F.col("now") + F.col("k") + 1).alias("step"), F.col("p.mean").alias("mean"), clip(F.col("p.second") - F.col("p.mean") * F.col("p.mean")).alias("variance"))


def one_step_ahead(long: DataFrame, weights: DataFrame, w: int, first: int) -> DataFrame:
    """Forecasts of every step from ``first`` on, each from the observed steps
    before it (long must be dense; absent values count as zero)."""
    run = Window.partitionBy("cohort", "series_id").orderBy("step").rowsBetween(-(w - 1), -1)
    filled = F.coalesce(F.col("value"), F.lit(0.0))
    rows = long.withColumn("lags", F.collect_list(filled).over(run)).where((F.col("step") >= first) & (F.size("lags") == w - 1))
    pick = lambda m, name: weights.where(F.col("moment") == m).select("cohort", F.col("beta").alias(name))
    both = rows.join(pick(1, "b1"), "cohort").join(pick(2, "b2"), "cohort")
    mean = dot(F.col("lags"), F.col("b1"))
    second = dot(F.transform("lags", lambda x: x * x), F.col("b2"))
    return both.select("cohort", "series_id", "step", mean.alias("mean"), clip(second - mean * mean).alias("variance"))


def interval(answers: DataFrame, confidence: float, method: str = "gaussian") -> DataFrame:
    """Adds sd, lower, upper. 'gaussian' uses the normal quantile, 'chebyshev'
    needs no distribution and is wider."""
    if not 0 < confidence < 100:
        raise ValueError("confidence lies between 0 and 100, both excluded")
    if method == "gaussian":
        factor = NormalDist().inv_cdf(0.5 + confidence / 200)
    elif method == "chebyshev":
        factor = (1 - confidence / 100) ** -0.5
    else:
        raise ValueError(f"unknown interval method {method}")
    sd = F.sqrt(clip(F.col("variance")))
    return answers.withColumns({"sd": sd, "lower": F.col("mean") - sd * factor, "upper": F.col("mean") + sd * factor})


def running_mean(long: DataFrame) -> DataFrame:
    """The answer of a model with too few observations: the average so far."""
    past = Window.partitionBy("cohort", "series_id").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return long.select("cohort", "series_id", "step", F.avg("value").over(past).alias("mean"))


def poisson_check(latent: DataFrame, tolerance: float = 0.15) -> DataFrame:
    """Does the estimated variance follow the estimated mean? Rows (cohort,
    ratio, share, verdict)."""
    ratio = F.avg("variance") / F.nullif(F.avg("mean"), F.lit(0.0))
    near = F.avg((F.abs(F.col("variance") - F.col("mean")) <= tolerance * F.abs(F.col("mean"))).cast("double"))
    out = latent.groupBy("cohort").agg(ratio.alias("ratio"), near.alias("share"))
    return out.withColumn("verdict", F.when(F.abs(F.col("ratio") - 1) <= tolerance, "poisson").otherwise("other"))
