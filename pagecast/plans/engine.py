"""Create a model over columns of a relation, then ask it for any step.

CREATE reads the rows twice: once for the size, span and statistics of every
series, once to lay them out as pages, in one shuffle that also puts a half
window's pages where they are added up. The pages are the stored rows; they lie
in folders by half window, so a question reads the folders of the steps it names.
Beside them lies one short row per series (``members``) with its last two pages
of values, which is all that a forecast reads; latency does not depend on the
length of the history.

Each cohort has its own first step and length: pages are counted from its first
observation, and what lies behind its last one is a forecast.
"""

from __future__ import annotations

import json
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.cluster import scratch_path
from pagecast.functions.mathfn import dot
from pagecast.operators import answers, factor, ingest, pagematrix, segments
from pagecast.plans.config import ModelConfig, half_window, settle
from pagecast.sources.modelstore import ModelStore


@dataclass
class Model:
    """What is needed to read a trained model's tables (stored as ``meta``)."""

    name: str
    config: ModelConfig
    n_series: int = 0
    steps: int = 0  # of the longest cohort
    observations: int = 0
    half_pages: int = 1
    bucket_halves: int = 1  # half windows in one folder of pages
    #: smallest and largest over the cohorts: first step, end of the full pages, end of the history
    first: tuple[int, int] = (0, 0)
    covered: tuple[int, int] = (0, 0)
    end: tuple[int, int] = (0, 0)
    trained: bool = False
    averaged: bool = True  # some cohort has no sub-model
    time: dict = field(default_factory=dict)  # column, interval, origin of a relation

    @property
    def w(self) -> int:
        return self.config.w

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @classmethod
    def from_json(cls, text: str) -> Model:
        held = json.loads(text)
        held["config"] = ModelConfig(**held["config"])
        return cls(**{k: tuple(v) if isinstance(v, list) else v for k, v in held.items()})


class Engine:
    """Models live below ``root``; an engine over the same root finds them again."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark = spark
        self.store = ModelStore(spark, root or scratch_path(spark, "models"))
        self.models: dict[str, Model] = {}

    # ------------------------------------------------------------------ create
    def create_model(self, name: str, long: DataFrame, config: ModelConfig = ModelConfig(), keep_right: bool = False, time: dict | None = None) -> Model:
        """Train on long rows (cohort, series_id, step, value) and store.

        Null and NaN values are missing. A cohort with fewer observations than
        ``config.least``, or shorter than a page, answers with averages.
        """
        store = self.store
        store.drop(name)
        self.models.pop(name, None)
        rows = long.select("cohort", "series_id", F.col("step").cast("bigint").alias("step"), F.col("value").cast("double").alias("value")).where("step is not null")
        seen = F.when(~F.isnan("value"), F.col("value"))
        step = F.when(~F.isnan("value"), F.col("step"))
        sd = F.stddev_pop(seen)
        store.save(name, "sizes", rows.groupBy("cohort", "series_id").agg(F.count(seen).alias("n"), F.min(step).alias("lo"), F.max(step).alias("hi"), F.avg(seen).alias("average"), F.var_pop(seen).alias("spread"), F.when(sd > 0, sd).otherwise(1.0).alias("deviation")))
        sizes = store.load(name, "sizes")
        store.save(name, "spans", sizes.groupBy("cohort").agg(F.min("lo").alias("first"), (F.max("hi") - F.min("lo") + 1).alias("steps"), F.sum("n").alias("count"), F.count("*").alias("n_series")).where("steps is not null"))
        spans = store.load(name, "spans")
        top = spans.agg(F.max("n_series").alias("n"), F.max("steps").alias("t"), F.sum("count").alias("c")).first()
        n, steps, count = top["n"] or 0, top["t"] or 0, top["c"] or 0
        config = settle(config, max(1, n), max(2, steps))
        w = config.w
        model = Model(name, config, n, steps, count, half_window(config, max(1, n)) // w, time=time or {})
        model.bucket_halves = max(1, 1_250_000 // max(1, model.half_pages * w * max(1, n)))
        covered = F.col("steps") - F.col("steps") % w
        fits = (F.col("count") >= config.least) & (F.col("steps") >= w)
        spans = spans.select("cohort", "first", "steps", covered.alias("covered"), fits.alias("modelled"))
        ends = spans.agg(*(f(c).alias(f"{k}_{at}") for k, f in (("lo", F.min), ("hi", F.max)) for at, c in (("first", F.col("first")), ("covered", F.col("first") + F.col("covered")), ("end", F.col("first") + F.col("steps")))), F.max(F.col("modelled").cast("int")).alias("any"), F.min(F.col("modelled").cast("int")).alias("all")).first()
        if steps:
            model.first, model.covered, model.end = ((ends[f"lo_{k}"], ends[f"hi_{k}"]) for k in ("first", "covered", "end"))
            model.trained, model.averaged = bool(ends["any"]), not ends["all"]
        scale = [F.col("average").alias("mu"), F.col("deviation").alias("sd")] if config.standardize else [F.lit(0.0).alias("mu"), F.lit(1.0).alias("sd")]
        members = sizes.join(spans, "cohort").select("cohort", "series_id", "average", "spread", F.coalesce(scale[0], F.lit(0.0)).alias("mu"), scale[1], "first", "steps", "covered", "modelled")
        if model.trained:
            placed = rows.where(seen.isNotNull()).join(spans.where("modelled"), "cohort").withColumn("rel", F.col("step") - F.col("first"))
            if config.standardize:
                placed = placed.join(members.select("cohort", "series_id", "mu", "sd"), ["cohort", "series_id"])
            else:
                placed = placed.withColumns({"mu": F.lit(0.0), "sd": F.lit(1.0)})
            pages = pagematrix.gathered(placed, w, model.half_pages, pagematrix.salts(n * model.half_pages, w), ("covered", "mu", "sd"))
            store.save(name, "pages", pages.withColumn("bucket", F.floor(F.col("half") / model.bucket_halves).cast("bigint")))
            pages = store.load(name, "pages")
            full = pages.where(F.col("page") * w < F.col("covered"))
            store.save(name, "factors", factor.train(full, model.half_pages, config))
            factors = store.load(name, "factors")
            # small tables, independent of each other
            weights = answers.weight_view(factors, config.average)
            beta = lambda m: F.max(F.when(F.col("moment") == m, F.col("beta"))).alias(f"b{m}")
            tables = {
                "weights": weights,
                "betas": weights.groupBy("cohort").agg(beta(1), beta(2)),
                "projectors": answers.projectors(factors).withColumn("idx_bucket", F.floor(F.col("half") / 1000).cast("bigint")),
                "members": self._with_recent(members, pages, w),
            }
            if keep_right:
                tables["right"] = factor.right_vectors(_scaled(full), factors, model.half_pages)
            with ThreadPoolExecutor(len(tables)) as pool:
                for job in [pool.submit(store.save, name, table, df) for table, df in tables.items()]:
                    job.result()
        else:
            store.save(name, "members", members.withColumn("recent", F.array().cast("array<double>")))
        store.forget(name, "sizes", "spans")
        store.save_meta(name, model.to_json())
        self.models[name] = model
        return model

    @staticmethod
    def _with_recent(members: DataFrame, pages: DataFrame, w: int) -> DataFrame:
        """Each series' last 2 w steps as the model sees them: scaled, missing zero."""
        span = members.select("cohort", "steps").distinct()
        low, high = F.floor((F.col("steps") - 2 * w) / w), F.floor((F.col("steps") - 1) / w)
        near = pages.join(span, "cohort").where(F.col("page").between(low, high))
        held = _scaled(near).groupBy("cohort", "series_id").agg(F.map_from_entries(F.collect_list(F.struct("page", "vals"))).alias("m"))
        zero = F.transform(F.sequence(F.lit(1), F.lit(w)), lambda _: F.lit(0.0))
        every = F.flatten(F.transform(F.sequence(low, high), lambda p: F.coalesce(F.try_element_at("m", p), zero)))
        joined = members.join(held, ["cohort", "series_id"], "left").withColumn("m", F.coalesce("m", F.create_map().cast(f"map<bigint,array<double>>")))
        recent = F.slice(every, (F.col("steps") - 2 * w - low * w + 1).cast("int"), F.lit(2 * w))
        return joined.withColumn("recent", F.when(F.col("modelled"), recent).otherwise(F.array().cast("array<double>"))).drop("m")

    def create_from_table(self, name: str, df: DataFrame, time_col: str, value_cols: list[str], interval: str, agg: str = "mean", origin: str | None = None, config: ModelConfig = ModelConfig()) -> Model:
        """One column per series of a relation with a time column. Without an
        origin, steps are counted from the interval of the earliest row."""
        if origin is None:
            origin = ingest.first_interval(df, time_col, interval)
        parts = [ingest.regularize(df.withColumn("_name", F.lit(c)), time_col, c, ["_name"], interval, agg, origin) for c in value_cols]
        long = parts[0]
        for p in parts[1:]:
            long = long.unionByName(p)
        return self.create_model(name, long, config, time={"column": time_col, "interval": interval, "origin": origin})

    def model(self, name: str) -> Model:
        """A model of this engine or of an earlier one over the same root."""
        if name not in self.models:
            held = self.store.load_meta(name)
            if held is None:
                raise ValueError(f"no model {name}")
            self.models[name] = Model.from_json(held)
        return self.models[name]

    # ----------------------------------------------------------------- predict
    def predict(self, name: str, first: int, last: int, series: list[str] | None = None, confidence: float = 95.0, method: str = "gaussian", uncertainty: bool = True) -> DataFrame:
        """cohort, series_id, step, task, mean (, sd, lower, upper) for the steps
        first..last: de-noised within a cohort's history, forecasts after it,
        nothing before it. Without ``uncertainty`` squares are not touched."""
        model = self.model(name)
        members = self.store.load(name, "members")
        if series is not None:
            members = members.where(F.col("series_id").isin(series))
        parts = []
        if model.trained:
            known = members.where("modelled")
            if first < model.covered[1] and last >= model.first[0]:
                parts.append(self._imputed(model, known, first, last, series, uncertainty).withColumn("task", F.lit("impute")))
            if last >= model.covered[0]:
                parts.append(self._tail(model, known, first, last, uncertainty))
            if last >= model.end[0]:
                parts.append(self._ahead(model, known, F.lit(last), uncertainty).where(F.col("step") >= first))
        if model.averaged or not parts:
            plain = members.where("not modelled") if model.trained else members
            more = {"variance": F.col("spread")} if uncertainty else {}
            asked = plain.withColumns({"step": F.explode(F.sequence(F.lit(first).cast("bigint"), F.lit(last).cast("bigint"))), "task": F.lit("average"), "mean": F.col("average"), **more, "mu": F.lit(0.0), "sd": F.lit(1.0)})
            parts.append(asked)
        columns = ["cohort", "series_id", "step", "task", "mean", *(["variance"] if uncertainty else []), "mu", "sd"]
        out = parts[0].select(*columns)
        for p in parts[1:]:
            out = out.unionByName(p.select(*columns))
        return self._finished(out, confidence, method, uncertainty)

    @staticmethod
    def _finished(out: DataFrame, confidence: float, method: str, uncertainty: bool, keys: tuple[str, ...] = ("cohort", "series_id", "step", "task")) -> DataFrame:
        """Back in the series' own units, with the interval."""
        mean = (F.col("mean") * F.col("sd") + F.col("mu")).alias("mean")
        if not uncertainty:
            return out.select(*keys, mean)
        scaled = out.select(*keys, mean, (F.col("variance") * F.col("sd") * F.col("sd")).alias("variance"))
        return answers.interval(scaled, confidence, method).select(*keys, "mean", "sd", "lower", "upper")

    def _pages(self, model: Model, first: int, last: int) -> DataFrame:
        """Stored pages of the folders that can hold the steps first..last."""
        per = model.half_pages * model.w * model.bucket_halves
        low, high = max(0, (first - model.first[1]) // per), (last - model.first[0]) // per
        return self.store.load(model.name, "pages").where(F.col("bucket").between(low, high))

    def _projectors(self, model: Model, first: int, last: int) -> DataFrame:
        """The vectors of the half windows that can hold the steps first..last."""
        per = model.half_pages * model.w
        low, high = max(0, (first - model.first[1]) // per), max(0, (last - model.first[0]) // per)
        held = self.store.load(model.name, "projectors")
        return held.where(F.col("idx_bucket").between(low // 1000, high // 1000) & F.col("half").between(low, high))

    def _imputed(self, model: Model, members: DataFrame, first: int, last: int, series: list[str] | None, second: bool) -> DataFrame:
        w = model.w
        lo = F.greatest(F.lit(0), F.floor((F.lit(first) - F.col("first")) / w))
        hi = F.floor((F.least(F.lit(last), F.col("first") + F.col("covered") - 1) - F.col("first")) / w)
        asked = members.select("cohort", "series_id", "first", "covered", "mu", "sd", lo.alias("lo"), hi.alias("hi")).where("lo <= hi")
        grid = asked.withColumn("page", F.explode(F.sequence("lo", "hi"))).drop("lo", "hi")
        pages = self._pages(model, first, last)
        if series is not None:
            pages = pages.where(F.col("series_id").isin(series))
        # a page without a single observation is a column of zeros
        zero = F.transform(F.sequence(F.lit(1), F.lit(w)), lambda _: F.lit(0.0))
        scaled = F.transform("raw", lambda x: F.coalesce((x - F.col("mu")) / F.col("sd"), F.lit(0.0)))
        held = grid.join(pages.select("cohort", "series_id", "page", F.col("vals").alias("raw")), ["cohort", "series_id", "page"], "left")
        held = held.withColumn("vals", F.coalesce(scaled, zero)).drop("raw")
        est = answers.denoise(held, self._projectors(model, first, last).drop("idx_bucket"), model.half_pages, second)
        cells = answers.flattened(est, w, ["cohort", "series_id", "first", "mu", "sd"], second)
        return cells.withColumn("step", F.col("step") + F.col("first")).where(F.col("step").between(first, last))

    def _weights(self, model: Model, second: bool) -> DataFrame:
        return self.store.load(model.name, "betas").select("cohort", "b1", *(["b2"] if second else []))

    def _tail(self, model: Model, members: DataFrame, first: int, last: int, second: bool) -> DataFrame:
        """The last steps fill no page: what the forecaster said one step before."""
        w = model.w
        lo, hi = F.greatest(F.lit(first), F.col("first") + F.col("covered")), F.least(F.lit(last), F.col("first") + F.col("steps") - 1)
        rows = members.select("cohort", "series_id", "first", "steps", "recent", "mu", "sd", lo.alias("lo"), hi.alias("hi")).where("lo <= hi").join(self._weights(model, second), "cohort")
        rows = rows.withColumn("step", F.explode(F.sequence("lo", "hi")))
        at = F.col("step") - F.col("first") - F.col("steps") + 2 * w  # place of the step in ``recent``
        rows = rows.withColumn("lags", F.slice("recent", (at - w + 2).cast("int"), F.lit(w - 1)))
        mean = dot(F.col("lags"), F.col("b1"))
        out = rows.withColumns({"mean": mean, "task": F.lit("impute")})
        if second:
            out = out.withColumn("variance", answers.clip(dot(F.transform("lags", lambda x: x * x), F.col("b2")) - F.col("mean") * F.col("mean")))
        return out

    def _ahead(self, model: Model, members: DataFrame, last: Column, second: bool) -> DataFrame:
        """All steps after the history up to ``last`` (a column), fed back."""
        w = model.w
        far = (last.cast("bigint") - F.col("first") - F.col("steps") + 1).alias("far")
        rows = members.select("*", far).where("far >= 1").join(self._weights(model, second), "cohort")
        lags = F.slice("recent", F.lit(w + 2), F.lit(w - 1))
        paths = [answers.roll(lags, F.col("b1"), F.col("far")).alias("m1")]
        if second:
            paths.append(answers.roll(F.transform(lags, lambda x: x * x), F.col("b2"), F.col("far")).alias("m2"))
        rolled = rows.select("cohort", "series_id", "first", "steps", "mu", "sd", *paths)
        flat = rolled.select("cohort", "series_id", "first", "steps", "mu", "sd", F.posexplode(F.arrays_zip("m1", "m2") if second else F.arrays_zip("m1")).alias("k", "p"))
        more = [answers.clip(F.col("p.m2") - F.col("p.m1") * F.col("p.m1")).alias("variance")] if second else []
        return flat.select("cohort", "series_id", (F.col("first") + F.col("steps") + F.col("k")).alias("step"), F.lit("forecast").alias("task"), F.col("p.m1").alias("mean"), "mu", "sd", *more)

    def observed(self, name: str, first: int, last: int) -> DataFrame:
        """The stored values (cohort, series_id, step, stored) of modelled cohorts."""
        model = self.model(name)
        span = self.store.load(name, "members").select("cohort", "first").distinct()
        cells = self._pages(model, first, last).join(span, "cohort").select("cohort", "series_id", "first", "page", F.posexplode("vals").alias("row", "stored")).where("stored is not null")
        return cells.select("cohort", "series_id", (F.col("first") + F.col("page") * model.w + F.col("row")).alias("step"), "stored").where(F.col("step").between(first, last))

    def compare(self, name: str, first: int, last: int) -> DataFrame:
        """The stored value beside the de-noised one."""
        out = self.predict(name, first, last)
        if not self.model(name).trained:
            return out.withColumn("stored", F.lit(None).cast("double"))
        return out.join(self.observed(name, first, last), ["cohort", "series_id", "step"], "left")

    def point(self, name: str, asks: DataFrame, confidence: float = 95.0, method: str = "gaussian") -> DataFrame:
        """Many point questions (cohort, series_id, step) at once: the past from
        stored factors by equi-joins, the rest as ``predict`` answers it.
        Repeated questions are answered once, those before a cohort's first
        step or of unknown series not at all."""
        model = self.model(name)
        asks = asks.select("cohort", "series_id", F.col("step").cast("bigint").alias("step")).distinct()
        members = self.store.load(name, "members").where("modelled")
        asked = asks.join(members.select("cohort", "series_id", "first", "covered", "steps", "mu", "sd"), ["cohort", "series_id"]).withColumn("rel", F.col("step") - F.col("first"))
        past = asked.where((F.col("rel") >= 0) & (F.col("rel") < F.col("covered"))).select("cohort", "series_id", F.col("rel").alias("step"), "first", "mu", "sd")
        found = answers.lookup(past, self.store.load(name, "factors"), self.store.load(name, "right"), model.half_pages, model.w)
        # a page without an observation has no right vector: its estimate is zero
        held = past.join(found, past.columns, "left").select(*past.columns, F.coalesce("mean", F.lit(0.0)).alias("mean"), F.coalesce("variance", F.lit(0.0)).alias("variance"))
        columns = ["cohort", "series_id", "step", "mean", "variance", "mu", "sd"]
        out = held.withColumn("step", F.col("step") + F.col("first")).select(*columns)
        tail = self._tail(model, members, model.covered[0], model.end[1], True).select(*columns)
        ends = asked.where(F.col("rel") >= F.col("steps")).groupBy("cohort", "series_id").agg(F.max("step").alias("far_step"))
        ahead = self._ahead(model, members.join(ends, ["cohort", "series_id"]), F.col("far_step"), True).select(*columns)
        out = out.unionByName(tail.unionByName(ahead).join(asks, ["cohort", "series_id", "step"], "left_semi"))
        return self._finished(out, confidence, method, True, ("cohort", "series_id", "step"))

    # ------------------------------------------------------------------- costs
    def cost_report(self, name: str) -> DataFrame:
        """Sub-models, kept numbers, retrains and updates of a model."""
        model = self.model(name)
        c = model.config
        points = segments.retrain_points(c.least, min(c.capacity, model.observations), c.growth)
        halves = -(-model.observations // (c.capacity // 2))
        later = len(segments.retrain_points(c.capacity // 2, c.capacity, c.growth)) * max(0, halves - 2)
        stored = self.store.load(name, "factors").agg(F.countDistinct("model_idx").alias("models"), F.count("*").alias("rows"), F.sum(F.size("s") * (F.col("w") + 1) + F.size("sf") * F.col("w") + F.size("weights")).alias("doubles")).first()
        row = (name, stored["models"], stored["rows"], stored["doubles"], len(points) + later, 2, model.w)
        return self.spark.createDataFrame([row], "model string, sub_models bigint, factor_rows bigint, doubles bigint, full_retrains bigint, models_per_query bigint, w int")


def _scaled(pages: DataFrame) -> DataFrame:
    """Stored pages with scaled, zero-filled values."""
    return pages.withColumn("vals", F.transform("vals", lambda x: F.coalesce((x - F.col("mu")) / F.col("sd"), F.lit(0.0))))


def describe(model: Model) -> dict:
    return {"name": model.name, "n_series": model.n_series, "steps": model.steps, "half_pages": model.half_pages, **asdict(model.config)}


def with_config(config: ModelConfig, **changes) -> ModelConfig:
    return replace(config, **changes)


def task_of(step: Column, steps: int) -> Column:
    return F.when(step < steps, "impute").otherwise("forecast")
