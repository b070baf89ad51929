"""The experiment workloads, on series of the given tables and generated ones.

The tables hold no predictable signal of their own, so accuracy is measured on
a signal planted on their steps and gaps. Every grid point is a cohort of its
own: all models of a workload train in one shuffle.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.baselines import learners
from pagecast.cluster import Written, ship
from pagecast.functions import noise
from pagecast.operators import answers, factor, ingest, pagematrix
from pagecast.plans import metrics
from pagecast.plans.config import ModelConfig, half_window, settle
from pagecast.plans.engine import Engine
from pagecast.sources import series, synth

#: The four data sets and the survey's grid: shares of cells kept, deviations of the added noise.
DATASETS = ("orders", "lineitem", "events", "synthetic")
KEEPS, SIGMAS = (1.0, 0.8, 0.5), (0.0, 0.1, 0.2, 0.5, 1.0)

_UNION = lambda a, b: a.unionByName(b)


def cells_of(long: DataFrame, steps: int) -> DataFrame:
    """The observed (series, step) cells of a table's series, with ranks."""
    return series.with_rank(long.select("cohort", "series_id", "step")).where(F.col("step") < steps)


def datasets(spark: SparkSession, sf_dir: str) -> dict[str, tuple[DataFrame, int]]:
    """Cells and number of steps of the four data sets."""
    return {
        "orders": (cells_of(series.orders_by_priority(spark, sf_dir), 2400), 2400),
        "lineitem": (cells_of(series.lineitem_by_flags(spark, sf_dir), 2400), 2400),
        "events": (cells_of(series.events_by_type(spark, sf_dir), 720), 720),
        "synthetic": (synth.grid(spark, 20, 1000), 1000),
    }


def _as_cohort(df: DataFrame, name: str) -> DataFrame:
    return df.withColumn("cohort", F.lit(name))


def trained(long: DataFrame, n_series: int, steps: int, config: ModelConfig = ModelConfig()) -> tuple[DataFrame, DataFrame, ModelConfig, int]:
    """Models of all cohorts at once: (pages, factors, settled config, half)."""
    config = settle(config, n_series, steps)
    half = half_window(config, n_series) // config.w
    pages = pagematrix.build(long, config.w, steps=steps)
    return pages, factor.train(pages, half, config), config, half


def _by_experiment(scored: DataFrame, dataset: str, method: str) -> DataFrame:
    return scored.select(F.concat_ws("/", F.lit(dataset), "cohort").alias("experiment"), F.lit(dataset).alias("dataset"), F.lit(method).alias("method"), F.col("nrmse"))


def _rescaled(long: DataFrame) -> tuple[DataFrame, DataFrame]:
    stats = ingest.statistics(long.where("value is not null"))
    return ingest.standardize(long, stats), stats


def _on_each(spark: SparkSession, sf_dir: str, only: tuple[str, ...], keeps, sigmas, experiment: Callable) -> DataFrame:
    """The rows that ``experiment(name, noisy, steps, n)`` gives for each data
    set, written. ``noisy`` has a cohort per grid point, and lies in files."""

    def one(name: str, cells: DataFrame, steps: int) -> DataFrame:
        noisy = Written(synth.plant_grid(cells, steps, list(keeps), list(sigmas)), f"noisy-{name}")
        n = noisy.df.select("series_id").distinct().count()
        found = Written(experiment(name, noisy.df, steps, n).coalesce(1), f"errors-{name}").df
        noisy.drop()
        return found

    ship(spark)  # once, before the threads
    asked = [(name, *of) for name, of in datasets(spark, sf_dir).items() if name in only]
    with ThreadPoolExecutor(max(1, len(asked))) as pool:
        return reduce(_UNION, [job.result() for job in [pool.submit(one, *a) for a in asked]])


def _together(parts: list[Callable[[], DataFrame]]) -> DataFrame:
    """Short results of independent jobs, each written by itself."""
    with ThreadPoolExecutor(len(parts)) as pool:
        jobs = [pool.submit(lambda part: Written(part().coalesce(1), "errors").df, part) for part in parts]
        return reduce(_UNION, [job.result() for job in jobs])


def mean_imputation(spark: SparkSession, sf_dir: str, keeps=KEEPS, sigmas=SIGMAS, only: tuple[str, ...] = DATASETS, rivals: bool = True) -> DataFrame:
    """De-noised values of masked, noisy series against the factorisation."""

    def experiment(name: str, noisy: DataFrame, steps: int, n: int) -> DataFrame:
        scaled, stats = (Written(df, f"{label}-{name}").df for label, df in zip(("scaled", "stats"), _rescaled(noisy)))
        config = settle(ModelConfig(), n, steps)
        half = half_window(config, n) // config.w
        # the sums of the pages serve both ways to fill
        pages = Written(pagematrix.build(scaled, config.w, steps=steps), f"pages-{name}").df
        gram = Written(factor.gram_rows(pages, half), f"gram-{name}").df

        def own(fill: str, method: str) -> DataFrame:
            models = Written(factor.solve(gram, replace(config, fill=fill)), f"models-{name}").df
            est = ingest.unscale(answers.impute(pages, models, half, config.w), stats)
            return _by_experiment(metrics.nrmse(est, noisy, ["cohort"]), name, method)

        def rival() -> DataFrame:
            est = learners.grouped(scaled, ["cohort"], steps, lambda y: {"mean": learners.trmf_impute(y)}, 0)
            return _by_experiment(metrics.nrmse(ingest.unscale(est, stats), noisy, ["cohort"]), name, "factorisation")

        parts = [lambda: own("zero", "pages"), lambda: own("inverse_rate", "pages/rate"), *([rival] if rivals else [])]
        return _together(parts)

    return _on_each(spark, sf_dir, only, keeps, sigmas, experiment)


def mean_forecasting(spark: SparkSession, sf_dir: str, keeps=KEEPS, sigmas=SIGMAS, only: tuple[str, ...] = DATASETS, horizon: int = 24) -> DataFrame:
    """The first steps after the history, five methods and the plain average."""
    from pagecast.baselines.naive import average

    def experiment(name: str, noisy: DataFrame, steps: int, n: int) -> DataFrame:
        cut = steps - steps // 10
        truth = noisy.where(F.col("step") >= cut)
        scaled, stats = (Written(df, f"{label}-{name}").df for label, df in zip(("scaled", "stats"), _rescaled(noisy.where(F.col("step") < cut))))

        def own() -> DataFrame:
            pages, models, cfg, _ = trained(scaled, n, cut, ModelConfig(fill="inverse_rate"))
            weights = Written(answers.weight_view(models, cfg.average), f"weights-{name}").df
            now = scaled.select("cohort").distinct().withColumn("now", F.lit(cut - 1).cast("bigint"))
            return answers.forecast(scaled, weights, cfg.w, horizon, now)

        kernels = {
            "factorisation": lambda y: {"mean": learners.trmf_forecast(y, horizon)},
            "additive": lambda y: {"mean": learners.additive_fit_forecast(y, horizon)},
            "recurrent": lambda y: {"mean": learners.recurrent_forecast(y, horizon)},
            "probabilistic": lambda y: dict(zip(("mean", "variance"), learners.probabilistic_forecast(y, horizon))),
        }
        found = {"pages": own, "average": lambda: average(scaled, horizon)} | {m: lambda k=k: learners.grouped(scaled, ["cohort"], cut, k, cut) for m, k in kernels.items()}

        def error(method: str) -> DataFrame:
            pred = ingest.unscale(found[method]().select("cohort", "series_id", "step", "mean"), stats)
            return _by_experiment(metrics.nrmse(pred, truth, ["cohort"]), name, method)

        return _together([lambda m=m: error(m) for m in found])

    return _on_each(spark, sf_dir, only, keeps, sigmas, experiment)


FAMILIES = [(kind, model) for kind in ("har", "har+trend", "har+ar+trend") for model in ("gaussian", "poisson", "bernoulli")]


def _families(spark: SparkSession, keeps, n: int, steps: int) -> DataFrame:
    cells = synth.grid(spark, n, steps)
    return reduce(_UNION, (_as_cohort(synth.observed(cells, steps, kind, model, p), f"{model}/{kind}/p{p:g}") for kind, model in FAMILIES for p in keeps))


def variance_imputation(spark: SparkSession, sf_dir: str, keeps=KEEPS, n: int = 10, steps: int = 600, rivals: bool = True) -> DataFrame:
    """Time-varying variance of nine families, against two factorisations."""
    noisy = _families(spark, keeps, n, steps).persist()
    pages, models, cfg, half = trained(noisy, n, steps, ModelConfig(fill="inverse_rate"))
    est = answers.impute(pages, models, half, cfg.w)
    out = [_by_experiment(_error(est, noisy), "families", "pages")]
    if rivals:
        rival = learners.grouped(noisy, ["cohort"], steps, lambda y: {"variance": learners.trmf_variance(y), "mean": y * 0}, 0)
        out.append(_by_experiment(_error(rival, noisy), "families", "factorisation"))
    return reduce(_UNION, out)


def _error(pred: DataFrame, truth: DataFrame) -> DataFrame:
    return metrics.nrmse(pred, truth, ["cohort"], "variance", "latent_variance")


def variance_forecasting(spark: SparkSession, sf_dir: str, keeps=KEEPS, n: int = 10, steps: int = 600, horizon: int = 20) -> DataFrame:
    noisy = _families(spark, keeps, n, steps).persist()
    cut = steps - horizon
    past, truth = noisy.where(F.col("step") < cut), noisy.where(F.col("step") >= cut)
    pages, models, cfg, _ = trained(past, n, cut, ModelConfig(fill="inverse_rate"))
    now = past.select("cohort").distinct().withColumn("now", F.lit(cut - 1).cast("bigint"))
    own = answers.forecast(past, answers.weight_view(models, cfg.average), cfg.w, horizon, now)
    rival = learners.grouped(past, ["cohort"], cut, lambda y: dict(zip(("mean", "variance"), learners.probabilistic_forecast(y, horizon))), cut)
    return _by_experiment(_error(own, truth), "families", "pages").unionByName(_by_experiment(_error(rival, truth), "families", "probabilistic"))


def noise_kinds(spark: SparkSession, sf_dir: str, n: int = 10, steps: int = 2000, ahead: int = 100) -> DataFrame:
    """One latent path seen as floats, booleans and integers: RMSE and R2 of the
    de-noised past and of one-step forecasts of the last ``ahead`` steps."""
    cells = synth.grid(spark, n, steps)
    noisy = reduce(_UNION, (_as_cohort(synth.observed(cells, steps, "har+trend", m), m) for m in ("gaussian", "bernoulli", "poisson"))).persist()
    pages, models, cfg, half = trained(noisy, n, steps)
    est = answers.impute(pages, models, half, cfg.w)
    past = metrics.rmse_r2(est, noisy, ["cohort"]).withColumn("task", F.lit("impute"))
    cut = steps - ahead
    _, models, cfg, _ = trained(noisy.where(F.col("step") < cut), n, cut)
    one = answers.one_step_ahead(noisy.select("cohort", "series_id", "step", "value"), answers.weight_view(models, cfg.average), cfg.w, cut)
    future = metrics.rmse_r2(one, noisy.where(F.col("step") >= cut), ["cohort"]).withColumn("task", F.lit("forecast"))
    return past.unionByName(future).withColumnRenamed("cohort", "kind")


def poisson_or_not(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly event counts follow a Poisson law, returned items in blocks do not."""
    counts = _as_cohort(ingest.densify(series.event_counts(spark, sf_dir), 0, 719).fillna(0.0, ["value"]), "events")
    blocks = _as_cohort(series.returned_in_blocks(spark, sf_dir), "returned")
    parts = []
    for long, steps in ((counts, 720), (blocks, blocks.count())):
        pages, models, cfg, half = trained(long, 1, steps)
        parts.append(answers.poisson_check(answers.impute(pages, models, half, cfg.w)))
    return parts[0].unionByName(parts[1])


def _draws(spark: SparkSession, n: int, draws: int, steps: int) -> DataFrame:
    """``draws`` cohorts of n series each, of a thousand that share their
    dynamics; every series of a draw is another one."""
    cells = spark.range(draws * n * steps).select((F.col("id") % steps).alias("step"), (F.col("id") / steps % n).cast("bigint").alias("k"), (F.col("id") / (steps * n)).cast("bigint").alias("draw"))
    rank = (F.col("draw") * 7919 + F.col("k") * 389) % 1000
    return cells.select(F.concat(F.lit("d"), "draw").alias("cohort"), F.format_string("s%04d", "k").alias("series_id"), (rank % 10).alias("rank"), (rank + F.col("draw") * 1000).alias("own"), "step")


def series_count(spark: SparkSession, sf_dir: str, counts=(1, 10, 40, 80, 160, 400), steps: int = 300, sigma: float = 0.5, draws: int = 50, most_series: int = 4000, costs: bool = False) -> DataFrame:
    """One-step forecast error of a series as more related series share its
    model, over ``draws`` choices of them, or as many as have ``most_series``
    series together; with ``costs`` also the seconds of
    training and the milliseconds of a point forecast, all relative to the
    smallest count."""
    out = []
    cut = steps - steps // 10
    for n in counts:
        cells = _draws(spark, n, max(1, min(draws, most_series // n)), steps)
        latent = synth.planted_mean(F.col("step"), F.col("rank"), steps)
        noisy = cells.withColumn("latent", latent).withColumn("value", F.col("latent") + sigma * noise.gauss(F.col("step"), F.col("own"), 1))
        pages, models, cfg, _ = trained(noisy.where(F.col("step") < cut), n, cut)
        first = noisy.where("series_id = 's0000'")
        est = answers.one_step_ahead(first.select("cohort", "series_id", "step", "value"), answers.weight_view(models, cfg.average), cfg.w, cut)
        row = metrics.nrmse(est, first.where(F.col("step") >= cut)).withColumn("n_series", F.lit(n))
        if costs:
            long = noisy.where("cohort = 'd0'").persist()
            long.count()
            engine = Engine(spark)
            taken, _ = metrics.timed(lambda: engine.create_model("m", long))
            asked = metrics.latency(lambda: engine.predict("m", steps, steps, ["s0000"]).collect(), 3)["median"]
            long.unpersist()
            row = row.withColumns({"train_s": F.lit(taken), "latency_ms": F.lit(asked)})
        out.append(row)
    return metrics.relative_to_first(reduce(_UNION, out), "n_series", ["nrmse", *(["train_s", "latency_ms"] if costs else [])])


def capacity_growth(spark: SparkSession, sf_dir: str, capacities=(600, 6000, 60000), growths=(0.2, 0.5, 1.0), batches: int = 2) -> DataFrame:
    """A signal planted on the line items in key order arrives in a bulk load
    and then in batches, for each capacity and growth: what the schedule asks
    for over a thousand batches, and of the models trained here the seconds for
    the bulk load and for a batch, the milliseconds of a forecast and its error."""
    from pagecast.operators.segments import action
    from pagecast.streaming.models import IncrementalModel

    rows = series.table(spark, sf_dir, "lineitem").count()
    long = synth.harmonics(spark, rows).persist()
    bulk, size = rows - rows // 10, max(1, rows // 10 // max(1, batches))
    ends = [bulk + k * size for k in range(batches + 1)]
    out, trained = [], {}
    for capacity in capacities:
        for growth in growths:
            config = settle(ModelConfig(capacity=capacity, growth=growth), 1, min(rows, capacity))
            done = {"average": 0, "retrain": 0, "update": 0}
            before, batch = 0, max(1, rows // 1000)
            while before < rows:
                count = min(rows, before + batch)
                done[action(count, before, config)[0]] += 1
                before = count
            # growth says no more than what each append does: where that is the same, so are the models
            asked = (capacity, *(action(count, before, config) for before, count in zip([0, *ends], ends)))
            if asked not in trained:
                model = IncrementalModel(spark, 1, config, update="columns")
                load, *each = [metrics.timed(lambda: model.append(long.where((F.col("step") >= lo) & (F.col("step") < hi))))[0] for lo, hi in zip([0, *ends], ends)]
                past = long.where((F.col("step") >= ends[-1] - 2 * config.w) & (F.col("step") < ends[-1])).select("cohort", "series_id", "step", "value")
                ask, said = lambda: answers.forecast(past, model.weights(), config.w, 10), []
                milliseconds = metrics.latency(lambda: said.append(ask().collect()), 2)["least"]
                truth = synth.harmonics(spark, ends[-1] + 10).where(F.col("step") >= ends[-1])
                error = metrics.rmse_r2(spark.createDataFrame(said[-1], ask().schema), truth, ["cohort"]).first()["rmse"]
                trained[asked] = (load, sum(each) / max(1, batches), milliseconds, error)
            out.append((capacity, growth, done["retrain"], done["update"], max(1, 2 * rows // capacity - 1), *trained[asked]))
    long.unpersist()
    return spark.createDataFrame(out, "capacity bigint, growth double, retrains bigint, updates bigint, sub_models bigint, bulk_s double, batch_s double, forecast_ms double, rmse double")


def rival_costs(spark: SparkSession, sf_dir: str, only: tuple[str, ...] = DATASETS, times: int = 3) -> DataFrame:
    """Seconds of training and milliseconds of a one-step forecast of every
    method on every data set, beside a plain insert and a point SELECT. The
    rivals work on one matrix in memory, as their libraries do."""
    from pagecast.baselines.store import bulk_insert, select_point
    from pagecast.cluster import scratch_path

    out = []
    for name, (cells, steps) in datasets(spark, sf_dir).items():
        if name not in only:
            continue
        long = synth.plant(cells, steps, 1.0, 0.2).select("cohort", "series_id", "step", "value").persist()
        long.count()
        engine, path = Engine(spark), scratch_path(spark, "rows")
        train, _ = metrics.timed(lambda: engine.create_model("m", long))
        one = long.first()["series_id"]
        ask = metrics.latency(lambda: engine.predict("m", steps, steps, [one], uncertainty=False).collect(), times)["median"]
        out.append((name, "pages", train, ask))
        insert, _ = metrics.timed(lambda: bulk_insert(long, path))
        out.append((name, "store", insert, metrics.latency(lambda: select_point(spark, path, steps // 2).where(F.col("series_id") == one).collect(), times)["median"]))
        # a few series by a few thousand steps
        y = long.toPandas().pivot_table(index="series_id", columns="step", values="value").reindex(columns=range(steps)).to_numpy(float)
        long.unpersist()
        for method, fit in learners.FITTED.items():
            train, ahead = metrics.timed(lambda: fit(y))
            out.append((name, method, train, metrics.latency(lambda: ahead(1), times)["median"]))
    return spark.createDataFrame(out, "dataset string, method string, train_s double, latency_ms double")


def cost_ratios(costs: DataFrame) -> DataFrame:
    """Every method's training time over an insert's, its latency over a
    SELECT's, and both over those of the page models."""
    base = lambda m, a, b: costs.where(F.col("method") == m).select("dataset", F.col("train_s").alias(a), F.col("latency_ms").alias(b))
    both = costs.join(base("store", "_i", "_s"), "dataset").join(base("pages", "_t", "_l"), "dataset")
    return both.select("dataset", "method", "train_s", "latency_ms", (F.col("train_s") / F.col("_i")).alias("train_per_insert"), (F.col("latency_ms") / F.col("_s")).alias("latency_per_select"), (F.col("train_s") / F.col("_t")).alias("train_per_pages"), (F.col("latency_ms") / F.col("_l")).alias("latency_per_pages"))


def scale_latency(spark: SparkSession, sizes=(10_000, 100_000, 1_000_000), times: int = 3) -> DataFrame:
    """Milliseconds of the five kinds of question as one series grows."""
    out = []
    for rows in sizes:
        row = _latency(spark, synth.harmonics(spark, rows).select("cohort", "series_id", "step", "value"), rows // 2, rows, ["s0000"], times)
        out.append((rows, *row.values(), *metrics.relative(row, "select_ms").values()))
    names = ["select_ms", "impute_ms", "impute_uq_ms", "forecast_ms", "forecast_uq_ms", "impute_x", "impute_uq_x", "forecast_x", "forecast_uq_x"]
    return spark.createDataFrame(out, "rows bigint, " + ", ".join(f"{n} double" for n in names))


def live(spark: SparkSession, sf_dir: str, batches: int = 3) -> DataFrame:
    """Forecasts while a batch is being added: they come from the last finished
    state, whatever the writer is doing."""
    from concurrent.futures import ThreadPoolExecutor

    from pagecast.streaming.models import IncrementalModel

    rows = series.events_by_type(spark, sf_dir).persist()
    config = ModelConfig(w=6, r_impute=3, r_forecast=3)
    model = IncrementalModel(spark, 5, config)
    model.append(rows.where("step < 400"))
    out = []
    with ThreadPoolExecutor(1) as pool:
        for k in range(batches):
            lo, reader = 400 + 100 * k, IncrementalModel(spark, 5, config, model.root)
            want = {r["moment"]: r["beta"] for r in reader.weights().collect()}
            write = pool.submit(model.append, rows.where(F.col("step").between(lo, lo + 99)))
            asked = 0
            while not write.done() or not asked:
                got = {r["moment"]: r["beta"] for r in IncrementalModel(spark, 5, config, model.root, keep=2).weights().collect()}
                asked += 1
            write.result()
            after = {r["moment"]: r["beta"] for r in model.weights().collect()}
            out.append((k, asked > 0, got in (want, after)))
    rows.unpersist()
    return spark.createDataFrame(out, "batch int, answered boolean, consistent boolean")


def minimum_count(spark: SparkSession, sf_dir: str, leasts=(50, 100, 500)) -> DataFrame:
    """The least count hardly matters once there are more observations."""
    cells, steps = datasets(spark, sf_dir)["events"]
    noisy = synth.plant(cells, steps, 1.0, 0.2).persist()
    out = []
    for least in leasts:
        engine = Engine(spark)
        engine.create_model("m", noisy, ModelConfig(least=least))
        out.append(metrics.nrmse(engine.predict("m", 0, steps - 1), noisy).withColumn("least", F.lit(least)))
    return reduce(_UNION, out)


def scale_training(spark: SparkSession, sizes=(10_000, 100_000)) -> list[dict]:
    """Seconds and microseconds per row for training and for a plain insert."""
    from pagecast.baselines.store import bulk_insert
    from pagecast.cluster import scratch_path

    out = []
    for rows in sizes:
        long = synth.harmonics(spark, rows).persist()
        long.count()
        engine = Engine(spark)
        create, _ = metrics.timed(lambda: engine.create_model("m", long))
        insert, _ = metrics.timed(lambda: bulk_insert(long, scratch_path(spark, "insert")))
        long.unpersist()
        out.append({"rows": rows, "create_s": create, "insert_s": insert, "us_per_row": metrics.per_record(create, rows), "relative": create / insert})
    return out


def latency(spark: SparkSession, sf_dir: str, times: int = 5) -> dict[str, float]:
    """Milliseconds of a point SELECT, an imputation and a forecast."""
    long = series.orders_by_priority(spark, sf_dir)
    return _latency(spark, long, 1000, 2405, ["1-URGENT"], times)


def _latency(spark: SparkSession, long: DataFrame, past: int, future: int, one: list[str], times: int) -> dict[str, float]:
    from pagecast.baselines.store import bulk_insert, select_point
    from pagecast.cluster import scratch_path

    engine = Engine(spark)
    engine.create_model("m", long)
    path = scratch_path(spark, "rows")
    bulk_insert(long, path)
    kinds = {
        "select_ms": lambda: select_point(spark, path, past).where(F.col("series_id").isin(one)),
        "impute_ms": lambda: engine.predict("m", past, past, one, uncertainty=False),
        "impute_uq_ms": lambda: engine.predict("m", past, past, one),
        "forecast_ms": lambda: engine.predict("m", future, future, one, uncertainty=False),
        "forecast_uq_ms": lambda: engine.predict("m", future, future, one),
    }
    for ask in kinds.values():  # the first of each compiles
        ask().collect()
    return {k: metrics.latency(lambda: ask().collect(), times)["median"] for k, ask in kinds.items()}


def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three series of a hundred days: day 100 (0-based) is a forecast, day 9 is
    recovered from the history."""
    long = series.orders_by_priority(spark, sf_dir).where("step < 100 and series_id in ('1-URGENT', '2-HIGH', '3-MEDIUM')")
    engine = Engine(spark)
    engine.create_model("stock", long, ModelConfig(w=10))
    return engine.predict("stock", 9, 9).unionByName(engine.predict("stock", 100, 100))


def summary(results: DataFrame) -> DataFrame:
    """Weighted Borda count and mean error of each method, best first."""
    return metrics.wbc(results).join(metrics.mean_nrmse(results), "method").orderBy(F.desc("wbc"))
