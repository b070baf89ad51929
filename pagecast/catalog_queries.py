"""The registered queries of the engine and their SQL counterparts."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pagecast.baselines import naive, store
from pagecast.functions import mathfn, noise
from pagecast.operators import answers, factor, ingest, pagematrix, relational, segments  # noqa: F401
from pagecast.plans import metrics, sqlfront, theory, workloads
from pagecast.plans.config import ModelConfig, half_window, settle
from pagecast.plans.engine import Engine
from pagecast.plans.registry import ORACLES, QUERIES, query
from pagecast.sources import series, synth

R = relational.R

#: Daily prices by priority, as SQL: the observations behind most queries here.
OBS = "obs AS (SELECT o_orderpriority AS series_id, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate)::BIGINT AS step, avg(o_totalprice) AS value FROM orders GROUP BY 1, 2)"
EVENT_OBS = "obs AS (SELECT event_type AS series_id, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) // 3600000000 AS step, avg(value) AS value FROM events GROUP BY 1, 2)"


def _cells(w: int, obs: str = OBS) -> str:
    """Zero-filled pages of height w as rows (series_id, page, row, z, obs)."""
    return (
        f"{obs}, top AS (SELECT max(step) + 1 AS t FROM obs), kept AS (SELECT * FROM obs, top WHERE step < t - t % {w}), "
        f"page AS (SELECT DISTINCT series_id, step // {w} AS page FROM kept), "
        f"cell AS (SELECT p.series_id, p.page, r.range AS i, coalesce(k.value, 0.0) AS z, k.value IS NOT NULL AS seen FROM page p, range({w}) r "
        f"LEFT JOIN kept k ON k.series_id = p.series_id AND k.step = p.page * {w} + r.range)"
    )


def _orders(spark, d) -> DataFrame:
    return series.orders_by_priority(spark, d)


def _gram(spark, d, w: int) -> DataFrame:
    return factor.gram_cells(pagematrix.build(_orders(spark, d), w))


# ------------------------------------------------------------------------ methods
@query("q_m01_regularize", f"WITH {OBS} SELECT series_id, step, round(value, 4) + 0.0 AS value FROM obs")
def regularize(spark: SparkSession, d: str) -> DataFrame:
    return _orders(spark, d).select("series_id", "step", R("value").alias("value"))


for _agg, _sql in (("min", "min(value)"), ("max", "max(value)"), ("sum", "sum(value)"), ("count", "count(value)::DOUBLE"), ("median", "median(value)"), ("first", "min_by(value, ts)"), ("last", "max_by(value, ts)"), ("stddev", "stddev_samp(value)")):
    query(
        f"q_m01_{_agg}",
        f"SELECT event_type AS series_id, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) // 3600000000 AS step, round({_sql}, 4) + 0.0 AS value FROM events GROUP BY 1, 2",
    )(lambda spark, d, agg=_agg: series.events_by_type(spark, d, agg).select("series_id", "step", R("value").alias("value")))


@query("q_m02_densify", f"WITH {EVENT_OBS}, b AS (SELECT min(step) AS lo, max(step) AS hi FROM obs), g AS (SELECT s.series_id, unnest(generate_series(b.lo, b.hi)) AS step FROM (SELECT DISTINCT series_id FROM obs) s, b) SELECT g.series_id, g.step, round(o.value, 4) + 0.0 AS value FROM g LEFT JOIN obs o ON o.series_id = g.series_id AND o.step = g.step")
def densify(spark, d):
    return ingest.densify(series.events_by_type(spark, d)).select("series_id", "step", R("value").alias("value"))


@query("q_m03_wide", f"WITH {EVENT_OBS} SELECT step, round(max(value) FILTER (WHERE series_id = 'click'), 4) + 0.0 AS click, round(max(value) FILTER (WHERE series_id = 'error'), 4) + 0.0 AS error FROM obs WHERE series_id IN ('click', 'error') GROUP BY step")
def wide(spark, d):
    long = series.events_by_type(spark, d).where("series_id in ('click', 'error')")
    return ingest.to_wide(long, ["click", "error"]).select("step", R("click").alias("click"), R("error").alias("error"))


@query("q_m04_pages", f"WITH {_cells(20)} SELECT series_id, page::BIGINT AS page, i::INT AS row, round(z, 4) + 0.0 AS value FROM cell")
def pages(spark, d):
    return pagematrix.cells(pagematrix.build(_orders(spark, d), 20)).select("series_id", "page", "row", R("value").alias("value"))


@query("q_m05_squares", f"WITH {_cells(20)} SELECT series_id, page::BIGINT AS page, round(sum(z * z) / 1e6, 2) + 0.0 AS value FROM cell GROUP BY 1, 2")
def squares(spark, d):
    p = pagematrix.build(_orders(spark, d), 20)
    return p.select("series_id", "page", R(F.aggregate("sq", F.lit(0.0), lambda a, x: a + x) / 1e6, 2).alias("value"))


@query("q_m06_observed", f"WITH {_cells(20)} SELECT series_id, page::BIGINT AS page, count(*) FILTER (WHERE seen) AS seen FROM cell GROUP BY 1, 2")
def observed(spark, d):
    return pagematrix.build(_orders(spark, d), 20).select("series_id", "page", "seen")


@query("q_m06_standardize", f"WITH {OBS}, s AS (SELECT series_id, avg(value) AS mu, stddev_pop(value) AS sd FROM obs GROUP BY 1) SELECT series_id, step, round((value - mu) / sd, 6) + 0.0 AS value FROM obs JOIN s USING (series_id)")
def standardize(spark, d):
    long = _orders(spark, d)
    return ingest.standardize(long, ingest.statistics(long)).select("series_id", "step", R("value", 6).alias("value"))


@query("q_m08_gram", f"WITH {_cells(6)} SELECT a.i::INT AS i, b.i::INT AS j, round(sum(a.z * b.z) / 1e9, 4) + 0.0 AS g FROM cell a JOIN cell b ON a.series_id = b.series_id AND a.page = b.page GROUP BY 1, 2")
def gram(spark, d):
    return _gram(spark, d, 6).select("i", "j", R(F.col("g") / 1e9).alias("g"))


@query("q_m08_gram_local_agree", "SELECT 0.0::DOUBLE AS gap")
def backends_agree(spark, d):
    """Largest relative difference of the weights between both backends, rounded."""
    p = pagematrix.build(series.events_by_type(spark, d), 6)
    a = factor.train(p, 1 << 20, ModelConfig(w=6, r_impute=3, r_forecast=3))
    b = factor.train(p, 1 << 20, ModelConfig(w=6, r_impute=3, r_forecast=3, backend="local"))
    flat = lambda m, n: m.where("moment = 1").select(F.posexplode("weights").alias("k", n))
    return flat(a, "x").join(flat(b, "y"), "k").agg(R(F.max(F.abs(F.col("x") - F.col("y"))), 6).alias("gap"))


@query("q_m09_impute_full_rank", f"WITH {_cells(6)} SELECT series_id, (page * 6 + i)::BIGINT AS step, round(z, 2) + 0.0 AS mean FROM cell")
def impute_full(spark, d):
    """With every singular value kept the answer is the zero-filled input."""
    return _imputed(spark, d, 6, 6, 2)


@query("q_m09_impute_rank_one", f"WITH {_cells(2, EVENT_OBS)}, g AS (SELECT sum(a.z * a.z) AS aa, sum(b.z * b.z) AS bb, sum(a.z * b.z) AS ab FROM cell a JOIN cell b ON a.series_id = b.series_id AND a.page = b.page WHERE a.i = 0 AND b.i = 1), t AS (SELECT 0.5 * atan2(2 * ab, aa - bb) AS x FROM g), p AS (SELECT series_id, page, max(z) FILTER (WHERE i = 0) AS z0, max(z) FILTER (WHERE i = 1) AS z1 FROM cell GROUP BY 1, 2) SELECT series_id, (page * 2 + r.range)::BIGINT AS step, round((z0 * cos(x) + z1 * sin(x)) * CASE WHEN r.range = 0 THEN cos(x) ELSE sin(x) END, 4) + 0.0 AS mean FROM p, t, range(2) r")
def impute_one(spark, d):
    """Two rows and one direction: the projection on the leading angle."""
    p = pagematrix.build(series.events_by_type(spark, d), 2)
    m = factor.train(p, 1 << 20, ModelConfig(w=2, r_impute=1, r_forecast=1))
    return answers.impute(p, m, 1 << 20, 2).select("series_id", "step", R("mean").alias("mean"))


def _imputed(spark, d, w: int, rank: int, digits: int) -> DataFrame:
    p = pagematrix.build(_orders(spark, d), w)
    m = factor.train(p, 1 << 20, ModelConfig(w=w, r_impute=rank, r_forecast=min(rank, w - 1)))
    return answers.impute(p, m, 1 << 20, w).select("series_id", "step", R("mean", digits).alias("mean"))


@query("q_m10_split", f"WITH {_cells(6)} SELECT series_id, page::BIGINT AS page, round(max(z) FILTER (WHERE i = 5), 4) + 0.0 AS target, round(sum(z) FILTER (WHERE i < 5), 2) + 0.0 AS lags FROM cell GROUP BY 1, 2")
def split(spark, d):
    s = pagematrix.split_last(pagematrix.build(_orders(spark, d), 6))
    return s.select("series_id", "page", R("target").alias("target"), R(F.aggregate("lags", F.lit(0.0), lambda a, x: a + x), 2).alias("lags"))


def _weights(spark, d, w: int, rank: int) -> DataFrame:
    p = pagematrix.build(_orders(spark, d), w)
    m = factor.train(p, 1 << 20, ModelConfig(w=w, r_impute=rank, r_forecast=rank))
    return answers.weight_view(m, 10)


@query("q_m12_weight", f"WITH {_cells(2)}, p AS (SELECT series_id, page, max(z) FILTER (WHERE i = 0) AS a, max(z) FILTER (WHERE i = 1) AS b FROM cell GROUP BY 1, 2) SELECT round(sum(a * b) / sum(a * a), 7) + 0.0 AS beta FROM p")
def weight(spark, d):
    return _weights(spark, d, 2, 1).where("moment = 1").select(R(F.col("beta")[0], 7).alias("beta"))


_CRAMER = f"{_cells(3)}, p AS (SELECT series_id, page, max(z) FILTER (WHERE i = 0) AS a, max(z) FILTER (WHERE i = 1) AS b, max(z) FILTER (WHERE i = 2) AS y FROM cell GROUP BY 1, 2), g AS (SELECT sum(a*a) AS aa, sum(a*b) AS ab, sum(b*b) AS bb, sum(a*y) AS ay, sum(b*y) AS byy FROM p), beta AS (SELECT (ay*bb - byy*ab) / (aa*bb - ab*ab) AS b0, (aa*byy - ab*ay) / (aa*bb - ab*ab) AS b1 FROM g)"


@query("q_m12_weights_cramer", f"WITH {_CRAMER} SELECT round(b0, 7) + 0.0 AS b0, round(b1, 7) + 0.0 AS b1 FROM beta")
def weights_cramer(spark, d):
    b = F.col("beta")
    return _weights(spark, d, 3, 2).where("moment = 1").select(R(b[0], 7).alias("b0"), R(b[1], 7).alias("b1"))


@query("q_m14_roll", f"WITH RECURSIVE {_CRAMER}, now AS (SELECT max(step) AS n FROM obs), s AS (SELECT DISTINCT series_id FROM obs), start AS (SELECT s.series_id, coalesce((SELECT value FROM obs o, now WHERE o.series_id = s.series_id AND o.step = n - 1), 0) AS x, coalesce((SELECT value FROM obs o, now WHERE o.series_id = s.series_id AND o.step = n), 0) AS y FROM s), f AS (SELECT series_id, 0 AS k, x, y FROM start UNION ALL SELECT series_id, k + 1, y, b0 * x + b1 * y FROM f, beta WHERE k < 10) SELECT series_id, (n + k)::BIGINT AS step, round(y, 3) + 0.0 AS mean FROM f, now WHERE k > 0")
def roll(spark, d):
    """Ten steps ahead, predictions fed back."""
    return answers.forecast(_orders(spark, d), _weights(spark, d, 3, 2), 3, 10).select("series_id", "step", R("mean", 3).alias("mean"))


@query("q_m17_clip", "SELECT event_id, round(sqrt(greatest(0.0, value - 50)), 6) + 0.0 AS sd FROM events")
def clipped(spark, d):
    return series.table(spark, d, "events").select("event_id", R(F.sqrt(answers.clip(F.col("value") - 50)), 6).alias("sd"))


def _bounds(spark, d, method: str) -> DataFrame:
    rows = _orders(spark, d).groupBy("series_id").agg(F.avg("value").alias("mean"), F.var_pop("value").alias("variance"))
    return answers.interval(rows, 95, method).select("series_id", R("lower", 3).alias("lower"), R("upper", 3).alias("upper"))


_BOUND_SQL = "WITH {obs}, m AS (SELECT series_id, avg(value) AS mu, stddev_pop(value) AS sd FROM obs GROUP BY 1) SELECT series_id, round(mu - sd * {f}, 3) + 0.0 AS lower, round(mu + sd * {f}, 3) + 0.0 AS upper FROM m"


@query("q_m18_gaussian", _BOUND_SQL.format(obs=OBS, f="1.959963984540054"))
def gaussian(spark, d):
    return _bounds(spark, d, "gaussian")


@query("q_m19_chebyshev", _BOUND_SQL.format(obs=OBS, f="power(1 - 0.95, -0.5)"))
def chebyshev(spark, d):
    return _bounds(spark, d, "chebyshev")


@query("q_m22_running", f"WITH {OBS} SELECT series_id, step, round(avg(value) OVER (PARTITION BY series_id ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) + 0.0 AS mean FROM obs")
def running(spark, d):
    return answers.running_mean(_orders(spark, d)).select("series_id", "step", R("mean").alias("mean"))


@query("q_m23_retrains", "SELECT DISTINCT floor(100 * power(1.5, range))::BIGINT AS point FROM range(200) WHERE floor(100 * power(1.5, range)) <= 2500000")
def retrains(spark, d):
    return spark.createDataFrame([(p,) for p in segments.retrain_points(100, 2_500_000, 0.5)], "point bigint")


@query("q_m24_active", "SELECT range * 700 AS count, greatest(0, 2 * range * 700 // 6000 - 1)::BIGINT AS model_idx, (greatest(0, 2 * range * 700 // 6000 - 1) * 3000)::BIGINT AS origin, CASE WHEN range * 700 < 100 THEN 1 WHEN range * 700 <= 6000 THEN 2 ELSE 3 END::INT AS n_case FROM range(100)")
def active(spark, d):
    counts = spark.range(100).select((F.col("id") * 700).alias("count"))
    return segments.schedule(spark, counts, ModelConfig(capacity=6000))


@query("q_m26_two_windows", f"WITH {OBS}, s AS (SELECT series_id, step // 100 AS h, value FROM obs WHERE step < 2400) SELECT series_id, h::BIGINT AS half, round(avg(value), 3) + 0.0 AS mean, CASE WHEN h = 0 OR h = 23 THEN 1 ELSE 2 END::INT AS models FROM s GROUP BY series_id, h")
def two_windows(spark, d):
    """How many sub-models cover each half window."""
    rows = _orders(spark, d).where("step < 2400").groupBy("series_id", F.floor(F.col("step") / 100).cast("bigint").alias("half")).agg(R(F.avg("value"), 3).alias("mean"))
    return rows.withColumn("models", F.size(segments.models_of_half(F.col("half"), F.lit(22))))


@query("q_m26_two_windows_whole", f"WITH {OBS}, e AS (SELECT max(step) // 100 AS hi FROM obs), s AS (SELECT series_id, step // 100 AS h, hi, value FROM obs, e) SELECT series_id, h::BIGINT AS half, round(avg(value), 3) + 0.0 AS mean, CASE WHEN h = 0 OR h = hi THEN 1 ELSE 2 END::INT AS models FROM s GROUP BY series_id, h, hi")
def two_windows_whole(spark, d):
    """The same over all steps; the table's own last step gives the last sub-model."""
    halves = _orders(spark, d).withColumn("half", F.floor(F.col("step") / 100).cast("bigint"))
    newest = halves.agg(F.greatest(F.lit(0), F.max("half") - 1).alias("newest"))
    rows = halves.groupBy("series_id", "half").agg(R(F.avg("value"), 3).alias("mean")).join(F.broadcast(newest))
    return rows.select("series_id", "half", "mean", F.size(segments.models_of_half(F.col("half"), F.col("newest"))).alias("models"))


@query("q_m26_windows_full_rank", f"WITH {_cells(6)} SELECT series_id, (page * 6 + i)::BIGINT AS step, round(z, 2) + 0.0 AS mean FROM cell")
def windows_full_rank(spark, d):
    """The average over covering sub-models of full rank is the input again."""
    p = pagematrix.build(_orders(spark, d), 6)
    m = factor.train(p, 40, ModelConfig(w=6, r_impute=6, r_forecast=5))
    return answers.impute(p, m, 40, 6).select("series_id", "step", R("mean", 2).alias("mean"))


@query("q_m32_select", "SELECT o_orderpriority, count(*) AS n FROM orders GROUP BY 1")
def select(spark, d):
    series.table(spark, d, "orders").createOrReplaceTempView("pagecast_orders")
    return sqlfront.run(Engine(spark), "SELECT o_orderpriority, count(*) AS n FROM pagecast_orders GROUP BY 1")


@query("q_m33_compare", f"WITH {_cells(6)} SELECT series_id, (page * 6 + i)::BIGINT AS step, CASE WHEN seen THEN round(z, 2) + 0.0 END AS stored, round(z, 2) + 0.0 AS mean FROM cell WHERE page < 50")
def compare(spark, d):
    engine = Engine(spark)
    engine.create_model("m", _orders(spark, d), ModelConfig(w=6, r_impute=6, r_forecast=5))
    out = engine.compare("m", 0, 299).where("stored is not null or mean is not null")
    pages_there = _orders(spark, d).select("series_id", F.floor(F.col("step") / 6).alias("p")).distinct()
    return out.join(pages_there, (out.series_id == pages_there.series_id) & (F.floor(out.step / 6) == pages_there.p), "left_semi").select("series_id", "step", R("stored", 2).alias("stored"), R("mean", 2).alias("mean"))


@query("q_m33_compare_whole")
def compare_whole(spark, d):
    """Every step of every series, the last ones that fill no page included."""
    engine = Engine(spark)
    model = engine.create_model("m", _orders(spark, d), ModelConfig(w=6, r_impute=6, r_forecast=5))
    return engine.compare("m", 0, model.steps - 1)


@query("q_m36_hankel", f"WITH {EVENT_OBS}, b AS (SELECT max(step) AS hi FROM obs), g AS (SELECT s.series_id, unnest(generate_series(0, b.hi)) AS step FROM (SELECT DISTINCT series_id FROM obs) s, b), z AS (SELECT g.series_id, g.step, coalesce(o.value, 0) AS z FROM g LEFT JOIN obs o ON o.series_id = g.series_id AND o.step = g.step), r AS (SELECT series_id, step, sum(z) OVER w AS total, count(*) OVER w AS n FROM z WINDOW w AS (PARTITION BY series_id ORDER BY step ROWS BETWEEN CURRENT ROW AND 11 FOLLOWING)) SELECT series_id, step::BIGINT AS page, round(total, 3) + 0.0 AS total FROM r WHERE n = 12")
def hankel(spark, d):
    h = pagematrix.hankel(ingest.densify(series.events_by_type(spark, d), lo=0), 12)
    return h.select("series_id", "page", R(F.aggregate("vals", F.lit(0.0), lambda a, x: a + x), 3).alias("total"))


@query("q_m37_cohorts", "SELECT n_name AS series_id, r_name AS cohort, count(*) AS days FROM (SELECT DISTINCT n_name, r_name, o_orderdate::DATE AS day FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) GROUP BY 1, 2")
def cohorts(spark, d):
    long = segments.cohorts(series.orders_by_nation(spark, d), "attribute", attribute=series.regions(spark, d))
    return long.groupBy("series_id", "cohort").agg(F.count("*").alias("days"))


@query("q_m38_config", "SELECT floor(sqrt(5 * 2405 // 10))::INT AS w, 100::INT AS least, 2500000::INT AS capacity, 0.5::DOUBLE AS growth, 10::INT AS average")
def config(spark, d):
    c = settle(ModelConfig(), 5, 2405)
    return spark.createDataFrame([(c.w, c.least, c.capacity, c.growth, c.average)], "w int, least int, capacity int, growth double, average int")


@query("q_m38_geometry", "SELECT range + 1 AS n, (greatest(1, 60000 // (2 * (range + 1)) // 20) * 20)::BIGINT AS half FROM range(400)")
def geometry(spark, d):
    rows = [(n, half_window(ModelConfig(w=20, capacity=60000), n)) for n in range(1, 401)]
    return spark.createDataFrame(rows, "n bigint, half bigint")


@query("q_m39_poisson")
def poisson(spark, d):
    return workloads.poisson_or_not(spark, d)


@query("q_m44_bounds", "SELECT a.range::INT AS terms, m.range::INT AS degree, (a.range * (m.range + 1) * (m.range + 2))::INT AS bound FROM range(1, 6) a, range(0, 4) m")
def bounds(spark, d):
    return spark.createDataFrame([(a, m, theory.recurrence_bound(a, m)) for a in range(1, 6) for m in range(4)], "terms int, degree int, bound int")


# ---------------------------------------------------------------------- baselines
@query("q_b09_insert", "SELECT count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders")
def insert(spark, d):
    from pagecast.cluster import scratch_path

    path = scratch_path(spark, "insert")
    store.bulk_insert(series.table(spark, d, "orders").select("o_orderkey", "o_orderdate"), path, "o_orderdate")
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query("q_b10_point", f"WITH {OBS} SELECT series_id, round(value, 4) + 0.0 AS value FROM obs WHERE step = 1000")
def select_point(spark, d):
    from pagecast.cluster import scratch_path

    path = scratch_path(spark, "rows")
    store.bulk_insert(_orders(spark, d), path)
    return store.select_point(spark, path, 1000).select("series_id", R("value").alias("value"))


_NAIVE = "WITH {obs}, now AS (SELECT max(step) AS n FROM obs) SELECT series_id, (n + k.range)::BIGINT AS step, round({v}, 4) + 0.0 AS mean FROM (SELECT series_id, {agg} AS v FROM obs GROUP BY 1), now, range(1, 4) k"


@query("q_b11_average", _NAIVE.format(obs=OBS, v="v", agg="avg(value)"))
def average(spark, d):
    return naive.average(_orders(spark, d), 3).select("series_id", "step", R("mean").alias("mean"))


@query("q_b11_last", _NAIVE.format(obs=OBS, v="v", agg="arg_max(value, step)"))
def last(spark, d):
    return naive.last(_orders(spark, d), 3).select("series_id", "step", R("mean").alias("mean"))


@query("q_b11_seasonal", f"WITH {EVENT_OBS}, now AS (SELECT max(step) AS n FROM obs), p AS (SELECT series_id, step % 24 AS ph, arg_max(value, step) AS v FROM obs GROUP BY 1, 2), s AS (SELECT DISTINCT series_id FROM obs) SELECT s.series_id, (n + k.range)::BIGINT AS step, round(coalesce(p.v, 0), 4) + 0.0 AS mean FROM s CROSS JOIN now CROSS JOIN range(1, 25) k LEFT JOIN p ON p.series_id = s.series_id AND p.ph = (n + k.range) % 24")
def seasonal(spark, d):
    return naive.seasonal(series.events_by_type(spark, d), 24, 24).select("series_id", "step", R("mean").alias("mean"))


@query("q_b13_capabilities", f"WITH {EVENT_OBS}, s AS (SELECT series_id, max(step) - min(step) + 1 - count(*) AS missing FROM obs GROUP BY 1) SELECT series_id, missing::BIGINT AS missing, v.*, gaps OR missing = 0 AS serves FROM s, (VALUES ('page matrix', true, true, true), ('recurrent network', true, false, false), ('probabilistic recurrent network', true, true, true), ('regularised matrix factorisation', true, false, true), ('additive model', false, false, true)) v(method, multivariate, variance, gaps)")
def capabilities(spark, d):
    """Which methods can take a series as it is, gaps included."""
    missing = series.events_by_type(spark, d).groupBy("series_id").agg((F.max("step") - F.min("step") + 1 - F.count("*")).alias("missing"))
    both = missing.crossJoin(F.broadcast(store.capabilities(spark)))
    return both.withColumn("serves", F.col("gaps") | (F.col("missing") == 0))


# ----------------------------------------------------------------------- measures
#: Errors of three plain forecasts of a year of daily prices, a priority each an experiment.
_CUT, _YEAR = 2000, 365
_RIVALS = (
    f"{OBS}, past AS (SELECT * FROM obs WHERE step < {_CUT}), now AS (SELECT max(step) AS n FROM past), truth AS (SELECT obs.* FROM obs, now WHERE step BETWEEN {_CUT} AND n + {_YEAR}), "
    "pred AS (SELECT t.series_id, value AS t, 'average' AS method, v AS p FROM truth t JOIN (SELECT series_id, avg(value) AS v FROM past GROUP BY 1) USING (series_id) "
    "UNION ALL SELECT t.series_id, value, 'last', v FROM truth t JOIN (SELECT series_id, arg_max(value, step) AS v FROM past GROUP BY 1) USING (series_id) "
    "UNION ALL SELECT t.series_id, t.value, 'seasonal', coalesce(v, 0) FROM truth t JOIN (SELECT DISTINCT series_id FROM past) s ON s.series_id = t.series_id LEFT JOIN (SELECT series_id, (step % 7 + 7) % 7 AS ph, arg_max(value, step) AS v FROM past GROUP BY 1, 2) a ON a.series_id = t.series_id AND ph = t.step % 7), "
    "r AS (SELECT series_id AS experiment, method, sqrt(sum((p - t) ** 2) / CASE WHEN stddev_pop(t) > 0 THEN var_pop(t) ELSE 1 END / count(*)) AS nrmse FROM pred GROUP BY 1, 2)"
)


def _rivals(spark, d) -> DataFrame:
    long = _orders(spark, d)
    past, truth = long.where(F.col("step") < _CUT), long.where(F.col("step") >= _CUT).withColumn("latent", F.col("value"))
    found = {"average": naive.average(past, _YEAR), "last": naive.last(past, _YEAR), "seasonal": naive.seasonal(past, _YEAR, 7)}
    errors = [metrics.nrmse(p, truth, ["series_id"]).select(F.col("series_id").alias("experiment"), F.lit(m).alias("method"), "nrmse") for m, p in found.items()]
    return errors[0].unionByName(errors[1]).unionByName(errors[2])


@query("q_a03_wbc", f"WITH {_RIVALS} SELECT a.method, round(avg(b.nrmse / (a.nrmse + b.nrmse)), 6) + 0.0 AS wbc FROM r a JOIN r b ON a.experiment = b.experiment AND a.method <> b.method GROUP BY 1")
def wbc(spark, d):
    return metrics.wbc(_rivals(spark, d)).select("method", R("wbc", 6).alias("wbc"))


@query("q_a04_mean_error", f"WITH {_RIVALS} SELECT method, round(avg(nrmse), 6) + 0.0 AS mean_nrmse FROM r GROUP BY 1")
def mean_error(spark, d):
    return metrics.mean_nrmse(_rivals(spark, d)).select("method", R("mean_nrmse", 6).alias("mean_nrmse"))


@query("q_a05_wins", f"WITH {_RIVALS}, k AS (SELECT *, rank() OVER (PARTITION BY experiment ORDER BY nrmse) AS p FROM r), b AS (SELECT a.experiment, a.method, min(b.nrmse)::DOUBLE / a.nrmse::DOUBLE AS ratio FROM r a JOIN r b ON a.experiment = b.experiment AND a.method <> b.method GROUP BY a.experiment, a.method, a.nrmse) SELECT k.method, avg((p = 1)::INT)::DOUBLE AS won, avg((p <= 2)::INT)::DOUBLE AS second_or_better, round(min(ratio), 6) + 0.0 AS least_ratio, round(max(ratio), 6) + 0.0 AS most_ratio FROM k JOIN b USING (experiment, method) GROUP BY 1")
def wins(spark, d):
    return metrics.wins(_rivals(spark, d)).select("method", "won", "second_or_better", R("least_ratio", 6).alias("least_ratio"), R("most_ratio", 6).alias("most_ratio"))


@query("q_a01_nrmse", f"WITH {OBS}, s AS (SELECT series_id, avg(value) AS mu, nullif(var_pop(value), 0) AS v FROM obs GROUP BY 1) SELECT round(sqrt(sum((value - mu) ** 2 / coalesce(v, 1)) / count(*)), 6) + 0.0 AS nrmse FROM obs JOIN s USING (series_id)")
def nrmse(spark, d):
    """The error of the plain average is one by definition."""
    long = _orders(spark, d)
    mean = long.join(ingest.statistics(long), ["cohort", "series_id"]).select("cohort", "series_id", "step", F.col("mu").alias("mean"))
    return metrics.nrmse(mean, long.withColumn("latent", F.col("value"))).select(R("nrmse", 6).alias("nrmse"))


@query("q_a02_r2", f"WITH {EVENT_OBS}, p AS (SELECT *, 0.5 * value + 0.5 * avg(value) OVER (PARTITION BY series_id) AS m FROM obs) SELECT series_id, round(sqrt(avg((m - value) ** 2)), 5) + 0.0 AS rmse, round(1 - avg((m - value) ** 2) / var_pop(value), 6) + 0.0 AS r2 FROM p GROUP BY 1")
def rmse(spark, d):
    long = series.events_by_type(spark, d)
    half = long.withColumn("mean", 0.5 * F.col("value") + 0.5 * F.avg("value").over(Window.partitionBy("series_id")))
    found = metrics.rmse_r2(half.select("cohort", "series_id", "step", "mean"), long.withColumn("latent", F.col("value")), ["series_id"])
    return found.select("series_id", R("rmse", 5).alias("rmse"), R("r2", 6).alias("r2"))


@query("q_a14_coverage", f"WITH {OBS}, m AS (SELECT *, avg(value) OVER w AS mu, stddev_pop(value) OVER w AS sd FROM obs WINDOW w AS (PARTITION BY series_id)) SELECT round(avg((value BETWEEN mu - 1.959963984540054 * sd AND mu + 1.959963984540054 * sd)::INT), 6) + 0.0 AS coverage, round(avg(2 * 1.959963984540054 * sd) / 1000, 5) + 0.0 AS width_k FROM m")
def coverage(spark, d):
    long = _orders(spark, d)
    stats = long.groupBy("cohort", "series_id").agg(F.avg("value").alias("mean"), F.var_pop("value").alias("variance"))
    pred = answers.interval(long.select("cohort", "series_id", "step").join(stats, ["cohort", "series_id"]), 95)
    return metrics.coverage(pred, long).select(R("coverage", 6).alias("coverage"), R(F.col("width") / 1000, 5).alias("width_k"))


@query("q_a08_speedups", f"WITH {_RIVALS} SELECT r.method, round(min(r.nrmse / o.nrmse), 6) + 0.0 AS least, round(median(r.nrmse / o.nrmse), 6) + 0.0 AS middle, round(max(r.nrmse / o.nrmse), 6) + 0.0 AS most FROM r JOIN r o USING (experiment) WHERE o.method = 'average' AND r.method <> 'average' GROUP BY 1")
def speedups(spark, d):
    """Range and median of the rivals' errors over those of the average."""
    out = metrics.speedups(_rivals(spark, d).select(F.col("experiment").alias("dataset"), "method", F.col("nrmse").alias("value")), "average")
    return out.select("method", *(R(c, 6).alias(c) for c in ("least", "middle", "most")))


@query("q_a17_dispersion", "WITH h AS (SELECT (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) // 3600000000 AS step, count(value)::DOUBLE AS n FROM events GROUP BY 1) SELECT round(var_pop(n) / avg(n), 6) + 0.0 AS ratio FROM h")
def dispersion(spark, d):
    return series.event_counts(spark, d).agg(R(F.var_pop("value") / F.avg("value"), 6).alias("ratio"))


# --------------------------------------------------------------- functions, sources
@query("q_f03_probit", "SELECT CASE WHEN count(c_acctbal) > 0 THEN 1 END AS k, count(c_acctbal) AS n FROM customer")
def probit(spark, d):
    """The quantile expression agrees with the library's to eight digits, at
    shares that the balances give."""

    @F.pandas_udf("double")
    def library(p: pd.Series) -> pd.Series:
        from statistics import NormalDist

        return p.map(NormalDist().inv_cdf)

    p = ((F.pmod(F.col("c_acctbal").cast("double"), F.lit(1000.0)) + 0.5) / 1001).alias("p")
    rows = series.table(spark, d, "customer").where("c_acctbal is not null").select(p)
    gap = F.abs(mathfn.probit(F.col("p")) - library("p"))
    return rows.agg((F.max(gap) < 1e-8).cast("int").alias("k"), F.count("*").alias("n"))


@query("q_f11_uniform", f"SELECT range AS step, round({noise.sql_uniform('range', '3', 1)}, 7) + 0.0 AS u FROM range(5000)")
def uniform(spark, d):
    return spark.range(5000).select(F.col("id").alias("step"), R(noise.uniform(F.col("id"), 3, 1), 7).alias("u"))


@query("q_f11_gauss", "SELECT c_custkey AS step, round(-6.0 + " + " + ".join(noise.sql_uniform("c_custkey", "2", 100 + k) for k in range(12)) + ", 7) + 0.0 AS g FROM customer")
def gauss(spark, d):
    return series.table(spark, d, "customer").select(F.col("c_custkey").alias("step"), R(noise.gauss(F.col("c_custkey"), 2, 1), 7).alias("g"))


@query("q_f11_mask", f"WITH {OBS}, n AS (SELECT series_id, row_number() OVER (ORDER BY series_id) - 1 AS r FROM (SELECT DISTINCT series_id FROM obs)) SELECT series_id, count(*) AS kept FROM obs JOIN n USING (series_id) WHERE {noise.sql_uniform('step', 'r', 8)} < 0.5 GROUP BY 1")
def mask(spark, d):
    cells = series.with_rank(_orders(spark, d))
    return cells.where(noise.mask(F.col("step"), F.col("rank"), 8, 0.5)).groupBy("series_id").agg(F.count("*").alias("kept"))


_TURN = str(2 * math.pi)


@query("q_f11_planted", f"WITH {EVENT_OBS}, n AS (SELECT series_id, row_number() OVER (ORDER BY series_id) - 1 AS rank FROM (SELECT DISTINCT series_id FROM obs)) SELECT rank, step, round((1 + 0.2 * rank) * cos({_TURN} * step / 24.0) + (0.5 - 0.1 * rank) * sin({_TURN} * step / 24.0) + 0.3 * (rank % 3 - 1) * cos({_TURN} * step / 7.5) + 0.5 * (rank % 2) * step / 720.0, 4) + 0.0 AS latent FROM obs JOIN n USING (series_id)")
def planted(spark, d):
    cells = series.with_rank(series.events_by_type(spark, d))
    return cells.select("rank", "step", R(synth.planted_mean(F.col("step"), F.col("rank"), 720)).alias("latent"))


@query("q_s08_data_source", f"WITH RECURSIVE {_CRAMER}, now AS (SELECT max(step) AS n FROM obs), start AS (SELECT s.series_id, coalesce((SELECT value FROM obs o, now WHERE o.series_id = s.series_id AND o.step = n - 1), 0) AS x, coalesce((SELECT value FROM obs o, now WHERE o.series_id = s.series_id AND o.step = n), 0) AS y FROM (SELECT DISTINCT series_id FROM obs) s), f AS (SELECT series_id, 0 AS k, x, y FROM start UNION ALL SELECT series_id, k + 1, y, b0 * x + b1 * y FROM f, beta WHERE k < 5) SELECT series_id, k::INT AS ahead, round(y, 3) + 0.0 AS mean FROM f WHERE k > 0")
def data_source(spark, d):
    """Forecasts read from a stored model; the limit on ``ahead`` is taken over."""
    from pagecast.cluster import full_address, ship
    from pagecast.sources.datasource import register

    ship(spark)
    register(spark)
    engine = Engine(spark)
    engine.create_model("m", _orders(spark, d), ModelConfig(w=3, r_impute=2, r_forecast=2))
    read = spark.read.format("pagecast").option("root", full_address(spark, engine.store.root)).option("model", "m").option("horizon", "50").load()
    return read.where("ahead <= 5").select("series_id", "ahead", R("mean", 3).alias("mean"))


# ---------------------------------------------------------------------- workloads
for _name, _fn in {
    "q_w00_example": workloads.worked_example,
    "q_w01_mean_imputation": lambda s, d: workloads.mean_imputation(s, d),
    "q_w02_mean_forecasting": lambda s, d: workloads.mean_forecasting(s, d),
    "q_w03_variance_imputation": lambda s, d: workloads.variance_imputation(s, d),
    "q_w04_variance_forecasting": lambda s, d: workloads.variance_forecasting(s, d),
    "q_w05_noise_kinds": lambda s, d: workloads.noise_kinds(s, d),
    "q_w06_poisson_or_not": workloads.poisson_or_not,
    "q_w07_rival_costs": lambda s, d: workloads.cost_ratios(workloads.rival_costs(s, d)),
    "q_w12_latency": lambda s, d: workloads.scale_latency(s),
    "q_w13_series_count": lambda s, d: workloads.series_count(s, d),
    "q_w14_capacity_growth": lambda s, d: workloads.capacity_growth(s, d),
    "q_w15_minimum_count": workloads.minimum_count,
}.items():
    query(_name)(_fn)


@query("q_w16_summary")
def summary(spark, d):
    return workloads.summary(workloads.variance_imputation(spark, d))


@query("q_w17_live", "SELECT range::INT AS batch, true AS answered, true AS consistent FROM range(3)")
def live(spark, d):
    return workloads.live(spark, d)


# ----------------------------------------------------------------------- streaming
@query("q_r02_hourly", "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_hours(spark, d):
    from pagecast.streaming.models import events_stream, hourly, run_once

    out = run_once(hourly(events_stream(spark, d)), "pagecast_hourly", "complete")
    return out.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@query("q_r08_click_purchase", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND c.ts <= p.ts AND c.ts > p.ts - INTERVAL 1 HOUR")
def stream_join(spark, d):
    from pagecast.streaming.models import click_then_purchase, events_stream, run_once

    return run_once(click_then_purchase(events_stream(spark, d)), "pagecast_pairs").select("click", "purchase")


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Create a model over daily prices and ask for past and future days."""
    engine = Engine(spark)
    engine.create_model("prices", series.orders_by_priority(spark, sf_dir), ModelConfig(w=20))
    return engine.predict("prices", 2380, 2410)


from pagecast import engine_queries, surface_queries  # noqa: E402, F401  (registers its queries)
