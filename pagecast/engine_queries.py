"""Queries that ask whole models, with closed forms as their SQL.

With pages of two rows the factors have formulas: the leading direction of a
2 x 2 Gram matrix is an angle, the weight of a one-lag forecast a quotient of two
sums, and full rank gives the zero-filled input back.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.baselines import learners, store
from pagecast.cluster import scratch_path
from pagecast.operators import answers, factor, pagematrix, relational, segments
from pagecast.plans import sqlfront
from pagecast.plans.config import ModelConfig, half_window
from pagecast.plans.engine import Engine
from pagecast.plans.registry import query
from pagecast.sources import series
from pagecast.streaming.models import IncrementalModel

R = relational.R

OBS = "obs AS (SELECT o_orderpriority AS series_id, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate)::BIGINT AS step, avg(o_totalprice) AS value FROM orders GROUP BY 1, 2)"
#: Steps from the first observation, and the pages of two rows.
_REL = f"{OBS}, span AS (SELECT min(step) AS lo, max(step) - min(step) + 1 AS t FROM obs), rel AS (SELECT series_id, step - lo AS r, value FROM obs, span)"
_P2 = f"{_REL}, p AS (SELECT series_id, r // 2 AS page, coalesce(max(value) FILTER (WHERE r % 2 = 0), 0) AS a, coalesce(max(value) FILTER (WHERE r % 2 = 1), 0) AS b, count(*) AS seen FROM rel, span WHERE r < t - t % 2 GROUP BY 1, 2)"
_SUMS = "count(*) AS pages, sum(seen) AS seen, sum(a * a) AS aa, sum(b * b) AS bb, sum(a * b) AS ab, sum(a ** 4) AS aa2, sum(b ** 4) AS bb2, sum(a * a * b * b) AS ab2"
_TOTALS = "sum(pages) AS pages, sum(seen) AS seen, sum(aa) AS aa, sum(bb) AS bb, sum(ab) AS ab, sum(aa2) AS aa2, sum(bb2) AS bb2, sum(ab2) AS ab2"
#: 400 steps (200 pages of each of five series) are half a sub-model.
_CAPACITY, _HALF_PAGES = 4000, 200
_MODELS = f"{_P2}, g AS (SELECT page // {_HALF_PAGES} AS h, {_SUMS} FROM p GROUP BY 1), m AS (SELECT j.h AS j, {_TOTALS} FROM (SELECT h FROM g) j JOIN g ON g.h IN (j.h, j.h + 1) GROUP BY 1 HAVING j.h = 0 OR max(g.h) = j.h + 1)"


def _orders(spark: SparkSession, d: str) -> DataFrame:
    return series.orders_by_priority(spark, d)


def _one(spark: SparkSession, d: str, config: ModelConfig, **more) -> Engine:
    engine = Engine(spark)
    engine.create_model("m", _orders(spark, d), config, **more)
    return engine


_LOG_S = "round(0.5 * ln((aa{k} + bb{k}) / 2 + sqrt(((aa{k} - bb{k}) / 2) ** 2 + ab{k} ** 2)), 7) + 0.0"


@query(
    "q_m30_create",
    f"WITH {_MODELS} SELECT j AS model_idx, 1::INT AS moment, pages::BIGINT AS pages, seen::BIGINT AS seen, {_LOG_S.format(k='')} AS log_s, round(ab / aa, 7) + 0.0 AS weight FROM m "
    f"UNION ALL SELECT j, 2::INT, pages::BIGINT, seen::BIGINT, {_LOG_S.format(k='2')}, round(ab2 / aa2, 7) + 0.0 FROM m",
)
def create(spark, d):
    """Leading singular values and weights of every sub-model, from the store."""
    engine = _one(spark, d, ModelConfig(w=2, r_impute=1, r_forecast=1, capacity=_CAPACITY))
    f = engine.store.load("m", "factors")
    return f.select("model_idx", "moment", "pages", "seen", R(F.log(F.col("s")[0]), 7).alias("log_s"), R(F.col("weights")[0], 7).alias("weight"))


@query("q_a15_cost")
def cost(spark, d):
    return _one(spark, d, ModelConfig(capacity=_CAPACITY)).cost_report("m")


#: Rows of predict() for a model of full rank: input, one-step answer, forecasts.
_FULL = (
    f"{_P2}, s AS (SELECT DISTINCT series_id FROM obs), w AS (SELECT sum(a * b) / sum(a * a) AS b1, sum(a * a * b * b) / sum(a ** 4) AS b2 FROM p), "
    "grid AS (SELECT s.series_id, g.r, coalesce(x.value, 0) AS z, x.value IS NOT NULL AS there, coalesce(y.value, 0) AS before FROM s, span, (SELECT unnest(generate_series(0, t - 1)) AS r FROM span) g LEFT JOIN rel x ON x.series_id = s.series_id AND x.r = g.r LEFT JOIN rel y ON y.series_id = s.series_id AND y.r = g.r - 1), "
    "answer AS (SELECT series_id, lo + r AS step, 'impute' AS task, CASE WHEN r < t - t % 2 THEN z ELSE b1 * before END AS mean, CASE WHEN r < t - t % 2 THEN 0 ELSE greatest(0, b2 * before * before - (b1 * before) ** 2) END AS variance FROM grid, span, w "
    "UNION ALL SELECT series_id, lo + t - 1 + k.range, 'forecast', b1 ** k.range * z, greatest(0, b2 ** k.range * z * z - (b1 ** k.range * z) ** 2) FROM grid, span, w, range(1, 8) k WHERE r = t - 1)"
)


@query("q_m31_predict", f"WITH {_FULL} SELECT series_id, step::BIGINT AS step, task, round(mean, 3) + 0.0 AS mean, round(sqrt(variance) / 1000, 3) + 0.0 AS sd_k, round((mean + 1.959963984540054 * sqrt(variance)) / 1000, 2) + 0.0 AS upper_k FROM answer, span WHERE step >= lo + t - 15")
def predict(spark, d):
    """The last two weeks and the next seven days."""
    engine = _one(spark, d, ModelConfig(w=2, r_impute=2, r_forecast=1))
    end = engine.model("m").end[1]
    out = engine.predict("m", end - 15, end + 6)
    return out.select("series_id", "step", "task", R("mean", 3).alias("mean"), R(F.col("sd") / 1000, 3).alias("sd_k"), R(F.col("upper") / 1000, 2).alias("upper_k"))


_TIMED = _FULL.replace(OBS, "obs AS (SELECT 'o_totalprice' AS series_id, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate)::BIGINT AS step, avg(o_totalprice) AS value FROM orders GROUP BY 1, 2)")
_CREATE = "CREATE PREDICTION MODEL m ON pagecast_orders (o_totalprice) TIME o_orderdate EVERY '1 day' USING mean {more} WITH (w = 2, r_impute = 2, r_forecast = 1)"


def _stated(spark, d, more: str, question: str) -> DataFrame:
    series.table(spark, d, "orders").createOrReplaceTempView("pagecast_orders")
    root = scratch_path(spark, "models")
    sqlfront.run(Engine(spark, root), _CREATE.format(more=more))
    # another engine over the same folder finds the model
    return sqlfront.run(Engine(spark, root), question)


@query("q_m31_statement", f"WITH {_TIMED} SELECT series_id, step::BIGINT AS step, task, round(mean, 3) + 0.0 AS mean, round((mean - sqrt(variance) / sqrt(1 - 0.9)) / 1000, 2) + 0.0 AS lower_k FROM answer WHERE step BETWEEN 2395 AND 2408")
def statement(spark, d):
    out = _stated(spark, d, "ORIGIN '1995-01-01'", "PREDICT o_totalprice FROM m WHERE step BETWEEN 2395 AND 2408 CONFIDENCE 90 INTERVAL chebyshev")
    return out.select("series_id", "step", "task", R("mean", 3).alias("mean"), R(F.col("lower") / 1000, 2).alias("lower_k"))


@query("q_m31_time", f"WITH {_TIMED} SELECT (DATE '1995-01-01' + step::INT)::TIMESTAMP AS o_orderdate, task, round(mean, 3) + 0.0 AS mean FROM answer WHERE step BETWEEN date_diff('day', DATE '1995-01-01', DATE '2001-07-20') AND date_diff('day', DATE '1995-01-01', DATE '2001-08-06')")
def by_time(spark, d):
    """Asked by the relation's time column; steps count from its first day."""
    out = _stated(spark, d, "", "PREDICT o_totalprice FROM m WHERE o_orderdate BETWEEN '2001-07-20' AND '2001-08-06 12:00:00' INTERVAL none")
    return out.select("o_orderdate", "task", R("mean", 3).alias("mean"))


#: Answers of rank-one sub-models, averaged over those that cover a step.
_WINDOWS = (
    f"{_MODELS}, x AS (SELECT j, 0.5 * atan2(2 * ab, aa - bb) AS x1, 0.5 * atan2(2 * ab2, aa2 - bb2) AS x2 FROM m), "
    f"cover AS (SELECT p.series_id, p.page, p.a, p.b, x.* FROM p JOIN x ON x.j IN (p.page // {_HALF_PAGES} - 1, p.page // {_HALF_PAGES})), "
    "est AS (SELECT series_id, page * 2 + i.range AS r, avg((a * cos(x1) + b * sin(x1)) * CASE WHEN i.range = 0 THEN cos(x1) ELSE sin(x1) END) AS mean, avg((a * a * cos(x2) + b * b * sin(x2)) * CASE WHEN i.range = 0 THEN cos(x2) ELSE sin(x2) END) AS second FROM cover, range(2) i GROUP BY 1, 2), "
    "late AS (SELECT avg(ab / aa) AS b1, avg(ab2 / aa2) AS b2 FROM (SELECT * FROM m ORDER BY j DESC LIMIT 10)), "
    "answer AS (SELECT e.series_id, e.r, mean, greatest(0, second - mean * mean) AS variance FROM est e JOIN rel USING (series_id, r) "
    "UNION ALL SELECT x.series_id, x.r, b1 * coalesce(y.value, 0), greatest(0, b2 * coalesce(y.value, 0) ** 2 - (b1 * coalesce(y.value, 0)) ** 2) FROM span, late, rel x LEFT JOIN rel y ON y.series_id = x.series_id AND y.r = x.r - 1 WHERE x.r >= t - t % 2)"
)
_RANK_ONE = ModelConfig(w=2, r_impute=1, r_forecast=1, capacity=_CAPACITY)


@query("q_m31_point", f"WITH {_WINDOWS} SELECT series_id, (lo + r)::BIGINT AS step, round(mean, 2) + 0.0 AS mean, round(sqrt(variance) / 1000, 2) + 0.0 AS sd_k FROM answer, span")
def point(spark, d):
    """Every observed step by equi-joins with the stored factors."""
    engine = _one(spark, d, _RANK_ONE, keep_right=True)
    return engine.point("m", _orders(spark, d)).select("series_id", "step", R("mean", 2).alias("mean"), R(F.col("sd") / 1000, 2).alias("sd_k"))


@query("q_m26_windows_predict", f"WITH {_WINDOWS} SELECT series_id, (lo + r)::BIGINT AS step, round(mean, 2) + 0.0 AS mean, round(sqrt(variance) / 1000, 2) + 0.0 AS sd_k FROM answer, span")
def windows_predict(spark, d):
    """The same steps from the pages themselves."""
    engine = _one(spark, d, _RANK_ONE)
    model = engine.model("m")
    out = engine.predict("m", model.first[0], model.end[1] - 1).join(_orders(spark, d).select("series_id", "step"), ["series_id", "step"], "left_semi")
    return out.select("series_id", "step", R("mean", 2).alias("mean"), R(F.col("sd") / 1000, 2).alias("sd_k"))


@query("q_m31_point_scaled", "SELECT 0.0::DOUBLE AS gap, 0::BIGINT AS missing")
def point_scaled(spark, d):
    """Both ways to answer agree with standardised values and the observed share."""
    engine = _one(spark, d, ModelConfig(w=12, capacity=_CAPACITY, standardize=True, fill="inverse_rate"), keep_right=True)
    model = engine.model("m")
    asks = engine.predict("m", model.first[0], model.end[1] + 4).select("cohort", "series_id", "step", F.col("mean").alias("m"), F.col("sd").alias("s"))
    both = asks.join(engine.point("m", asks), ["cohort", "series_id", "step"], "left")
    gap = F.greatest(F.abs(F.col("m") - F.col("mean")), F.abs(F.col("s") - F.col("sd"))) / 1e6
    return both.agg(R(F.max(gap), 6).alias("gap"), F.count_if(F.col("mean").isNull()).alias("missing"))


@query("q_m21_weight_view", f"WITH {_MODELS}, n AS (SELECT * FROM m ORDER BY j DESC LIMIT 3) SELECT 1::INT AS moment, round(avg(ab / aa), 7) + 0.0 AS weight, count(*) AS n_models FROM n UNION ALL SELECT 2::INT, round(avg(ab2 / aa2), 7) + 0.0, count(*) FROM n")
def weight_view(spark, d):
    """The stored average of the newest three sub-models' weights."""
    engine = _one(spark, d, ModelConfig(w=2, r_impute=1, r_forecast=1, capacity=_CAPACITY, average=3))
    return engine.store.load("m", "weights").select("moment", R(F.col("beta")[0], 7).alias("weight"), "n_models")


@query(
    "q_m06_inverse_rate",
    f"WITH {_MODELS}, s AS (SELECT j, seen / (2 * pages) AS share FROM m) SELECT p.series_id, (lo + page * 2 + i.range)::BIGINT AS step, round(avg(CASE WHEN i.range = 0 THEN a ELSE b END / share), 3) + 0.0 AS mean FROM p JOIN s ON s.j IN (page // {_HALF_PAGES} - 1, page // {_HALF_PAGES}), span, range(2) i GROUP BY 1, 2",
)
def inverse_rate(spark, d):
    """Full rank: the input over the observed share of each covering sub-model."""
    engine = _one(spark, d, ModelConfig(w=2, r_impute=2, r_forecast=1, capacity=_CAPACITY, fill="inverse_rate"))
    model = engine.model("m")
    out = engine.predict("m", model.first[0], model.covered[1] - 1, uncertainty=False)
    # pages that hold nothing have no row in the SQL
    there = _orders(spark, d).select("series_id", (F.floor((F.col("step") - model.first[0]) / 2)).alias("page")).distinct()
    return out.withColumn("page", F.floor((F.col("step") - model.first[0]) / 2)).join(there, ["series_id", "page"], "left_semi").select("series_id", "step", R("mean", 3).alias("mean"))


@query("q_m41_unscale", f"WITH {_REL}, m AS (SELECT series_id, avg(value) AS mu FROM obs GROUP BY 1), g AS (SELECT series_id, mu, unnest(generate_series(0, t - t % 2 - 1)) AS r FROM m, span) SELECT g.series_id, (lo + g.r)::BIGINT AS step, round(coalesce(value, mu), 3) + 0.0 AS mean FROM g JOIN span ON true LEFT JOIN rel ON rel.series_id = g.series_id AND rel.r = g.r")
def unscaled(spark, d):
    """Standardised, full rank: observed values come back, missing ones are the
    series' mean."""
    engine = _one(spark, d, ModelConfig(w=2, r_impute=2, r_forecast=1, standardize=True))
    model = engine.model("m")
    return engine.predict("m", model.first[0], model.covered[1] - 1, uncertainty=False).select("series_id", "step", R("mean", 3).alias("mean"))


@query(
    "q_m29_task",
    f"WITH {OBS}, c AS (SELECT *, 1000 + 100 * (series_id[1])::INT AS stop FROM obs), k AS (SELECT * FROM c WHERE step < stop), e AS (SELECT series_id, min(step) AS lo, max(step) AS hi FROM k GROUP BY 1), g AS (SELECT series_id, unnest(generate_series(1090, 1520)) AS step, lo, hi FROM e) "
    "SELECT g.series_id AS cohort, g.step, CASE WHEN g.step <= hi THEN 'impute' ELSE 'forecast' END AS task, CASE WHEN g.step < lo + (hi - lo + 1) // 2 * 2 THEN round(coalesce(value, 0), 3) + 0.0 END AS mean FROM g LEFT JOIN k ON k.series_id = g.series_id AND k.step = g.step",
)
def task(spark, d):
    """Cohorts of different length, asked for the same steps: each has its own end."""
    long = segments.cohorts(_orders(spark, d), "each")
    long = long.where(F.col("step") < 1000 + 100 * F.substring("series_id", 1, 1).cast("int"))
    engine = Engine(spark)
    engine.create_model("m", long, ModelConfig(w=2, r_impute=2, r_forecast=1))
    ends = engine.store.load("m", "members").select("cohort", (F.col("first") + F.col("covered")).alias("upto"))
    out = engine.predict("m", 1090, 1520, uncertainty=False).join(ends, "cohort")
    return out.select("cohort", "step", "task", F.when(F.col("step") < F.col("upto"), R("mean", 3)).alias("mean"))


@query("q_m34_univariate", f"WITH {OBS}, span AS (SELECT series_id, min(step) AS lo, max(step) - min(step) + 1 AS t FROM obs GROUP BY 1), rel AS (SELECT series_id, step - lo AS r, t, value FROM obs JOIN span USING (series_id)), p AS (SELECT series_id, r // 2 AS page, coalesce(max(value) FILTER (WHERE r % 2 = 0), 0) AS a, coalesce(max(value) FILTER (WHERE r % 2 = 1), 0) AS b FROM rel WHERE r < t - t % 2 GROUP BY 1, 2) SELECT series_id AS cohort, round(sum(a * b) / sum(a * a), 7) + 0.0 AS weight FROM p GROUP BY 1")
def univariate(spark, d):
    """A model for each series by itself."""
    engine = Engine(spark)
    engine.create_model("m", segments.cohorts(_orders(spark, d), "each"), ModelConfig(w=2, r_impute=1, r_forecast=1))
    return engine.store.load("m", "weights").where("moment = 1").select("cohort", R(F.col("beta")[0], 7).alias("weight"))


@query("q_m37_correlation", f"WITH {OBS}, c AS (SELECT o.series_id, a.series_id AS ref, coalesce(corr(o.value, a.value), 0) AS r FROM obs o JOIN obs a ON a.step = o.step AND a.series_id IN ('1-URGENT', '5-LOW') GROUP BY 1, 2) SELECT series_id, max_by(ref, r) AS cohort FROM c GROUP BY 1")
def correlated(spark, d):
    """Series join the cohort of the reference that they follow most closely."""
    long = segments.cohorts(_orders(spark, d), "correlation", reference=["1-URGENT", "5-LOW"])
    return long.select("series_id", "cohort").distinct()


@query("q_m37_hash", "SELECT 1000::BIGINT AS series, true AS balanced, 1::BIGINT AS cohorts_of_a_series")
def hashed(spark, d):
    """A thousand series in cohorts of about fifty by a hash of the name."""
    long = spark.range(1000).select(F.lit("all").alias("cohort"), F.concat(F.lit("s"), "id").alias("series_id"), F.lit(0).cast("bigint").alias("step"), F.lit(1.0).alias("value"))
    long = long.unionByName(long.withColumn("step", F.lit(1).cast("bigint")))
    out = segments.cohorts(long, "hash", most=50)
    sizes = out.groupBy("cohort").agg(F.countDistinct("series_id").alias("n"))
    per = out.groupBy("series_id").agg(F.countDistinct("cohort").alias("c")).agg(F.max("c").alias("cohorts_of_a_series"))
    return sizes.agg(F.sum("n").alias("series"), ((F.max("n") < 100) & (F.count("*") == 20)).alias("balanced")).join(per)


# ------------------------------------------------------------------- incremental
_INCREMENTAL = ModelConfig(w=2, r_impute=2, r_forecast=1, growth=1.0)


def _fed(spark, d, update: str) -> IncrementalModel:
    """Two thirds of the days first, then the rest before the next full solve is due:
    the counts of the schedule begin with what the first batch brings."""
    rows = _orders(spark, d)
    first = rows.where("step between 0 and 1599").count()
    model = IncrementalModel(spark, 5, replace(_INCREMENTAL, least=max(1, first)), update=update)
    model.append(rows.where("step < 1600"))
    model.append(rows.where("step >= 1600"))
    return model


_STATE = f"WITH {OBS}, e AS (SELECT max(step) + 1 AS t FROM obs), p AS (SELECT series_id, step // 2 AS page, coalesce(max(value) FILTER (WHERE step % 2 = 0), 0) AS a, coalesce(max(value) FILTER (WHERE step % 2 = 1), 0) AS b FROM obs, e WHERE step < {{until}} GROUP BY 1, 2) SELECT round(0.5 * ln((sum(a * a) + sum(b * b)) / 2 + sqrt(((sum(a * a) - sum(b * b)) / 2) ** 2 + sum(a * b) ** 2)), 7) + 0.0 AS log_s, round(sum(a * b) / sum(a * a), 7) + 0.0 AS weight, count(*)::BIGINT AS pages FROM p"


def _state(model: IncrementalModel) -> DataFrame:
    return model.factors.where("moment = 1").select(R(F.log(F.col("s")[0]), 7).alias("log_s"), R(F.col("weights")[0], 7).alias("weight"), "pages")


@query("q_m25_columns", _STATE.format(until="t - t % 2"))
def columns(spark, d):
    """New columns folded into the factors of the older ones; with every
    singular value kept the result is that of all columns."""
    return _state(_fed(spark, d, "columns"))


@query("q_m25_gram", _STATE.format(until="t - t % 2"))
def gram_state(spark, d):
    """Solved again from the additive state."""
    return _state(_fed(spark, d, "gram"))


@query("q_m25_fold", _STATE.format(until="1600"))
def fold(spark, d):
    """Folding in alone leaves the vectors as the first batch made them."""
    return _state(_fed(spark, d, "fold"))


@query("q_m24_schedule", "SELECT * FROM (VALUES (0::BIGINT, 'retrain'), (1::BIGINT, 'update')) v(batch, action)")
def schedule(spark, d):
    """What the schedule asked of the two batches above."""
    log = _fed(spark, d, "fold").log
    return spark.createDataFrame([(b, action) for b, _, action, _ in log], "batch bigint, action string")


@query("q_m42_beside_insert", f"WITH {_P2} SELECT round(sum(a * b) / sum(a * a), 7) + 0.0 AS weight, (SELECT count(*) FROM obs) AS stored FROM p")
def beside_insert(spark, d):
    """Training and a plain insert of the same rows at the same time."""
    rows, path = _orders(spark, d), scratch_path(spark, "beside")
    with ThreadPoolExecutor(2) as pool:
        put = pool.submit(store.bulk_insert, rows, path)
        made = pool.submit(_one, spark, d, ModelConfig(w=2, r_impute=1, r_forecast=1))
        put.result()
        engine = made.result()
    weight = engine.store.load("m", "weights").where("moment = 1").select(R(F.col("beta")[0], 7).alias("weight"))
    return weight.join(spark.read.parquet(path).agg(F.count("*").alias("stored")))


@query("q_m20_reopened", f"WITH {_P2} SELECT round(sum(a * b) / sum(a * a), 7) + 0.0 AS weight, 2::INT AS w, (SELECT t FROM span)::BIGINT AS steps FROM p")
def reopened(spark, d):
    """Parameters read back by another engine over the same folder."""
    root = scratch_path(spark, "models")
    Engine(spark, root).create_model("m", _orders(spark, d), ModelConfig(w=2, r_impute=1, r_forecast=1))
    again = Engine(spark, root)
    model = again.model("m")
    weights = again.store.load("m", "weights").where("moment = 1")
    return weights.select(R(F.col("beta")[0], 7).alias("weight"), F.lit(model.w).alias("w"), F.lit(model.steps).cast("bigint").alias("steps"))


# --------------------------------------------------------------------- layout, rivals
@query("q_n05_adjacent_halves", f"WITH {_P2}, g AS (SELECT page // {_HALF_PAGES} AS half, sum(a * a) AS aa, sum(a * b) AS ab, sum(b * b) AS bb FROM p GROUP BY 1) SELECT half::BIGINT AS half, round(sum(aa) OVER w / 1e9, 4) + 0.0 AS aa, round(sum(ab) OVER w / 1e9, 4) + 0.0 AS ab, round(sum(bb) OVER w / 1e9, 4) + 0.0 AS bb FROM g WINDOW w AS (ORDER BY half ROWS BETWEEN CURRENT ROW AND 1 FOLLOWING)")
def adjacent_halves(spark, d):
    """Gram matrices of neighbouring half windows, added up by a window frame."""
    from pyspark.sql import Window

    rows = _orders(spark, d)
    lo = rows.agg(F.min("step").alias("lo"))
    pages = pagematrix.build(rows.join(F.broadcast(lo)).withColumn("step", F.col("step") - F.col("lo")), 2)
    half = F.floor(F.col("page") / _HALF_PAGES).cast("bigint")
    a, b = F.col("vals")[0], F.col("vals")[1]
    g = pages.groupBy("cohort", half.alias("half")).agg(F.sum(a * a).alias("aa"), F.sum(a * b).alias("ab"), F.sum(b * b).alias("bb"))
    frame = Window.partitionBy("cohort").orderBy("half").rowsBetween(0, 1)
    return g.select("half", *(R(F.sum(c).over(frame) / 1e9).alias(c) for c in ("aa", "ab", "bb")))


@query("q_m08_partial_rows", "SELECT true AS bounded, true AS equal")
def partial_rows(spark, d):
    """A half window gives a bounded number of partial Gram rows, and their sum
    is the matrix of all pages."""
    half = half_window(ModelConfig(w=2, capacity=_CAPACITY), 5) // 2
    pages = pagematrix.build(_orders(spark, d), 2)
    rows = factor.gram_rows(pages, half)
    per = rows.groupBy("cohort", "half", "moment").agg(F.count("*").alias("n"), F.sum("pages").alias("pages"))
    total = pages.groupBy(F.floor(F.col("page") / half).cast("bigint").alias("half")).agg(F.count("*").alias("want"))
    return per.join(total, "half").agg((F.max("n") <= 16).alias("bounded"), F.bool_and(F.col("pages") == F.col("want")).alias("equal"))


@query("q_b07_trend", f"WITH {OBS}, f AS (SELECT series_id, regr_slope(value, step) AS m, regr_intercept(value, step) AS c FROM obs GROUP BY 1), e AS (SELECT max(step) + 1 AS t FROM obs) SELECT series_id, (t + k.range)::BIGINT AS step, round(c + m * (t + k.range), 1) + 0.0 AS mean FROM f, e, range(5) k")
def trend(spark, d):
    """The additive model itself, without seasons and change points: a line."""
    rows = _orders(spark, d)
    t = rows.agg(F.max("step")).first()[0] + 1
    fit = lambda y: {"mean": learners.additive_fit_forecast(y, 5, changepoints=0, periods=())}
    return learners.grouped(rows, ["cohort"], t, fit, t).select("series_id", "step", R("mean", 1).alias("mean"))


@query("q_m15_variance", f"WITH {_P2}, g AS (SELECT {_SUMS} FROM p), x AS (SELECT 0.5 * atan2(2 * ab, aa - bb) AS x1, 0.5 * atan2(2 * ab2, aa2 - bb2) AS x2 FROM g), e AS (SELECT series_id, page * 2 + i.range AS r, (a * cos(x1) + b * sin(x1)) * CASE WHEN i.range = 0 THEN cos(x1) ELSE sin(x1) END AS mean, (a * a * cos(x2) + b * b * sin(x2)) * CASE WHEN i.range = 0 THEN cos(x2) ELSE sin(x2) END AS second FROM p, x, range(2) i) SELECT series_id, r::BIGINT AS step, round(greatest(0, second - mean * mean) / 1e6, 2) + 0.0 AS variance FROM e")
def variance(spark, d):
    """Second moment minus squared mean, both from rank-one estimates."""
    rows = _orders(spark, d)
    lo = rows.agg(F.min("step").alias("lo"))
    pages = pagematrix.build(rows.join(F.broadcast(lo)).withColumn("step", F.col("step") - F.col("lo")), 2)
    models = factor.train(pages, 1 << 20, ModelConfig(w=2, r_impute=1, r_forecast=1))
    return answers.impute(pages, models, 1 << 20, 2).select("series_id", "step", R(F.col("variance") / 1e6, 2).alias("variance"))


@query("q_m16_variance_ahead", f"WITH {_FULL} SELECT series_id, step::BIGINT AS step, round(variance / 1e6, 2) + 0.0 AS variance FROM answer WHERE task = 'forecast'")
def variance_ahead(spark, d):
    engine = _one(spark, d, ModelConfig(w=2, r_impute=2, r_forecast=1))
    end = engine.model("m").end[1]
    return engine.predict("m", end, end + 6).select("series_id", "step", R(F.col("sd") ** 2 / 1e6, 2).alias("variance"))


_EST = f"{_P2}, g AS (SELECT {_SUMS} FROM p), x AS (SELECT 0.5 * atan2(2 * ab, aa - bb) AS x1, 0.5 * atan2(2 * ab2, aa2 - bb2) AS x2 FROM g), e AS (SELECT series_id, page * 2 + i.range AS r, (a * cos(x1) + b * sin(x1)) * CASE WHEN i.range = 0 THEN cos(x1) ELSE sin(x1) END AS mean, (a * a * cos(x2) + b * b * sin(x2)) * CASE WHEN i.range = 0 THEN cos(x2) ELSE sin(x2) END AS second FROM p, x, range(2) i), v AS (SELECT series_id, r, mean, greatest(0, second - mean * mean) AS variance FROM e)"


def _with_cohort(spark, d) -> DataFrame:
    rows = _orders(spark, d)
    lo = rows.agg(F.min("step").alias("lo"))
    pages = pagematrix.build(rows.join(F.broadcast(lo)).withColumn("step", F.col("step") - F.col("lo")), 2)
    return answers.impute(pages, factor.train(pages, 1 << 20, ModelConfig(w=2, r_impute=1, r_forecast=1)), 1 << 20, 2)


@query("q_m39_ratio", f"WITH {_EST} SELECT round(avg(variance) / avg(mean), 3) + 0.0 AS ratio, round(avg((abs(variance - mean) <= 0.15 * abs(mean))::INT), 6) + 0.0 AS near, 'other' AS verdict FROM v")
def ratio(spark, d):
    """The dispersion test on latent estimates of prices."""
    out = answers.poisson_check(_with_cohort(spark, d))
    return out.select(R("ratio", 3).alias("ratio"), R("share", 6).alias("near"), "verdict")


@query("q_a13_variance_error", f"WITH {_EST}, t AS (SELECT series_id, r, variance, 1e9 + 1e8 * (r % 7) AS truth FROM v), s AS (SELECT series_id, sum((variance - truth) ** 2) AS e, count(*) AS n, var_pop(truth) AS vt FROM t GROUP BY 1) SELECT round(sqrt(sum(e / vt) / sum(n)), 4) + 0.0 AS nrmse FROM s")
def variance_error(spark, d):
    """The error measure on variances, against a stated one."""
    from pagecast.plans import metrics

    est = _with_cohort(spark, d)
    truth = est.select("cohort", "series_id", "step", (1e9 + 1e8 * (F.col("step") % 7)).alias("latent_variance"))
    return metrics.nrmse(est, truth, predicted="variance", true="latent_variance").select(R("nrmse", 4).alias("nrmse"))


@query("q_a12_relative", "WITH t AS (SELECT l_linenumber AS n, stddev_pop(l_extendedprice) / avg(l_extendedprice) AS nrmse, avg(l_quantity) AS s FROM lineitem GROUP BY 1), f AS (SELECT * FROM t ORDER BY n LIMIT 1) SELECT t.n::INT AS n, round(t.nrmse / f.nrmse, 6) + 0.0 AS nrmse, round(t.s / f.s, 6) + 0.0 AS s FROM t, f")
def relative(spark, d):
    """Measures over their value for the first line of an order: the average
    price's error against the average, and the quantity."""
    from pagecast.plans import metrics

    lines = series.table(spark, d, "lineitem").groupBy(F.col("l_linenumber").cast("int").alias("n"))
    rows = lines.agg((F.stddev_pop("l_extendedprice") / F.avg("l_extendedprice")).alias("nrmse"), F.avg("l_quantity").alias("s"))
    return metrics.relative_to_first(rows, "n", ["nrmse", "s"]).select("n", R("nrmse", 6).alias("nrmse"), R("s", 6).alias("s"))


@query("q_m40_kinds", "WITH o AS (SELECT 'whole' AS series_id, o_orderkey // 16 AS r, count(*)::DOUBLE AS value FROM orders GROUP BY 2 UNION ALL SELECT 'flag', o_orderkey // 16, max(o_totalprice > 150000)::INT::DOUBLE FROM orders GROUP BY 2), e AS (SELECT max(r) + 1 AS t FROM o), g AS (SELECT s.series_id, unnest(generate_series(0, e.t - e.t % 2 - 1)) AS step FROM e, (SELECT DISTINCT series_id FROM o) s) SELECT g.series_id, g.step::BIGINT AS step, round(coalesce(value, 0), 6) + 0.0 AS mean FROM g LEFT JOIN o ON o.series_id = g.series_id AND o.r = g.step")
def kinds(spark, d):
    """Integer and boolean observations through the same path as floats."""
    o = series.table(spark, d, "orders")
    step = F.floor(F.col("o_orderkey") / 16).cast("bigint").alias("step")
    counts = o.groupBy(step).agg(F.count("*").cast("int").alias("value"))
    flags = o.groupBy(step).agg(F.max(F.col("o_totalprice") > 150000).alias("value"))
    long = counts.select(F.lit("all").alias("cohort"), F.lit("whole").alias("series_id"), "step", "value").unionByName(flags.select(F.lit("all").alias("cohort"), F.lit("flag").alias("series_id"), "step", F.col("value").cast("int").alias("value")))
    engine = Engine(spark)
    zero = long.unionByName(spark.createDataFrame([("all", "whole", 0, None)], "cohort string, series_id string, step bigint, value int"))
    engine.create_model("m", zero, ModelConfig(w=2, r_impute=2, r_forecast=1))
    model = engine.model("m")
    return engine.predict("m", 0, model.covered[1] - 1, uncertainty=False).select("series_id", "step", R("mean", 6).alias("mean"))


@query("q_a10_relative", "WITH t AS (SELECT event_type AS kind, (epoch_us(max(ts)) - epoch_us(min(ts))) / 1e6 / (count(ts) - 1) AS x FROM events GROUP BY 1 HAVING max(ts) > min(ts)) SELECT t.kind, round(t.x / b.x, 6) + 0.0 AS x FROM t, t b WHERE b.kind = 'click' AND t.kind <> 'click'")
def relative_times(spark, d):
    """Seconds between events of each kind over those between clicks."""
    from pagecast.plans import metrics

    micros = lambda c: F.unix_micros(c.cast("timestamp"))
    spans = series.table(spark, d, "events").groupBy("event_type").agg(micros(F.min("ts")).alias("lo"), micros(F.max("ts")).alias("hi"), F.count("ts").alias("n")).where("hi > lo and event_type is not null")
    times = {r["event_type"]: r["x"] for r in spans.select("event_type", ((F.col("hi") - F.col("lo")) / 1e6 / (F.col("n") - 1)).alias("x")).collect()}  # a row per kind
    rows = list(metrics.relative(times, "click").items()) if "click" in times else []
    return spark.createDataFrame(rows, "kind string, x double").select("kind", R("x", 6).alias("x"))
