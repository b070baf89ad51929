"""The rest of the surface around predictions, each row with its SQL: bucketed
tables, Arrow exchange, kinds of aggregation, maps and structs, digests, null
handling, user-defined functions of every kind, and streams."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType

from pagecast.cluster import scratch_path
from pagecast.operators import pagematrix, relational
from pagecast.plans.config import ModelConfig
from pagecast.plans.engine import Engine
from pagecast.plans.registry import query
from pagecast.sources import series
from pagecast.sources.series import table as T
from pagecast.streaming import models as streams

R = relational.R


# --------------------------------------------------------------- storage, exchange
@query("q_s06_bucketed", "SELECT c_custkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Two tables bucketed by the join key are joined without an exchange."""
    tag = uuid.uuid4().hex[:12]
    for name, key, columns in (("orders", "o_custkey", ["o_custkey", "o_orderkey"]), ("customer", "c_custkey", ["c_custkey"])):
        T(spark, d, name).select(*columns).write.bucketBy(8, key).sortBy(key).saveAsTable(f"pagecast_{name}_{tag}", mode="overwrite", path=scratch_path(spark, name))
    o, c = (spark.table(f"pagecast_{n}_{tag}") for n in ("orders", "customer"))
    return o.hint("merge").join(c.hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_custkey").agg(F.count("*").alias("n"))


@query("q_s11_arrow", "SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def arrow_exchange(spark, d):
    """A small result out as an Arrow table and a pandas frame, and back in."""
    nation = T(spark, d, "nation").select("n_nationkey", "n_name", "n_regionkey").toArrow()  # 25 rows
    region = T(spark, d, "region").select("r_regionkey", "r_name").toPandas()  # 5 rows
    back = spark.createDataFrame(nation).join(spark.createDataFrame(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return back.select("n_nationkey", "n_name", "r_name")


@query("q_t04_ranges", "SELECT count(*) AS n, true AS ordered, true AS disjoint FROM orders")
def ranges(spark, d):
    """Range partitions, sorted within: the layout that files are written in."""
    laid = T(spark, d, "orders").select("o_orderdate", "o_orderkey").repartitionByRange(6, "o_orderdate", "o_orderkey").sortWithinPartitions("o_orderdate", "o_orderkey")
    laid = laid.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id())
    key = F.struct("o_orderdate", "o_orderkey")
    before = F.lag(key).over(Window.partitionBy("part").orderBy("at"))
    sorted_ = laid.select("part", key.alias("k"), (before.isNull() | (before < key)).alias("ok"))
    per = sorted_.groupBy("part").agg(F.count("*").alias("n"), F.bool_and("ok").alias("ok"), F.min("k").alias("lo"), F.max("k").alias("hi"))
    previous = F.lag("hi").over(Window.orderBy("part"))  # six rows
    return per.select("n", "ok", (previous.isNull() | (previous < F.col("lo"))).alias("apart")).agg(F.sum("n").alias("n"), F.bool_and("ok").alias("ordered"), F.bool_and("apart").alias("disjoint"))


# -------------------------------------------------------------------- aggregation
@query("q_g13_kinds", "SELECT o_orderpriority, sum(o_orderkey)::BIGINT AS keys, max(o_orderstatus) AS status, count(DISTINCT year(o_orderdate)) AS years FROM orders GROUP BY 1")
def kinds(spark, d):
    """Hash aggregation holds fixed-width sums, sort aggregation texts, object
    hash aggregation collections: one of each."""
    o = T(spark, d, "orders")
    by_hash = o.groupBy("o_orderpriority").agg(F.sum("o_orderkey").alias("keys"))
    by_sort = o.groupBy("o_orderpriority").agg(F.max("o_orderstatus").alias("status"))
    by_object = o.groupBy("o_orderpriority").agg(F.size(F.collect_set(F.year("o_orderdate"))).cast("bigint").alias("years"))
    return by_hash.join(by_sort, "o_orderpriority").join(by_object, "o_orderpriority")


# ---------------------------------------------------------------------- functions
@query("q_f06_maps", "SELECT c_custkey, 'n' || c_nationkey AS nation, (c_nationkey + 1)::BIGINT AS next, 2 AS size, c_custkey % 2 = 0 AS has_even FROM customer")
def maps(spark, d):
    entries = F.map_from_arrays(F.array(F.lit("nation"), F.when(F.col("c_custkey") % 2 == 0, "even").otherwise("odd")), F.array(F.concat(F.lit("n"), "c_nationkey"), F.lit("x")))
    inner = F.named_struct(F.lit("key"), F.col("c_nationkey"), F.lit("next"), (F.col("c_nationkey") + 1).cast("bigint"))
    rows = T(spark, d, "customer").select("c_custkey", entries.alias("m"), inner.alias("s"))
    changed = F.map_filter(F.transform_values("m", lambda k, v: F.when(k == "nation", v).otherwise(F.upper(v))), lambda k, v: v.isNotNull())
    return rows.select("c_custkey", F.element_at(changed, "nation").alias("nation"), F.col("s.next").alias("next"), F.size("m").alias("size"), F.map_contains_key("m", "even").alias("has_even"))


@query("q_f09_digests", "SELECT p_partkey, md5(p_name) AS md5, sha256(p_name) AS sha FROM part")
def digests(spark, d):
    return T(spark, d, "part").select("p_partkey", F.md5(F.col("p_name").cast("binary")).alias("md5"), F.sha2(F.col("p_name").cast("binary"), 256).alias("sha"))


@query("q_f09_sketches", "SELECT true AS near, true AS same FROM (SELECT 1)")
def sketches(spark, d):
    """Sketches of two halves, merged, against one over all rows and the truth."""
    o = T(spark, d, "orders").select("o_custkey", (F.col("o_orderkey") % 2).alias("half"))
    halves = o.groupBy("half").agg(F.hll_sketch_agg("o_custkey", 12).alias("s"))
    merged = halves.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("merged"))
    whole = o.agg(F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey", 12)).alias("whole"), F.countDistinct("o_custkey").alias("exact"))
    both = merged.join(whole)
    return both.select((F.abs(F.col("whole") / F.col("exact") - 1) < 0.05).alias("near"), (F.abs(F.col("merged") / F.col("whole") - 1) < 0.01).alias("same"))


@query("q_f12_nulls", "SELECT event_id, coalesce(nullif(event_type, 'click'), 'none') AS kind, CASE WHEN nullif(event_type, 'click') IS NOT NULL THEN 1 ELSE 0 END AS known, nullif(value, 0) IS NULL AS empty FROM events")
def nulls(spark, d):
    kind = F.nullif(F.col("event_type"), F.lit("click"))
    return T(spark, d, "events").select("event_id", F.ifnull(kind, F.lit("none")).alias("kind"), F.nvl2(kind, F.lit(1), F.lit(0)).alias("known"), F.nullifzero(F.col("value")).isNull().alias("empty"))


# ------------------------------------------------------------ user-defined functions
@query("q_d02_table_function", "SELECT c_custkey, count(o_orderkey) AS n FROM customer JOIN orders ON o_custkey = c_custkey WHERE c_custkey BETWEEN 10 AND 60 GROUP BY 1")
def table_function(spark, d):
    """A parameterised query as an SQL table function."""
    T(spark, d, "orders").createOrReplaceTempView("pagecast_orders")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pagecast_counts(lo INT, hi INT) RETURNS TABLE(c_custkey BIGINT, n BIGINT) RETURN SELECT CAST(o_custkey AS BIGINT), count(*) FROM pagecast_orders WHERE o_custkey BETWEEN pagecast_counts.lo AND pagecast_counts.hi GROUP BY o_custkey")
    return spark.sql("SELECT * FROM pagecast_counts(10, 60)")


@query("q_d03_python_table_function", "SELECT n_nationkey, unnest(generate_series(1, n_regionkey::BIGINT + 1))::INT AS k FROM nation")
def python_table_function(spark, d):
    @F.udtf(returnType="k int")
    class Upto:
        def eval(self, n: int):
            for k in range(1, n + 1):
                yield (k,)

    spark.udtf.register("pagecast_upto", Upto)
    T(spark, d, "nation").createOrReplaceTempView("pagecast_nation")
    return spark.sql("SELECT n_nationkey, k FROM pagecast_nation, LATERAL pagecast_upto(CAST(n_regionkey AS INT) + 1)")


@query("q_d04_pandas_arrow", "SELECT p_partkey, upper(p_name) AS name, (p_size * 2 + 1)::BIGINT AS twice FROM part")
def pandas_arrow(spark, d):
    @F.pandas_udf(StringType())
    def raised(names: pd.Series) -> pd.Series:
        return names.str.upper()

    @F.arrow_udf(LongType())
    def twice(sizes: pa.Array) -> pa.Array:
        import pyarrow.compute as pc

        return pc.add(pc.multiply(sizes.cast(pa.int64()), 2), 1)

    return T(spark, d, "part").select("p_partkey", raised("p_name").alias("name"), twice("p_size").alias("twice"))


@query("q_d05_groups", "WITH a AS (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1), b AS (SELECT c_custkey AS k, c_nationkey FROM customer) SELECT b.k::BIGINT AS k, coalesce(n, 0)::BIGINT AS n, c_nationkey::BIGINT AS nation FROM b LEFT JOIN a ON a.k = b.k")
def groups(spark, d):
    """Grouped map, and two inputs grouped together."""

    def counted(key, frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"k": [key[0]], "n": [len(frame)]})

    def joined(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        n = int(left["n"].iloc[0]) if len(left) else 0
        return pd.DataFrame({"k": right["k"], "n": n, "nation": right["nation"]})

    o = T(spark, d, "orders").select(F.col("o_custkey").cast("bigint").alias("k"))
    per = o.groupBy("k").applyInPandas(counted, "k bigint, n bigint")
    c = T(spark, d, "customer").select(F.col("c_custkey").cast("bigint").alias("k"), F.col("c_nationkey").cast("bigint").alias("nation"))
    return per.groupBy("k").cogroup(c.groupBy("k")).applyInPandas(joined, "k bigint, n bigint, nation bigint")


@query("q_d06_grouped_aggregate", "SELECT event_type, round(max(value) - min(value), 6) + 0.0 AS extent FROM events GROUP BY 1")
def grouped_aggregate(spark, d):
    @F.pandas_udf("double")
    def extent(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return T(spark, d, "events").groupBy("event_type").agg(extent("value").alias("e")).select("event_type", R("e", 6).alias("extent"))


@query("q_d07_batches", "SELECT doc_id, coalesce(length(text), 0)::BIGINT AS n FROM documents WHERE coalesce(length(text), 0) > 100")
def batches(spark, d):
    """Map over Arrow batches: rows may go."""

    def long_ones(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        for part in parts:
            n = pc.fill_null(pc.utf8_length(part.column(1)), 0).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([part.column(0), n], ["doc_id", "n"]).filter(pc.greater(n, 100))

    return T(spark, d, "documents").select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInArrow(long_ones, "doc_id bigint, n bigint")


# ------------------------------------------------------------------------- streams
_CUT = "TIMESTAMP '2024-01-16 00:00:00'"


def _in_files(spark, d, label: str) -> tuple[DataFrame, str]:
    """Events as a folder of files: the later half of the month arrives first,
    its very last moment by itself, and the earlier half after it, late."""
    folder = scratch_path(spark, label)
    events = T(spark, d, "events").select("event_id", "user_id", "event_type", "value", "ts")
    last = events.agg(F.max("ts")).first()[0]
    for part, rows in enumerate((events.where((F.col("ts") >= F.expr(_CUT)) & (F.col("ts") < last)), events.where(F.col("ts") == last), events.where(F.col("ts") < F.expr(_CUT)))):
        rows.coalesce(1).write.mode("append").parquet(f"{folder}/part={part}")
    return events, folder


def _stream(spark, events: DataFrame, folder: str, parts: str, late: str = "1 hour") -> DataFrame:
    read = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/{parts}")
    return read.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)


_HOURLY = "SELECT date_trunc('hour', ts) AS hour, event_type, count(*) AS n FROM events {where} GROUP BY 1, 2"


_LATE = f"ts < {_CUT} AND date_trunc('hour', ts) + INTERVAL 1 HOUR <= mark"


@query("q_r05_late_rows", f"WITH w AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events WHERE ts < (SELECT max(ts) FROM events)) SELECT count(*) FILTER (WHERE NOT ({_LATE})) AS counted, count(*) FILTER (WHERE {_LATE}) > 0 AS dropped FROM events, w")
def late_rows(spark, d):
    """Rows of windows behind the watermark are dropped and counted as dropped.
    A batch is judged by the watermark that the batch before it began with."""
    events, folder = _in_files(spark, d, "late")
    name = f"late_{uuid.uuid4().hex[:8]}"
    hours = streams.hourly(_stream(spark, events, folder, "part=*"))
    run = hours.writeStream.format("memory").queryName(name).outputMode("update").option("checkpointLocation", scratch_path(spark, "late-checkpoint")).trigger(availableNow=True).start()
    run.awaitTermination()
    dropped = sum(s["numRowsDroppedByWatermark"] for progress in run.recentProgress for s in progress["stateOperators"])
    return spark.table(name).groupBy("hour", "event_type").agg(F.max("n").alias("n")).agg(F.sum("n").alias("counted")).withColumn("dropped", F.lit(dropped > 0))


@query("q_r02_sliding", "SELECT h.hour, event_type, count(*) AS n FROM (SELECT *, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS hour FROM events) h GROUP BY 1, 2")
def sliding(spark, d):
    """Windows of two hours that begin every hour."""
    events = streams.events_stream(spark, d)
    out = events.groupBy(F.window("at", "2 hours", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("hour"), "event_type", "n")
    return streams.run_once(out, f"sliding_{uuid.uuid4().hex[:8]}", "complete").select(F.col("hour").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@query("q_r02_sessions", "WITH s AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM s) SELECT user_id, min(ts) AS began, count(*) AS n FROM g GROUP BY user_id, k")
def sessions(spark, d):
    """A user's session ends after six quiet hours."""
    events = streams.events_stream(spark, d)
    out = events.groupBy(F.session_window("at", "6 hours").alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("began"), "n")
    return streams.run_to_files(out, "sessions", "complete").select("user_id", F.col("began").cast("timestamp_ntz").alias("began"), "n")


@query("q_r07_scored", "WITH l AS (SELECT event_type, avg(value) - 1.959963984540054 * stddev_pop(value) AS lo, avg(value) + 1.959963984540054 * stddev_pop(value) AS hi FROM events GROUP BY 1) SELECT event_id, NOT (value BETWEEN lo AND hi) AS odd FROM events JOIN l USING (event_type)")
def scored(spark, d):
    """Arriving rows joined with intervals of a model: too few observations of a
    type's own kind, so its average and spread."""
    events = T(spark, d, "events")
    engine = Engine(spark)
    ranked = events.select(F.lit("all").alias("cohort"), F.col("event_type").alias("series_id"), F.row_number().over(Window.partitionBy("event_type").orderBy("event_id")).cast("bigint").alias("step"), "value")
    least = events.count() + 1  # more than there are, whatever the size of the table
    engine.create_model("m", ranked, ModelConfig(least=least, capacity=2 * least))
    limits = engine.predict("m", 0, 0).select(F.col("series_id").alias("event_type"), "lower", "upper")
    return streams.run_to_files(streams.score(streams.events_stream(spark, d), limits).select("event_id", "odd"), "scored")


@query("q_r06_restart", _HOURLY.format(where=""))
def restarted(spark, d):
    """A query that is started again over its checkpoint goes on where it was."""
    folder, out, checkpoint = (scratch_path(spark, x) for x in ("restart-in", "restart-out", "restart-checkpoint"))
    events = T(spark, d, "events").select("event_id", "user_id", "event_type", "value", "ts")
    for rows in (events.where(F.col("ts") < F.expr(_CUT)), events.where(F.col("ts") >= F.expr(_CUT))):
        rows.coalesce(1).write.mode("append").parquet(folder)

        def keep(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

        hours = streams.hourly(_stream(spark, events, folder, ""))
        hours.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    newest = spark.read.parquet(out).groupBy("hour", "event_type").agg(F.max_by("n", "batch").alias("n"))
    return newest.select(F.col("hour").cast("timestamp_ntz").alias("hour"), "event_type", "n")


@query("q_r03_model_state", "WITH o AS (SELECT event_type, (epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) // 3600000000 AS r, avg(value) AS value FROM events GROUP BY 1, 2), s AS (SELECT max(r) + 1 AS t FROM o), p AS (SELECT event_type, r // 2 AS page, coalesce(max(value) FILTER (WHERE r % 2 = 0), 0) AS a, coalesce(max(value) FILTER (WHERE r % 2 = 1), 0) AS b FROM o, s WHERE r < t - t % 2 GROUP BY 1, 2) SELECT round(sum(a * b) / sum(a * a), 7) + 0.0 AS weight, count(*)::BIGINT AS pages FROM p")
def model_state(spark, d):
    """A stream of events feeds a model through foreachBatch, in two files of
    which the second overlaps the first; the state is that of one training."""
    folder = scratch_path(spark, "state-in")
    events = T(spark, d, "events").select("event_id", "user_id", "event_type", "value", "ts")
    model = streams.IncrementalModel(spark, 5, ModelConfig(w=2, r_impute=1, r_forecast=1))
    checkpoint = scratch_path(spark, "state-checkpoint")
    for k in (0, 1):
        events.where(F.col("event_id") % 2 == k).coalesce(1).write.mode("append").parquet(folder)
    streams.to_incremental(_stream(spark, events, folder, "", "60 days"), model, checkpoint, "2024-01-01")
    row = model.factors.where("moment = 1")
    return row.select(R(F.col("weights")[0], 7).alias("weight"), "pages")


@query("q_m04_gathered", "SELECT true AS same")
def gathered(spark, d):
    """Pages from the one shuffle that serves the sums are the plain ones."""
    rows = series.orders_by_priority(spark, d)
    a = pagematrix.build(rows, 20, partial=True).select("series_id", "page", "vals", "seen")
    b = pagematrix.gathered(rows.withColumn("rel", F.col("step")), 20, 5, 3).select("series_id", "page", F.transform("vals", lambda x: F.coalesce(x, F.lit(0.0))).alias("vals"), "seen")
    both = a.join(b.withColumnsRenamed({"vals": "v", "seen": "s"}), ["series_id", "page"], "full")
    return both.agg(F.coalesce(F.bool_and(F.coalesce((F.col("vals") == F.col("v")) & (F.col("seen") == F.col("s")), F.lit(False))), F.lit(False)).alias("same"))

