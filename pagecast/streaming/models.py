"""Models over rows that keep arriving, and streaming queries over events.

Rows come in micro-batches. A batch's rows change pages; the changed pages are
written anew beside the older versions, and the Gram matrix of a half window, a
sum over its full pages, loses what a page gave before and gains what it gives
now. Late rows, series that lag behind and corrected values are therefore exact.
A batch reads only the pages it changes.

The schedule of counts says what follows: averages, a full solve of the changed
sub-models, or an update of theirs by the new columns alone.

Every batch has a number, and all tables of a batch lie under it; its entry in
the log is written last. A batch that is replayed after a failure writes the same
tables again, one that is in the log already changes nothing, and a model opened
over the same folder goes on where the log ends.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.cluster import drop_path, exists, scratch_path, ship
from pagecast.operators import answers, factor, pagematrix, segments
from pagecast.plans.config import ModelConfig, half_window

_PAGES = "cohort string, half bigint, salt int, series_id string, page bigint, vals array<double>, seen bigint, batch bigint, bucket bigint"
_MERGED = _PAGES + ", was_vals array<double>, was_seen bigint"
_SPANS = "cohort string, steps bigint, count bigint"
_DELTA = "cohort string, half bigint, salt int, series_id string, page bigint, vals array<double>, seen bigint, sign int"
_LOG = "batch bigint, count bigint, action string, model_idx bigint"
_KEY = ["cohort", "half", "salt", "series_id", "page"]


class IncrementalModel:
    """Batch by batch the same Gram state as one training over everything.

    ``update`` says what a batch between two full solves does to the sub-models
    it changes: 'gram' solves them again from the state (exact), 'columns' folds
    the new pages into the truncated factors, 'fold' leaves the vectors as they
    are. A sub-model whose older pages changed is always solved again. The last
    ``keep`` versions of the state stay, so that whoever reads beside the writer
    finds the one that was newest when it looked.
    """

    def __init__(self, spark: SparkSession, n_series: int, config: ModelConfig, root: str | None = None, update: str = "gram", keep: int = 2):
        if config.w is None:
            raise ValueError("a model over a stream needs its page height beforehand")
        if update not in ("gram", "columns", "fold"):
            raise ValueError(f"unknown update {update}")
        if keep < 2:
            raise ValueError("readers need the version before the newest")
        self.spark, self.n, self.config, self.update, self.keep = spark, n_series, config, update, keep
        self.half_pages = half_window(config, n_series) // config.w
        self.root = (root or scratch_path(spark, "stream-model")).rstrip("/")
        self.log: list[tuple[int, int, str, int]] = []
        if exists(spark, f"{self.root}/log"):
            rows = spark.read.schema(_LOG).parquet(f"{self.root}/log").orderBy("batch").collect()  # one short row a batch
            self.log = [tuple(r) for r in rows]

    # ------------------------------------------------------------------- state
    @property
    def last(self) -> int:
        return self.log[-1][0] if self.log else -1

    @property
    def count(self) -> int:
        return self.log[-1][1] if self.log else 0

    def _path(self, table: str, batch: int) -> str:
        return f"{self.root}/{table}/b{batch:012d}"

    def _read(self, table: str, schema: str, batch: int | None = None) -> DataFrame:
        batch = self.last if batch is None else batch
        path = self._path(table, batch)
        if batch < 0 or not exists(self.spark, path):
            return self._none(schema)
        return self.spark.read.schema(schema).parquet(path)

    def _none(self, schema: str) -> DataFrame:
        """No rows, in a form that the optimiser takes joins away for."""
        return self.spark.createDataFrame([], schema).where("false")

    def _pages(self) -> DataFrame:
        """All committed versions of pages."""
        paths = [self._path("pages", b) for b, *_ in self.log]
        if not paths:
            return self._none(_PAGES)
        return self.spark.read.schema(_PAGES).parquet(*paths)

    @staticmethod
    def _newest(versions: DataFrame) -> DataFrame:
        return versions.groupBy(*_KEY).agg(F.max_by(F.struct("vals", "seen"), "batch").alias("p")).select(*_KEY, "p.vals", "p.seen")

    @property
    def gram(self) -> DataFrame:
        return self._read("gram", factor.GRAM_SCHEMA)

    @property
    def factors(self) -> DataFrame:
        return self._read("factors", factor.MODEL_SCHEMA)

    def weights(self) -> DataFrame:
        return answers.weight_view(self.factors, self.config.average)

    # ------------------------------------------------------------------ append
    def append(self, batch: DataFrame, batch_id: int | None = None) -> None:
        """batch(cohort, series_id, step, value): new rows, or new values of
        older ones; of several values for one step in a batch the greatest counts.
        Steps are counted from 0; null and NaN values change nothing."""
        number = self.last + 1 if batch_id is None else batch_id
        if number <= self.last:
            return
        ship(self.spark)
        w, spark = self.config.w, self.spark
        rows = batch.select("cohort", "series_id", F.col("step").cast("bigint").alias("rel"), F.col("value").cast("double").alias("value")).where("rel >= 0 and not isnan(value)")
        rows = rows.groupBy("cohort", "series_id", "rel").agg(F.max("value").alias("value"))
        changed = pagematrix.gathered(rows, w, self.half_pages, pagematrix.salts(self.n * self.half_pages, w))
        if self.log:  # used twice below; the first batch has no pages to be compared with
            path = self._path("changed", number)
            changed.write.mode("overwrite").parquet(path)
            changed = spark.read.schema("cohort string, half bigint, salt int, series_id string, page bigint, vals array<double>, seen bigint").parquet(path)

        # versions of the changed pages, each beside the one before it
        before, stored = self._read("spans", _SPANS), self._pages()
        old = self._newest(stored.join(changed.select(*_KEY), _KEY, "left_semi"))
        merged = changed.join(old.select(*_KEY, F.col("vals").alias("was_vals"), F.col("seen").alias("was_seen")), _KEY, "left")
        vals = F.when(F.col("was_vals").isNull(), F.col("vals")).otherwise(F.zip_with("vals", "was_vals", lambda a, b: F.coalesce(a, b)))
        merged = merged.withColumn("vals", vals).withColumn("seen", F.size(F.filter("vals", lambda x: x.isNotNull())).cast("bigint"))
        path = self._path("pages", number)
        merged.select(*_KEY, "vals", "seen", F.lit(number).cast("bigint").alias("batch"), F.col("half").alias("bucket"), "was_vals", "was_seen").write.mode("overwrite").parquet(path)
        written = spark.read.schema(_MERGED).parquet(path)

        end = F.col("page") * w + w - F.aggregate(F.reverse("vals"), F.struct(F.lit(0).alias("n"), F.lit(False).alias("stop")), lambda s, x: F.struct((s["n"] + F.when(s["stop"] | x.isNotNull(), 0).otherwise(1)).alias("n"), (s["stop"] | x.isNotNull()).alias("stop")))["n"]
        grown = written.groupBy("cohort").agg(F.max(end).alias("top"), F.sum(F.col("seen") - F.coalesce("was_seen", F.lit(0))).alias("more"))
        zero = lambda c: F.coalesce(c, F.lit(0)).cast("bigint")
        after = before.withColumnRenamed("steps", "was").join(grown, "cohort", "full").select("cohort", F.greatest(zero("was"), zero("top")).alias("steps"), (zero("count") + zero("more")).alias("count"), zero("was").alias("was"))
        after.write.mode("overwrite").parquet(self._path("spans", number))
        edges = self._read("spans", _SPANS + ", was bigint", number)
        count = edges.agg(F.sum("count")).first()[0] or 0

        # what full pages gave before, and what they give now; also the pages left open behind the last full one
        edges = edges.select("cohort", "was", "steps")
        full = lambda df, edge: df.join(edges, "cohort").where((F.col("page") + 1) * w <= F.col(edge)).select(*_KEY, "vals", "seen")
        lost = full(written.where("was_vals is not null").select(*_KEY, F.col("was_vals").alias("vals"), F.col("was_seen").alias("seen")), "was")
        open_ = self._newest(stored.join(before.select("cohort", "steps"), "cohort").where((F.col("page") + 1) * w > F.col("steps")).drop("steps"))
        untouched = open_.join(written.select(*_KEY), _KEY, "left_anti")
        won = full(written.select(*_KEY, "vals", "seen"), "steps").unionByName(full(untouched, "steps"))
        delta = won.withColumn("sign", F.lit(1)).unionByName(lost.withColumn("sign", F.lit(-1)))
        path = self._path("delta", number)
        delta.repartition("cohort", "half", "salt").sortWithinPartitions("cohort", "half", "sign").write.mode("overwrite").parquet(path)
        delta = spark.read.schema(_DELTA).parquet(path)
        gram = factor.merge_gram(self.gram, factor.gram_rows(delta, self.half_pages))
        gram.write.mode("overwrite").parquet(self._path("gram", number))

        kind, model = segments.action(count, self.count, self.config)
        if kind == "average":
            found = self.factors
        else:
            found = self._refreshed(number, delta, kind)
        found.write.mode("overwrite").parquet(self._path("factors", number))
        entry = [F.lit(number).cast("bigint").alias("batch"), F.lit(count).cast("bigint").alias("count"), F.lit(kind).alias("action"), F.lit(model).cast("bigint").alias("model_idx")]
        spark.range(0, 1, 1, 1).select(*entry).write.mode("append").parquet(f"{self.root}/log")
        self.log.append((number, count, kind, model))
        for table in ("changed", "delta"):
            drop_path(spark, self._path(table, number))
        # readers that opened the model before may still be at the version before
        for older, *_ in self.log[: -self.keep][-2:]:
            for table in ("gram", "factors", "spans"):
                drop_path(spark, self._path(table, older))

    def _refreshed(self, number: int, delta: DataFrame, kind: str) -> DataFrame:
        """Factors of all sub-models after a batch: those that it changed anew,
        the others as they are."""
        gram = self._read("gram", factor.GRAM_SCHEMA, number)
        ids = ["cohort", "model_idx"]
        touched = lambda df: factor.to_models(df.select("cohort", "half").distinct()).select(*ids).distinct()
        held = self.factors
        # a sub-model may become whole by a batch; there are no factors of it yet
        known = held.select(*ids).distinct()
        if kind == "retrain" or self.update == "gram":
            solved = touched(delta)
            grown = None
        else:
            won, lost = delta.where("sign = 1").drop("sign"), delta.where("sign = -1")
            fresh = touched(won).join(known, ids, "left_anti")
            solved = touched(lost).unionByName(fresh).distinct()
            grown = touched(won).join(known, ids, "left_semi").join(solved, ids, "left_anti")
        anew = factor.solve(gram, self.config, only=solved)
        if grown is None or self.update == "fold":
            return held.join(solved, ids, "left_anti").unionByName(anew)
        rest = held.join(solved, ids, "left_anti").join(grown, ids, "left_anti")
        return rest.unionByName(anew).unionByName(self._widened(held.join(grown, ids, "left_semi"), won))

    def _widened(self, held: DataFrame, won: DataFrame) -> DataFrame:
        """Truncated factors with the new pages' columns folded in."""
        config = self.config
        columns = factor.to_models(won.select("cohort", "half", "vals", "seen")).select("cohort", "model_idx", "vals", "seen")

        def one(key, models: pd.DataFrame, pages: pd.DataFrame) -> pd.DataFrame:
            if not len(models) or not len(pages):
                return models
            z = np.nan_to_num(np.stack(pages["vals"].to_list()).astype(float)).T
            out = []
            for row in models.to_dict("records"):
                new = (z if row["moment"] == 1 else z * z) / row["share"]
                out.append(row | factor.widen(row, new, int(pages["seen"].sum()), config))
            return pd.DataFrame(out)

        return held.groupBy("cohort", "model_idx").cogroup(columns.groupBy("cohort", "model_idx")).applyInPandas(one, factor.MODEL_SCHEMA)

    def solve(self) -> DataFrame:
        """Factors of all sub-models from the additive state."""
        return factor.solve(self.gram, self.config)


def events_stream(spark: SparkSession, sf_dir: str, late: str = "1 hour", files_per_batch: int | None = None) -> DataFrame:
    """The events table as a file stream with a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet")
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(sf_dir).withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)


def run_once(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Everything available through a memory table (for small results)."""
    writer = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    query = writer.start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def run_to_files(df: DataFrame, label: str, mode: str = "append") -> DataFrame:
    """Everything available through files of the scratch folder: rows go from the
    tasks to the files, none to the driver. In complete mode the last batch is
    the result."""
    spark, out = df.sparkSession, scratch_path(df.sparkSession, label)
    numbers = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/b{number:012d}")
        numbers.append(number)

    query = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", scratch_path(spark, f"{label}-checkpoint")).trigger(availableNow=True).start()
    query.awaitTermination()
    written = [f"{out}/b{n:012d}" for n in sorted(set(numbers))]
    if not written:
        return spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(*(written[-1:] if mode == "complete" else written))


def hourly(events: DataFrame) -> DataFrame:
    """Tumbling hours by type; an hour is final once the watermark has passed."""
    return events.groupBy(F.window("at", "1 hour").alias("win"), "event_type").agg(F.count("*").alias("n")).select(F.col("win.start").alias("hour"), "event_type", "n")


def score(arriving: DataFrame, limits: DataFrame) -> DataFrame:
    """Stream-static join: flags arriving values outside their interval.
    limits(event_type, lower, upper) is an answer of a model, a row per series."""
    return arriving.join(limits, "event_type").withColumn("odd", ~F.col("value").between(F.col("lower"), F.col("upper")))


def click_then_purchase(events: DataFrame) -> DataFrame:
    """Stream-stream interval join: purchases within the hour after a click."""
    e = events.select("event_id", "user_id", "event_type", "at")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("at").alias("c_at"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("p_user"), F.col("at").alias("p_at"))
    near = (F.col("user_id") == F.col("p_user")) & (F.col("c_at") <= F.col("p_at")) & (F.col("c_at") > F.col("p_at") - F.expr("INTERVAL 1 HOUR"))
    return c.join(p, near).select("click", "purchase")


def to_incremental(events: DataFrame, model: IncrementalModel, checkpoint: str, origin: str) -> None:
    """Feed hourly means of the stream into an incremental model.

    The hours are a streaming aggregate in update mode: an hour whose rows come
    in several micro-batches, or late but within the watermark, is given again
    with its new mean, which replaces the older value.
    """
    from pagecast.operators.ingest import step_of

    hours = events.groupBy(F.window("at", "1 hour").alias("win"), "event_type").agg(F.avg("value").alias("value"))

    def feed(batch: DataFrame, number: int) -> None:
        step = step_of(F.col("win.start"), origin, "1 hour")
        model.append(batch.select(F.lit("all").alias("cohort"), F.col("event_type").alias("series_id"), step.alias("step"), "value"), number)

    query = hours.writeStream.foreachBatch(feed).outputMode("update").option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
