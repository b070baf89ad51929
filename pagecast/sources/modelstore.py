"""Models as Parquet tables beside the data.

pages: the stored rows, one page each, in folders by half window. factors: one
row per (cohort, model_idx, moment) with left vectors, singular values and
weights of both matrices. projectors: the left vectors again, by the half window
that they answer for. right: the right vectors by page. weights: the averaged
weights, a row per cohort and moment; betas: the same, a row per cohort, as
forecasts read them. members: one row per series. meta: the model's parameters
as JSON, written last: a model without it does not exist.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from pagecast.cluster import drop_path
from pagecast.operators.answers import weight_view

TABLES = ("pages", "factors", "projectors", "right", "weights", "betas", "members", "meta")
#: Folder column of the tables that lie in folders, and their order within a file.
FOLDERS = {
    "pages": ("bucket", ["cohort", "half", "salt", "page"]),
    "factors": ("idx_bucket", ["cohort", "model_idx", "moment"]),
    "projectors": ("idx_bucket", ["cohort", "half"]),
    "right": ("idx_bucket", ["cohort", "model_idx", "moment", "series_id", "page"]),
}


class ModelStore:
    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self._known: dict[tuple[str, str], DataFrame] = {}

    def path(self, name: str, table: str) -> str:
        return f"{self.root}/model={name}/{table}"

    def save(self, name: str, table: str, df: DataFrame) -> None:
        self._known.pop((name, table), None)
        if table in FOLDERS:
            folder, order = FOLDERS[table]
            if folder not in df.columns:
                df = df.withColumn(folder, F.floor(F.col("model_idx") / 1000).cast("bigint"))
            df.sortWithinPartitions(folder, *order).write.mode("overwrite").partitionBy(folder).parquet(self.path(name, table))
        else:
            df.write.mode("overwrite").parquet(self.path(name, table))
        # what is known of a table need not be read from its files
        schema = df.schema
        if table in FOLDERS:
            schema = StructType([f for f in schema if f.name != folder] + [f for f in schema if f.name == folder])
        self._known[name, table] = self.spark.read.schema(schema).parquet(self.path(name, table))

    def load(self, name: str, table: str) -> DataFrame:
        if (name, table) not in self._known:
            self._known[name, table] = self.spark.read.parquet(self.path(name, table))
        return self._known[name, table]

    def save_meta(self, name: str, text: str) -> None:
        self.spark.createDataFrame([(name, text)], "name string, held string").coalesce(1).write.mode("overwrite").parquet(self.path(name, "meta"))

    def load_meta(self, name: str) -> str | None:
        try:
            row = self.spark.read.schema("name string, held string").parquet(self.path(name, "meta")).first()
        except AnalysisException:
            return None
        return row["held"] if row else None

    def refresh_weight_view(self, name: str, average: int) -> DataFrame:
        self.save(name, "weights", weight_view(self.load(name, "factors"), average))
        return self.load(name, "weights")

    def forget(self, name: str, *tables: str) -> None:
        for table in tables:
            self._known.pop((name, table), None)
            drop_path(self.spark, self.path(name, table))

    def drop(self, name: str) -> None:
        for key in [k for k in self._known if k[0] == name]:
            del self._known[key]
        drop_path(self.spark, f"{self.root}/model={name}")
