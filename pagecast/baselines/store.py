"""Insert and look-up of the same rows without any model."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def bulk_insert(df: DataFrame, path: str, key: str = "step") -> None:
    """Rows in key order: the counterpart of an index on the key."""
    df.repartitionByRange(key).sortWithinPartitions(key).write.mode("overwrite").parquet(path)


def select_point(spark: SparkSession, path: str, at: int, key: str = "step") -> DataFrame:
    """One row; row groups are skipped by their statistics."""
    return spark.read.parquet(path).where(F.col(key) == at)


CAPABILITIES = [
    ("page matrix", True, True, True),
    ("recurrent network", True, False, False),
    ("probabilistic recurrent network", True, True, True),
    ("regularised matrix factorisation", True, False, True),
    ("additive model", False, False, True),
]


def capabilities(spark: SparkSession) -> DataFrame:
    """What each method can do: several series at once, variance, gaps."""
    return spark.createDataFrame(CAPABILITIES, "method string, multivariate boolean, variance boolean, gaps boolean")
