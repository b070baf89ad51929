"""Series that the given tables contain, as long rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pagecast.operators.ingest import regularize

ORIGIN = "1995-01-01"
EVENTS_ORIGIN = "2024-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def orders_by_priority(spark: SparkSession, sf_dir: str, agg: str = "mean") -> DataFrame:
    """Daily order price (5 series)."""
    rows = table(spark, sf_dir, "orders").select("o_orderpriority", "o_orderdate", "o_totalprice")
    return regularize(rows, "o_orderdate", "o_totalprice", ["o_orderpriority"], "1 day", agg, ORIGIN)


def lineitem_by_flags(spark: SparkSession, sf_dir: str, agg: str = "mean") -> DataFrame:
    """Daily extended price by return flag and line status (6 series)."""
    rows = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", "l_shipdate", "l_extendedprice")
    return regularize(rows, "l_shipdate", "l_extendedprice", ["l_returnflag", "l_linestatus"], "1 day", agg, ORIGIN)


def events_by_type(spark: SparkSession, sf_dir: str, agg: str = "mean") -> DataFrame:
    """Hourly event value by type (5 series)."""
    rows = table(spark, sf_dir, "events").select("event_type", "ts", "value")
    return regularize(rows, "ts", "value", ["event_type"], "1 hour", agg, EVENTS_ORIGIN)


def events_by_user(spark: SparkSession, sf_dir: str, agg: str = "mean") -> DataFrame:
    rows = table(spark, sf_dir, "events").select("user_id", "ts", "value")
    return regularize(rows, "ts", "value", ["user_id"], "1 hour", agg, EVENTS_ORIGIN)


def lineitem_by_supplier(spark: SparkSession, sf_dir: str, agg: str = "sum") -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_shipdate", "l_extendedprice")
    return regularize(rows, "l_shipdate", "l_extendedprice", ["l_suppkey"], "1 day", agg, ORIGIN)


def orders_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily order counts by the customer's nation; the region is the cohort."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", F.lit(1.0).alias("one"))
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    rows = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return regularize(rows, "o_orderdate", "one", ["n_name"], "1 day", "count", ORIGIN)


def regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(series_id, cohort): nations by their region."""
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_name").alias("series_id"), F.col("r_name").alias("cohort"))


def _ranked(df: DataFrame, order: list[str]) -> DataFrame:
    """A step for each row by a total order. The order is one global range
    partitioning; each partition numbers its rows from its own base."""
    spread = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id())
    sizes = spread.groupBy("_part").agg(F.count("*").alias("n"), F.min("_at").alias("low"))
    base = sizes.select("_part", "low", F.coalesce(F.sum("n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return spread.join(F.broadcast(base), "_part").withColumn("step", F.col("_at") - F.col("low") + F.col("base")).drop("_part", "_at", "low", "base")


def quantities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line item quantities in key order: one long series without gaps."""
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity")
    return _ranked(rows, ["l_orderkey", "l_linenumber"]).select(F.lit("all").alias("cohort"), F.lit("quantity").alias("series_id"), "step", F.col("l_quantity").alias("value"))


def event_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events per hour (close to Poisson)."""
    rows = table(spark, sf_dir, "events").select("ts", "value")
    return regularize(rows.withColumn("one", F.lit("all")), "ts", "value", ["one"], "1 hour", "count", EVENTS_ORIGIN)


def returned_in_blocks(spark: SparkSession, sf_dir: str, block: int = 24) -> DataFrame:
    """Returned items in each block of line items (binomial, not Poisson)."""
    rows = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag")
    steps = _ranked(rows, ["l_orderkey", "l_linenumber"]).groupBy(F.floor(F.col("step") / block).cast("bigint").alias("step"))
    counted = steps.agg(F.sum((F.col("l_returnflag") == "R").cast("double")).alias("value"), F.count("*").alias("n")).where(F.col("n") == block)
    return counted.select(F.lit("all").alias("cohort"), F.lit("returned").alias("series_id"), "step", "value")


def with_rank(long: DataFrame) -> DataFrame:
    """0-based rank of each series' name within its cohort."""
    names = long.select("cohort", "series_id").distinct()
    ranked = names.withColumn("rank", (F.row_number().over(Window.partitionBy("cohort").orderBy("series_id")) - 1).cast("bigint"))
    return long.join(ranked, ["cohort", "series_id"])
