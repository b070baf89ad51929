"""Queries whose result must not turn with the size of the table."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from pagecast.catalog_queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.01"


def _same(df, sql: str, folder: str, *tables: str) -> None:
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    names = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(names)} FROM ({sql})").fetchall()
    assert sorted(map(tuple, df.select(*names).collect())) == sorted(want)


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
@pytest.mark.parametrize("name", ["q_m24_schedule", "q_m25_fold"])
def test_second_batch_before_the_next_full_solve(spark, name):
    """With some 5,700 prices in the first batch, counts from 100 on had a full solve at 6,400."""
    _same(QUERIES[name](spark, SF), ORACLES[name], SF, "orders")


def test_scored_beyond_a_million_rows(spark, tmp_path):
    kind = F.when(F.col("id") % 3 == 0, "click").otherwise("view")
    rows = spark.range(1_000_100).select(F.col("id").alias("event_id"), (F.lit("2024-01-01").cast("timestamp_ntz") + F.make_dt_interval(secs=F.col("id") % 2_000_000)).alias("ts"), (F.col("id") % 9).alias("user_id"), kind.alias("event_type"), (F.col("id") * 7919 % 1009).cast("double").alias("value"))
    rows.toArrow().to_pandas().to_parquet(tmp_path / "events.parquet")
    found = QUERIES["q_r07_scored"](spark, str(tmp_path)).groupBy("odd").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))
    sql = f"SELECT odd, count(*) AS n, sum(event_id)::BIGINT AS ids FROM ({ORACLES['q_r07_scored']}) GROUP BY 1"
    _same(found, sql, str(tmp_path), "events")


@pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
def test_sessions_stay_off_the_driver(spark):
    found = QUERIES["q_r02_sessions"](spark, SF)
    assert found.inputFiles()  # a memory table has none: its rows are in the driver
    _same(found, ORACLES["q_r02_sessions"], SF, "events")
