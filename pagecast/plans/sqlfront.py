"""Statements: CREATE and PREDICT beside ordinary SQL.

    CREATE PREDICTION MODEL m ON t (c1, c2) TIME ts EVERY '1 day' [USING mean]
        [ORIGIN '1995-01-01'] [WITH (w = 20, capacity = 1000)]
    PREDICT c1, c2 FROM m WHERE step = 10 | WHERE step BETWEEN 5 AND 9
                              | WHERE ts = '1995-04-11' | WHERE ts BETWEEN '..' AND '..'
        [CONFIDENCE 95] [INTERVAL gaussian | chebyshev | none]

Asked by the relation's own time column, the answer has that column too: the
begin of each interval.

Everything else goes to Spark as it is.
"""

from __future__ import annotations

import re
from dataclasses import fields

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagecast.operators import ingest
from pagecast.plans.config import ModelConfig
from pagecast.plans.engine import Engine

_NAME = r"[A-Za-z_][\w.]*"
_CREATE = re.compile(
    rf"\s*create\s+prediction\s+model\s+(?P<model>{_NAME})\s+on\s+(?P<table>{_NAME})\s*\((?P<cols>[^)]*)\)\s*time\s+(?P<time>{_NAME})\s+every\s+'(?P<every>[^']+)'"
    rf"(?:\s+using\s+(?P<agg>\w+))?(?:\s+origin\s+'(?P<origin>[^']+)')?(?:\s+with\s*\((?P<options>[^)]*)\))?\s*;?\s*",
    re.IGNORECASE,
)
_LITERAL = r"(?:(?:timestamp|date|timestamp_ntz)\s*)?'[^']*'|-?[\d.]+"
_PREDICT = re.compile(
    rf"\s*predict\s+(?P<cols>\*|{_NAME}(?:\s*,\s*{_NAME})*)\s+from\s+(?P<model>{_NAME})\s+where\s+(?P<by>{_NAME})\s*(?:=\s*(?P<at>{_LITERAL})|between\s+(?P<lo>{_LITERAL})\s+and\s+(?P<hi>{_LITERAL}))"
    r"(?:\s+confidence\s+(?P<confidence>[\d.]+))?(?:\s+interval\s+(?P<method>\w+))?\s*;?\s*",
    re.IGNORECASE,
)


def _value(field_type: str, text: str):
    text = text.strip().strip("'\"")
    if "bool" in field_type:
        return text.lower() == "true"
    for kind in (int, float):
        try:
            return kind(text)
        except ValueError:
            continue
    return text


def _step(spark: SparkSession, literal: str, time: dict) -> int:
    """The step that a literal of WHERE names."""
    if not time:
        return int(literal)
    one = spark.range(1).select(ingest.step_of(F.expr(literal), time["origin"], time["interval"]).alias("s"))
    found = one.first()["s"]
    if found is None:
        raise ValueError(f"not a time: {literal}")
    return found


def run(engine: Engine, statement: str) -> DataFrame:
    """The result of a statement of any of the three forms."""
    spark = engine.spark
    made = _CREATE.fullmatch(statement)
    if made:
        types = {f.name: str(f.type) for f in fields(ModelConfig)}
        options = {}
        for item in filter(None, (made["options"] or "").split(",")):
            key, _, value = item.partition("=")
            if key.strip() not in types:
                raise ValueError(f"unknown option {key.strip()}")
            options[key.strip()] = _value(types[key.strip()], value)
        cols = [c.strip() for c in made["cols"].split(",")]
        model = engine.create_from_table(made["model"], spark.table(made["table"]), made["time"], cols, made["every"], (made["agg"] or "mean").lower(), made["origin"], ModelConfig(**options))
        return spark.createDataFrame([(model.name, model.n_series, model.steps, model.w)], "model string, n_series bigint, steps bigint, w int")
    asked = _PREDICT.fullmatch(statement)
    if asked:
        model = engine.model(asked["model"])
        lo, hi = (asked["at"], asked["at"]) if asked["at"] else (asked["lo"], asked["hi"])
        by, time = asked["by"].lower(), model.time
        own = bool(time) and by == time["column"].lower()
        if by != "step" and not own:
            raise ValueError(f"{asked['by']} is neither step nor the time column of {asked['model']}")
        first, last = (_step(spark, x, time if own else {}) for x in (lo, hi))
        series = None if asked["cols"] == "*" else [c.strip() for c in asked["cols"].split(",")]
        method = (asked["method"] or "gaussian").lower()
        out = engine.predict(asked["model"], first, last, series, float(asked["confidence"] or 95), "gaussian" if method == "none" else method, method != "none")
        return out.withColumn(time["column"], ingest.time_of(F.col("step"), time["origin"], time["interval"])) if own else out
    if re.match(r"\s*(predict\b|create\s+prediction\b)", statement, re.IGNORECASE):
        raise ValueError(f"not understood: {statement}")
    return spark.sql(statement)
