"""A Python data source over a model store: predictions as a readable format.

    register(spark)
    spark.read.format("pagecast").option("root", root).option("model", "m").option("horizon", 5).load()

Rows are forecasts of the next ``horizon`` steps of every series. A reader task
reads one file of the store's ``members`` (a row per series with its last values)
and the averaged weights of its cohorts, and rolls them forward. Filters on the
series or the cohort by equality or IN, and upper limits of ``ahead``, are taken
over: the first skip series before anything is computed, the last shorten the roll.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition, LessThan, LessThanOrEqual


def register(spark) -> None:
    """Make the format known; the session's switch for taking over filters is
    turned on, without which a reader that offers it is refused."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(PredictionSource)


class PredictionSource(DataSource):
    """Options: root and model of a store that the workers reach; horizon."""

    @classmethod
    def name(cls) -> str:
        return "pagecast"

    def schema(self) -> str:
        return "cohort string, series_id string, step bigint, ahead int, mean double, variance double"

    def reader(self, schema) -> PredictionReader:
        return PredictionReader(self.options)


class _Members(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _files(root: str, table: str):
    import pyarrow.fs as pafs

    fs, at = pafs.FileSystem.from_uri(f"{root}/{table}")
    return fs, sorted(f.path for f in fs.get_file_info(pafs.FileSelector(at, recursive=True)) if f.path.endswith(".parquet"))


class PredictionReader(DataSourceReader):
    def __init__(self, options: dict):
        self.root = f"{options['root'].rstrip('/')}/model={options['model']}"
        self.horizon = int(options.get("horizon", "1"))
        self.wanted: dict[str, set] = {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Takes what it can; gives back the rest, which Spark applies."""
        for f in filters:
            column = f.attribute[0] if len(f.attribute) == 1 else None
            if column in ("series_id", "cohort") and isinstance(f, (EqualTo, In)):
                values = {f.value} if isinstance(f, EqualTo) else set(f.value)
                self.wanted[column] = self.wanted.get(column, values) & values
            elif column == "ahead" and isinstance(f, (LessThan, LessThanOrEqual)):
                self.horizon = min(self.horizon, f.value - isinstance(f, LessThan))
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        return [_Members(p) for p in _files(self.root, "members")[1]]

    def read(self, partition: _Members) -> Iterator[tuple]:
        import numpy as np
        import pyarrow.parquet as pq

        if self.horizon < 1:
            return
        fs, files = _files(self.root, "weights")
        weights = {}
        for path in files:
            for row in pq.read_table(path, filesystem=fs).to_pylist():
                weights[row["cohort"], row["moment"]] = np.array(row["beta"])
        columns = ["cohort", "series_id", "first", "steps", "recent", "mu", "sd", "modelled"]
        for batch in pq.ParquetFile(partition.path, filesystem=fs).iter_batches(256, columns=columns):
            for row in batch.to_pylist():
                if not row["modelled"] or any(row[c] not in values for c, values in self.wanted.items()):
                    continue
                beta, squares = weights[row["cohort"], 1], weights[row["cohort"], 2]
                lags = np.array(row["recent"])[-len(beta) :]
                more = lags * lags
                for k in range(1, self.horizon + 1):
                    mean, second = float(lags @ beta), float(more @ squares)
                    lags, more = np.append(lags[1:], mean), np.append(more[1:], second)
                    yield row["cohort"], row["series_id"], row["first"] + row["steps"] + k - 1, k, mean * row["sd"] + row["mu"], max(0.0, second - mean * mean) * row["sd"] ** 2
