"""Series as pages: the columns of the stacked page matrix.

Step i + w*j of a series is row i of its page j. All pages of a cohort's series
stand side by side; the matrix is never held as one object. A page is one row
(cohort, series_id, page, vals, sq, seen), absent values zero in ``vals`` and
``sq``. Only the observations are shuffled, not a dense grid, and both moments
come from one pass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


#: Pages that one task adds up into one Gram matrix, at least; never fewer than
#: three for each of their rows, so that a matrix is smaller than what it sums up.
PAGES_TOGETHER = 256
#: Partial matrices of one half window, at most.
MOST_PARTS = 64


def _laid_out(entries: Column, w: int, absent: float | None = 0.0) -> Column:
    """An array of w cells from (row, value) entries, ``absent`` where there is
    none: the missing rows are added and all are sorted, w log w steps. A page
    that came complete and in order is taken as it is."""
    rows = F.transform(entries, lambda e: e["row"])
    full = F.sequence(F.lit(0).cast("bigint"), F.lit(w - 1).cast("bigint"))
    missing = F.array_except(full, rows)
    every = F.concat(entries, F.transform(missing, lambda i: F.struct(i.alias("row"), F.lit(absent).cast("double").alias("value"))))
    cells = F.transform(F.array_sort(every), lambda e: e["value"])
    values = F.transform(entries, lambda e: e["value"])
    return F.when(rows == full, values).when(F.size(every) == w, cells).otherwise(F.raise_error(F.lit("two values for one step of a series")))


def salts(pages_of_half: int, w: int) -> int:
    """Tasks that share a half window's pages."""
    return max(1, min(MOST_PARTS, -(-pages_of_half // max(PAGES_TOGETHER, 3 * w))))


def salt_of(number: int) -> Column:
    return F.pmod(F.xxhash64("series_id", "page"), F.lit(number)).cast("int")


def gathered(rows: DataFrame, w: int, half_pages: int, parts: int, carried: tuple[str, ...] = ()) -> DataFrame:
    """(cohort, half, salt, series_id, page, vals, seen, carried...) from rows
    with a ``rel`` step and a value: pages with null where nothing was observed.

    The rows go straight to where their half window is added up: one shuffle by
    (cohort, half, salt) serves the pages and their partial sums.
    """
    placed = rows.withColumn("page", F.floor(F.col("rel") / w).cast("bigint")).withColumn("half", F.floor(F.col("page") / half_pages).cast("bigint")).withColumn("salt", salt_of(parts))
    entry = F.struct((F.col("rel") - F.col("page") * w).alias("row"), F.col("value"))
    keys = ["cohort", "half", "salt", "series_id", "page"]
    pages = placed.repartition("cohort", "half", "salt").groupBy(*keys, *carried).agg(F.collect_list(entry).alias("e"))
    return pages.select(*keys, _laid_out(F.col("e"), w, None).alias("vals"), F.size("e").cast("bigint").alias("seen"), *carried)


def build(long: DataFrame, w: int, partial: bool = False, steps: int | None = None) -> DataFrame:
    """Pages of height w. The last T mod w steps of a cohort have no page,
    unless ``partial`` asks for a page that is not full."""
    rows = long.where("value is not null and step >= 0")
    if not partial:
        if steps is not None:
            rows = rows.where(F.col("step") < steps - steps % w)
        else:
            ends = rows.groupBy("cohort").agg((F.max("step") + 1).alias("steps"))
            rows = rows.join(ends, "cohort").where(F.col("step") < F.col("steps") - F.col("steps") % w).drop("steps")
    entry = F.struct((F.col("step") % w).alias("row"), F.col("value"))
    pages = rows.groupBy("cohort", "series_id", F.floor(F.col("step") / w).cast("bigint").alias("page")).agg(F.collect_list(entry).alias("e"))
    pages = pages.select("cohort", "series_id", "page", _laid_out(F.col("e"), w).alias("vals"), F.size("e").cast("bigint").alias("seen"))
    return pages.select("cohort", "series_id", "page", "vals", F.transform("vals", lambda x: x * x).alias("sq"), "seen")


def hankel(long: DataFrame, w: int) -> DataFrame:
    """The overlapping layout of the trajectory matrix: a column for every run
    of w steps. ``page`` is the run's first step."""
    run = Window.partitionBy("cohort", "series_id").orderBy("step").rowsBetween(0, w - 1)
    filled = F.coalesce(F.col("value"), F.lit(0.0))
    rows = long.select("cohort", "series_id", F.col("step").alias("page"), F.collect_list(filled).over(run).alias("vals"), F.count("value").over(run).alias("seen"))
    return rows.where(F.size("vals") == w).select("cohort", "series_id", "page", "vals", F.transform("vals", lambda x: x * x).alias("sq"), "seen")


def cells(pages: DataFrame, column: str = "vals") -> DataFrame:
    """Matrix cells (cohort, series_id, page, row, value)."""
    return pages.select("cohort", "series_id", "page", F.posexplode(column).alias("row", "value"))


def unbias(pages: DataFrame, rate: float) -> DataFrame:
    """Divide the zero-filled cells by the observed share."""
    scale = lambda c: F.transform(c, lambda x: x / F.lit(rate)).alias(c)
    return pages.select("cohort", "series_id", "page", scale("vals"), scale("sq"), "seen")


def split_last(pages: DataFrame, column: str = "vals") -> DataFrame:
    """First w - 1 rows and the last row of each page."""
    return pages.select("cohort", "series_id", "page", F.slice(F.col(column), F.lit(1), F.size(column) - 1).alias("lags"), F.element_at(column, -1).alias("target"))
