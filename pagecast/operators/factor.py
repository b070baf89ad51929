"""Truncated factors of the stacked page matrix.

Two ways lead to the same factors. 'gram' adds up the outer products of the
pages (w x w numbers, whatever the number of pages) and takes the eigenvectors:
pages are dealt by half window (with a salt that follows the pages of a half),
a task adds up one half window after the other, and the partial sums, a bounded
number for each half, go to the sub-models that contain it.
'local' gathers one sub-model's pages, at most its capacity, and calls LAPACK.
'power' iterates a block of vectors over the pages, and 'mllib' is Spark's own
row matrix, for comparison.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import groupby
from operator import itemgetter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagecast.cluster import ship
from pagecast.plans.config import ModelConfig

MODEL_SCHEMA = (
    "cohort string, model_idx bigint, moment int, w int, r_impute int, r_forecast int, pages bigint, seen bigint,"
    " share double, u array<array<double>>, s array<double>, uf array<array<double>>, sf array<double>, border array<double>, weights array<double>"
)
GRAM_SCHEMA = "cohort string, half bigint, moment int, g binary, pages bigint, seen bigint"
#: Rows and numbers of a batch that a worker gives back, about.
BATCH_ROWS, BATCH_NUMBERS = 1000, 1 << 20
FLOOR = 1e-8

_KINDS = {"string": pa.string(), "bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "binary": pa.binary()}
_KINDS |= {f"array<{k}>": pa.list_(v) for k, v in _KINDS.items()}
_KINDS |= {f"array<{k}>": pa.list_(v) for k, v in list(_KINDS.items())}


def canonical(u: np.ndarray) -> np.ndarray:
    """Signs fixed: the largest component of each column is positive."""
    if not u.size:
        return u
    top = np.argmax(np.abs(u), axis=0)
    return u * np.where(u[top, np.arange(u.shape[1])] < 0, -1.0, 1.0)


def choose_rank(s: np.ndarray, rule: str, rows: int, columns: int, energy: float = 0.9, fixed: int | None = None) -> int:
    """Number of singular values kept: fixed, by their share of the sum of
    squares, or above the published optimal hard threshold for unknown noise (a
    cubic in the aspect ratio times the median). Values below 1e-8 of the
    largest are never kept."""
    s = np.asarray(s, float)
    if not len(s) or s[0] <= 0:
        return 1
    real = int(np.count_nonzero(s > FLOOR * s[0]))
    if fixed is not None:
        return max(1, min(fixed, len(s)))
    if rule == "energy":
        share = np.cumsum(s**2) / np.sum(s**2)
        return max(1, min(real, int(np.searchsorted(share, energy)) + 1))
    aspect = min(rows, columns) / max(rows, columns)
    threshold = (0.56 * aspect**3 - 0.95 * aspect**2 + 1.82 * aspect + 1.43) * np.median(s)
    return max(1, min(real, int(np.count_nonzero(s > threshold))))


def from_gram(g: np.ndarray, pages: int, seen: int, config: ModelConfig) -> dict:
    """All factors of one sub-model and moment from its Gram matrix."""
    w = len(g)
    values, vectors = np.linalg.eigh(g)
    s, u = np.sqrt(np.maximum(values[::-1], 0)), canonical(vectors[:, ::-1])
    r1 = choose_rank(s, config.rank_rule, w, pages, config.energy, config.r_impute)
    values, vectors = np.linalg.eigh(g[:-1, :-1])
    sf, uf = np.sqrt(np.maximum(values[::-1], 0)), canonical(vectors[:, ::-1])
    r2 = choose_rank(sf, config.rank_rule, w - 1, pages, config.energy, config.r_forecast)
    return _factors(w, pages, seen, u[:, :r1], s[:r1], uf[:, :r2], sf[:r2], g[:-1, -1])


def _factors(w, pages, seen, u, s, uf, sf, border) -> dict:
    """Weights of the last row on the truncated others, oldest first: the least
    squares solution of least norm."""
    usable = sf > FLOOR * (sf[0] if len(sf) else 0)
    coefficient = np.zeros(len(sf))
    coefficient[usable] = (uf.T @ border)[usable] / sf[usable] ** 2
    return {
        "w": w, "r_impute": u.shape[1], "r_forecast": uf.shape[1], "pages": pages, "seen": seen,
        "u": [c.tolist() for c in u.T], "s": s.tolist(), "uf": [c.tolist() for c in uf.T], "sf": sf.tolist(), "border": np.asarray(border).tolist(), "weights": (uf @ coefficient).tolist(),
    }


def from_pages(z: np.ndarray, seen: int, config: ModelConfig) -> dict:
    """The same from the page matrix itself (w x pages), by LAPACK."""
    w, n = z.shape
    u, s, _ = np.linalg.svd(z, full_matrices=False)
    uf, sf, _ = np.linalg.svd(z[:-1], full_matrices=False)
    r1 = choose_rank(s, config.rank_rule, w, n, config.energy, config.r_impute)
    r2 = choose_rank(sf, config.rank_rule, w - 1, n, config.energy, config.r_forecast)
    return _factors(w, n, seen, canonical(u)[:, :r1], s[:r1], canonical(uf)[:, :r2], sf[:r2], z[:-1] @ z[-1])


def moments(batch: pa.RecordBatch) -> list[np.ndarray]:
    """Zero-filled values and their squares (rows x w) of a batch of pages;
    where the batch has ``mu`` and ``sd``, of the standardised values."""
    x = batch.column("vals").flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(batch), -1)
    if "mu" in batch.schema.names:
        mu, sd = (np.asarray(batch.column(c), float)[:, None] for c in ("mu", "sd"))
        x = (x - mu) / sd
    x = np.nan_to_num(x, nan=0.0)
    return [x, x * x]


def batched(rows: Iterator[dict], schema: str, numbers) -> Iterator[pa.RecordBatch]:
    """Rows as batches of a bounded size; ``numbers`` tells how many a row holds."""
    arrow = pa.schema([(name, _KINDS[kind]) for name, kind in (c.split() for c in schema.split(","))])
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += numbers(row)
        if len(held) >= BATCH_ROWS or size >= BATCH_NUMBERS:
            yield pa.RecordBatch.from_pylist(held, schema=arrow)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_pylist(held, schema=arrow)


def gram_rows(pages: DataFrame, half_pages: int, sign: int = 1) -> DataFrame:
    """(cohort, half, moment, g: w*w doubles as binary, pages, seen): partial sums.

    Pages that lie by (cohort, half, salt) already, as ``pagematrix.gathered``
    and the stored table have them, are read as they lie; others are dealt so
    first. A task holds the sums of one key at a time and gives them away when
    the next key begins. A column ``sign`` (1 or -1) says page by page what is
    added and what is taken away.
    """
    ship(pages.sparkSession)
    if "salt" not in pages.columns:
        pages = pages.withColumn("half", F.floor(F.col("page") / half_pages).cast("bigint")).withColumn("salt", F.pmod(F.xxhash64("series_id", F.floor(F.col("page") / 64)), F.lit(16)).cast("int"))
        pages = pages.repartition("cohort", "half", "salt").sortWithinPartitions("cohort", "half")

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        key, g, number, seen = None, [0.0, 0.0], 0, 0

        def done() -> list[dict]:
            way = key[2]
            return [{"cohort": key[0], "half": key[1], "moment": m + 1, "g": (way * g[m]).tobytes(), "pages": way * number, "seen": way * seen} for m in (0, 1)]

        for batch in batches:
            if not len(batch):
                continue
            keys = list(zip(*(batch.column(c).to_pylist() for c in ("cohort", "half", "sign"))))
            x, count = moments(batch), np.asarray(batch.column("seen"))
            cuts = [0, *(i for i in range(1, len(batch)) if keys[i] != keys[i - 1]), len(batch)]
            for a, b in zip(cuts, cuts[1:]):
                own = keys[a]
                if own != key:
                    if number:
                        yield from done()
                    key, g, number, seen = own, [0.0, 0.0], 0, 0
                g = [total + part[a:b].T @ part[a:b] for total, part in zip(g, x)]
                number, seen = number + b - a, seen + int(count[a:b].sum())
        if number:
            yield from done()

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return batched(sums(batches), GRAM_SCHEMA, lambda row: len(row["g"]) // 8)

    own = [c for c in ("mu", "sd") if c in pages.columns]
    way = "sign" if "sign" in pages.columns else F.lit(sign).alias("sign")
    return pages.select("cohort", "half", "vals", "seen", way, *own).mapInArrow(partial, GRAM_SCHEMA)


def _added_up(parts: DataFrame, keys: tuple[str, ...], schema: str, row, numbers) -> DataFrame:
    """One row of ``schema`` for each key whose parts ``row`` takes: row(key,
    sum of g, pages, seen, half windows), or None. A task gets the keys one
    after the other and holds the sum of one, so many small ones cost no more
    than their numbers do."""
    ship(parts.sparkSession)

    def every(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            yield from zip(zip(*(batch.column(c).to_pylist() for c in keys)), *(batch.column(c).to_pylist() for c in ("g", "pages", "seen", "half")))

    def found(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
        for key, own in groupby(every(batches), itemgetter(0)):
            total, pages, seen, halves = 0.0, 0, 0, set()
            for _, g, n, k, half in own:
                total, pages, seen = total + np.frombuffer(g), pages + n, seen + k
                halves.add(half)
            out = row(key, total, pages, seen, halves)
            if out is not None:
                yield dict(zip(keys, key)) | out

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return batched(found(batches), schema, numbers)

    columns = dict.fromkeys([*keys, "half", "g", "pages", "seen"])
    return parts.select(*columns).repartition(*keys).sortWithinPartitions(*keys).mapInArrow(task, schema)


def merge_gram(*parts: DataFrame) -> DataFrame:
    """One row per (cohort, half, moment): all parts added up."""
    every = parts[0]
    for more in parts[1:]:
        every = every.unionByName(more)
    merged = lambda key, g, pages, seen, _: {"g": g.tobytes(), "pages": pages, "seen": seen}
    return _added_up(every, ("cohort", "half", "moment"), GRAM_SCHEMA, merged, lambda row: len(row["g"]) // 8)


def gram_cells(pages: DataFrame, column: str = "vals") -> DataFrame:
    """The Gram matrix in rows (cohort, i, j, g), by SQL functions only."""
    one = pages.select("cohort", F.col(column).alias("v"), F.posexplode(column).alias("i", "x"))
    two = one.select("cohort", "i", "x", F.posexplode("v").alias("j", "y"))
    return two.groupBy("cohort", "i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g"))


def to_models(halves: DataFrame) -> DataFrame:
    """Each half window's rows, for the two sub-models that may contain it."""
    both = F.filter(F.array(F.col("half") - 1, F.col("half")), lambda m: m >= 0)
    return halves.withColumn("model_idx", F.explode(both))


def whole(model_idx: int, halves) -> bool:
    """A sub-model after the first needs its second half: its first alone is
    the second of the one before."""
    return model_idx == 0 or model_idx + 1 in set(halves)


def solve(halves: DataFrame, config: ModelConfig, only: DataFrame | None = None) -> DataFrame:
    """Factors of all sub-models from (partial) Gram rows: the parts go to their
    sub-models in one shuffle and are added up there. ``only`` (cohort,
    model_idx) names the sub-models to solve."""

    def one(key, flat: np.ndarray, n: int, seen: int, halves: set) -> dict | None:
        if not whole(key[1], halves) or n <= 0:
            return None
        w = round(len(flat) ** 0.5)
        share = share_of(config, seen, n * w)
        return {"share": share, **from_gram(flat.reshape(w, w) / share**2, n, seen, config)}

    parts = to_models(halves)
    if only is not None:
        parts = parts.join(only, ["cohort", "model_idx"], "left_semi")
    size = lambda row: row["w"] * (row["r_impute"] + row["r_forecast"] + 2)
    return _added_up(parts, ("cohort", "model_idx", "moment"), MODEL_SCHEMA, one, size)


def share_of(config: ModelConfig, seen: int, cells: int) -> float:
    """What zero-filled cells are divided by: the observed share of a
    sub-model's pages where ``fill`` asks for it."""
    return seen / cells if config.fill == "inverse_rate" and seen else 1.0


def train(pages: DataFrame, half_pages: int, config: ModelConfig) -> DataFrame:
    """One row per (cohort, model_idx, moment) with its factors and weights."""
    ship(pages.sparkSession)
    if config.backend == "gram":
        return solve(gram_rows(pages, half_pages), config)
    if config.backend != "local":
        raise ValueError(f"unknown backend {config.backend}")

    def one(key, frame: pd.DataFrame) -> pd.DataFrame:
        if not whole(key[1], frame["half"]):
            return pd.DataFrame()
        frame = frame.sort_values(["series_id", "page"])
        z, seen = np.nan_to_num(np.stack(frame["vals"].to_list()).astype(float)).T, int(frame["seen"].sum())
        share = share_of(config, seen, z.size)
        found = [from_pages(m / share, seen, config) for m in (z, z * z)]
        return pd.DataFrame([{"cohort": key[0], "model_idx": key[1], "moment": k + 1, "share": share, **f} for k, f in enumerate(found)])

    cut = pages.select("cohort", F.floor(F.col("page") / half_pages).cast("bigint").alias("half"), "series_id", "page", "vals", "seen")
    return to_models(cut).groupBy("cohort", "model_idx").applyInPandas(one, MODEL_SCHEMA)


def power_iterate(pages: DataFrame, rank: int, rounds: int = 30, tolerance: float = 1e-9, column: str = "vals") -> tuple[np.ndarray, np.ndarray]:
    """Leading left vectors and singular values of one cohort's matrix by block
    power iteration: each round is one pass over the pages, and only a block of
    w x rank numbers travels. Stops when the block's span is still."""
    spark = pages.sparkSession
    w = len(pages.select(column).first()[0])
    block = np.linalg.qr(np.random.default_rng(3).normal(size=(w, rank)))[0]
    s = np.zeros(rank)
    for _ in range(rounds):
        shared = spark.sparkContext.broadcast(block)

        def product(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((w, rank))
            for batch in batches:
                x = np.asarray(batch.column(0).flatten()).reshape(-1, w)
                total += x.T @ (x @ shared.value)
            yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary())], ["p"])

        moved = sum(np.frombuffer(r["p"]).reshape(w, rank) for r in pages.select(column).mapInArrow(product, "p binary").collect())
        after, upper = np.linalg.qr(moved)
        s = np.sqrt(np.abs(np.diag(upper)))
        still = np.linalg.norm(after @ (after.T @ block) - block) < tolerance
        block = after
        shared.destroy()
        if still:
            break
    order = np.argsort(-s)
    return canonical(block[:, order]), s[order]


def svd_mllib(pages: DataFrame, rank: int, column: str = "vals") -> np.ndarray:
    """Singular values by Spark's row matrix (one row per page)."""
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    rows = pages.select(column).rdd.map(lambda r: Vectors.dense(r[0]))
    return np.array(RowMatrix(rows).computeSVD(rank).s.toArray())


def grown_left(u: np.ndarray, s: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Left vectors and singular values of [old | new columns] from the old ones
    alone: the new columns are split into what the old vectors span and a rest,
    and a small matrix of the coefficients is factorised in their place. Also
    gives that factorisation's vectors."""
    inside = u.T @ new
    q, upper = np.linalg.qr(new - u @ inside)
    small = np.block([[np.diag(s), inside], [np.zeros((q.shape[1], len(s))), upper]])
    a, values, b = np.linalg.svd(small, full_matrices=False)
    return np.hstack([u, q]) @ a, values, a, b


def update_columns(u: np.ndarray, s: np.ndarray, v: np.ndarray, new: np.ndarray, rank: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Factors of [old | new columns] from the old factors, truncated."""
    left, values, _, b = grown_left(u, s, new)
    k = min(rank, len(values))
    right = np.block([[v, np.zeros((len(v), new.shape[1]))], [np.zeros((new.shape[1], v.shape[1])), np.eye(new.shape[1])]]) @ b.T[:, :k]
    return left[:, :k], values[:k], right


def widen(model: dict, new: np.ndarray, seen: int, config: ModelConfig) -> dict:
    """A stored sub-model (one row) after its pages gained columns (w x n).
    Ranks stay as they were chosen by the last full solve."""
    w, n = int(model["w"]), int(model["pages"]) + new.shape[1]
    stack = lambda rows, height: np.array([np.asarray(r, float) for r in rows]).reshape(-1, height).T
    parts = []
    for left, values, rank, columns in (("u", "s", "r_impute", new), ("uf", "sf", "r_forecast", new[:-1])):
        u, s, *_ = grown_left(stack(model[left], len(columns)), np.asarray(model[values], float), columns)
        k = min(int(model[rank]), len(s))
        parts += [canonical(u[:, :k]), s[:k]]
    border = np.asarray(model["border"], float) + new[:-1] @ new[-1]
    return _factors(w, n, int(model["seen"]) + seen, *parts, border)


def fold_in(u: np.ndarray, s: np.ndarray, v: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The cheap variant: new columns are only projected, vectors stay."""
    return u, s, np.vstack([v, (new.T @ u) / np.where(s > 0, s, 1.0)])


def right_vectors(pages: DataFrame, models: DataFrame, half_pages: int) -> DataFrame:
    """(cohort, model_idx, moment, series_id, page, v) for stored look-ups. Pages
    hold zero-filled values (standardised where the model is)."""
    from pagecast.functions.mathfn import dot

    half = F.floor(F.col("page") / half_pages).cast("bigint")
    placed = to_models(pages.select("cohort", "series_id", "page", "vals", half.alias("half")))
    both = placed.join(models.select("cohort", "model_idx", "moment", "share", "u", "s"), ["cohort", "model_idx"])
    z = F.transform("vals", lambda x: F.when(F.col("moment") == 1, x).otherwise(x * x) / F.col("share"))
    v = F.zip_with("u", "s", lambda u, s: F.when(s > 0, dot(u, F.col("z")) / s).otherwise(0.0))
    return both.withColumn("z", z).select("cohort", "model_idx", "moment", "series_id", "page", v.alias("v"))
