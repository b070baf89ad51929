"""Nearest neighbours by additive quantisation and exact reranking.

A vector is approximated by a sum of full-dimensional codewords, one from each
codebook. Codebooks are fitted one after the other to what the earlier ones
leave, on a bounded sample; vectors are encoded by beam search, which keeps the
best few partial sums instead of the single best. With the squared norm of the
approximation stored beside the codes, a query's distance to every vector of a
chunk is one table lookup per codebook. The best of each chunk are compared
exactly on the original vectors, and the chunks' answers are merged.

Vectors are packed into chunks of a fixed number of rows, queries into blocks
of a fixed number; a task meets one chunk with one block at a time, so its
memory does not depend on the table, and the share of vectors that is compared
exactly is the same at every size. Both lie in written tables that the tasks
scan: neither vectors nor codes are shuffled for the meeting, and a chunk is
read once for every block of queries, a quarter of a byte for each pair of a
query and a vector of 64 components. Only the ten best of a chunk move on.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pagecast.cluster import Written, ship

CODEWORDS = 256


@dataclass(frozen=True)
class SearchPlan:
    codebooks: int = 16
    beam: int = 4
    sample_rows: int = 8192  # rows that the codebooks are fitted on, at most
    rounds: int = 4
    chunk_rows: int = 4096
    block_queries: int = 2048
    rerank: int = 224  # of each chunk, compared exactly for each query
    neighbours: int = 10


def _nearest(points: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.argmin((centres**2).sum(1)[None, :] - 2.0 * points @ centres.T, axis=1)


def fit(sample: np.ndarray, plan: SearchPlan) -> np.ndarray:
    """Codebooks (number x 256 x dimension) fitted to the residuals in turn."""
    rng = np.random.default_rng(7)
    left = sample.astype(np.float32).copy()
    books = []
    for _ in range(plan.codebooks):
        centres = left[rng.choice(len(left), CODEWORDS, replace=len(left) < CODEWORDS)].copy()
        for _ in range(plan.rounds):
            label = _nearest(left, centres)
            count = np.bincount(label, minlength=CODEWORDS)
            order = np.argsort(label, kind="stable")
            filled = count > 0
            starts = np.concatenate([[0], np.cumsum(count)])[:-1]
            centres[filled] = np.add.reduceat(left[order], starts[filled], axis=0) / count[filled, None]
        label = _nearest(left, centres)
        left -= centres[label]
        books.append(centres)
    return np.stack(books)


def encode(vectors: np.ndarray, books: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Codes (rows x codebooks, uint8) and squared norms of the sums."""
    n, d = vectors.shape
    m = len(books)
    codes = np.zeros((n, m), np.uint8)
    norms = np.zeros(n, np.float32)
    for at in range(0, n, 512):
        x = vectors[at : at + 512].astype(np.float32)
        rows = len(x)
        held = np.zeros((rows, 1, 0), np.uint8)
        left = x[:, None, :]
        for book in books:
            width = left.shape[1]
            # |residual - c|^2 for each kept sum and codeword
            cost = (left**2).sum(2)[:, :, None] - 2.0 * (left @ book.T) + (book**2).sum(1)
            flat = cost.reshape(rows, -1)
            best = min(beam, flat.shape[1])
            top = np.argpartition(flat, best - 1, axis=1)[:, :best]
            parent, word = top // CODEWORDS, top % CODEWORDS
            pick = np.arange(rows)[:, None]
            held = np.concatenate([held[pick, parent], word[:, :, None].astype(np.uint8)], axis=2)
            left = left[pick, parent] - book[word]
        final = np.argmin((left**2).sum(2), axis=1)
        codes[at : at + 512] = held[np.arange(rows), final]
        norms[at : at + 512] = ((x - left[np.arange(rows), final]) ** 2).sum(1)
    return codes, norms


def _usable(vector: Column) -> Column:
    """Not null, not empty, all components finite, not all zero."""
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce(vector.isNotNull() & (F.size(vector) > 0) & finite & F.exists(vector, lambda x: x != 0), F.lit(False))


def _chunks(rows: DataFrame, size: int, label: str, spark: SparkSession) -> DataFrame:
    """Rows (id, v) packed into chunks of at most ``size`` rows: ids and
    vectors as one binary each. Chunks follow the partitions they lie in."""

    def packed(parts: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        arrays = [pa.array([i.tobytes() for i, _ in parts], pa.binary()), pa.array([v.tobytes() for _, v in parts], pa.binary()), pa.array([len(i) for i, _ in parts], pa.int64())]
        return pa.RecordBatch.from_arrays(arrays, ["ids", "vectors", "n"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, vectors = np.empty(0, np.int64), None
        for batch in batches:
            if not len(batch):
                continue
            more = np.asarray(batch.column(1).flatten().cast(pa.float64())).reshape(len(batch), -1)
            ids = np.concatenate([ids, np.asarray(batch.column(0).cast(pa.int64()))])
            vectors = more if vectors is None else np.concatenate([vectors, more])
            full = len(ids) - len(ids) % size
            if full:
                yield packed([(ids[k : k + size], vectors[k : k + size]) for k in range(0, full, size)])
                ids, vectors = ids[full:], vectors[full:]
        if len(ids):
            yield packed([(ids, vectors)])

    return rows.mapInArrow(pack, "ids binary, vectors binary, n bigint")


def search(df: DataFrame, is_query: Column, plan: SearchPlan = SearchPlan(), id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: each query's nearest rows by Euclidean
    distance on the original vectors, ties to the smaller id.

    Rows with a null id and vectors that are null, empty, zero or hold null or
    non-finite components take no part, as queries or candidates, nor do those
    of another dimension than the most common one (the smaller on a tie).
    Repeated rows with one id count once (the smallest vector). Fewer rows than
    neighbours give all of them; an empty table gives an empty result.
    """
    spark = df.sparkSession
    ship(spark)
    rows = df.select(F.col(id_col).cast("bigint").alias("id"), F.col(vector_col).cast("array<double>").alias("v"), is_query.alias("q"))
    rows = rows.where(F.col("id").isNotNull() & _usable(F.col("v")))
    rows = rows.groupBy("id").agg(F.min(F.struct("v", "q")).alias("s")).select("id", "s.v", "s.q")
    kept = Written(rows, "vectors")
    common = kept.df.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(1).collect()
    schema = "query_id bigint, rank int, vec_id bigint, score double"
    if not common:
        return spark.createDataFrame([], schema)
    dim = common[0]["d"]
    rows = kept.df.where(F.size("v") == dim)
    picked = rows.orderBy(F.xxhash64("id"), "id").limit(plan.sample_rows).select("v").collect()
    books = fit(np.array([r[0] for r in picked]), plan)
    shared = spark.sparkContext.broadcast(books)  # codebooks x 256 x dimension floats

    index = _chunks(rows.select("id", "v"), plan.chunk_rows, "index", spark)

    def encoded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes, norms = [], []
            for raw, n in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                c, norm = encode(np.frombuffer(raw).reshape(n, dim), shared.value, plan.beam)
                codes.append(c.tobytes())
                norms.append(norm.tobytes())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(codes, pa.binary()), pa.array(norms, pa.binary())], ["ids", "vectors", "n", "codes", "norms"])

    index = Written(index.mapInArrow(encoded, "ids binary, vectors binary, n bigint, codes binary, norms binary"), "vector-index").df
    queries = Written(_chunks(rows.where("q").select("id", "v"), plan.block_queries, "queries", spark), "vector-queries").df
    kept.drop()
    queries = queries.select(F.col("ids").alias("q_ids"), F.col("vectors").alias("q_vectors"), F.col("n").alias("q_n"))
    # every block of the stated queries meets every chunk, as packed rows
    met = index.hint("shuffle_replicate_nl").join(queries, F.lit(True), "inner")

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        books = shared.value
        for batch in batches:
            for row in batch.to_pylist():
                n, q_n = row["n"], row["q_n"]
                ids, x = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["vectors"]).reshape(n, dim)
                codes, norms = np.frombuffer(row["codes"], np.uint8).reshape(n, -1), np.frombuffer(row["norms"], np.float32)
                q_ids, q = np.frombuffer(row["q_ids"], np.int64), np.frombuffer(row["q_vectors"]).reshape(q_n, dim)
                best = min(plan.rerank, n)
                q32 = q.astype(np.float32)
                for at in range(0, q_n, 64):
                    part = q32[at : at + 64]
                    tables = np.einsum("qd,mkd->mkq", part, books, optimize=True)
                    dots = np.zeros((n, len(part)), np.float32)
                    for m in range(len(books)):
                        dots += tables[m][codes[:, m]]
                    rough = norms[:, None] - 2.0 * dots
                    if best < n:
                        top = np.argpartition(rough, best - 1, axis=0)[:best]
                    else:
                        top = np.broadcast_to(np.arange(n)[:, None], (n, len(part)))
                    out_q, out_v, out_s = [], [], []
                    for j in range(len(part)):
                        own = top[:, j]
                        own = own[ids[own] != q_ids[at + j]]
                        exact = np.sqrt(((x[own] - q[at + j]) ** 2).sum(1))
                        order = np.lexsort((ids[own], exact))[: plan.neighbours]
                        out_q.append(np.full(len(order), q_ids[at + j]))
                        out_v.append(ids[own][order])
                        out_s.append(exact[order])
                    frame = [pa.array(np.concatenate(c)) for c in (out_q, out_v, out_s)]
                    yield pa.RecordBatch.from_arrays(frame, ["query_id", "vec_id", "score"])

    found = met.mapInArrow(answer, "query_id bigint, vec_id bigint, score double")
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= plan.neighbours)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
