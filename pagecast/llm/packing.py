"""Packing of documents into sequences by shortest-pack-first on lengths.

Documents are tokenised once, and only lengths and checksums of their pieces are
kept: a document longer than a sequence is cut into full sequences and one
remainder. The histogram of piece lengths (at most one count per length, however
many documents there are) goes to the driver, where lengths are placed longest
first into the pack with the most room left; a pack is a pattern with a count,
and both are split as the counts require. Each pattern's places become ranges of
ranks within a length, and the pieces find theirs by their own rank, which is
computed from salted groups so that no length, however common, lies in one task.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pagecast.cluster import Written, ship
from pagecast.llm.library_tokens import library_ids
from pagecast.llm.words import worker_for

#: Pieces of one length that one window task ranks.
RANKED_TOGETHER = 1000
#: Places of patterns that are broadcast (some 40 bytes each); their number follows
#: the number of lengths and levels off at 42 thousand for sequences of 4096.
PLACES_BROADCAST = 500_000


def pieces(df: DataFrame, vocabulary: str, end_id: int, limit: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens of each piece."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of = library_ids(vocabulary)
        end = np.array([end_id], "<u4")
        for batch in worker_for("library", batches):
            row, start, length, crc, total = [], [], [], [], []
            for i, ids in enumerate(ids_of.texts(batch.column(1))):
                ids = np.concatenate([ids, end])
                n = len(ids)
                for at in range(0, n, limit):
                    part = ids[at : at + limit]
                    row.append(i)
                    start.append(at)
                    length.append(len(part))
                    crc.append(zlib.crc32(part))
                    total.append(n)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row, pa.int64())), *(pa.array(c, pa.int64()) for c in (start, length, crc, total))], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return df.select(F.col(id_col).cast("bigint"), text_col).mapInArrow(run, "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint")


def shortest_pack_first(histogram: dict[int, int], limit: int) -> list[tuple[list[int], int]]:
    """Patterns (lengths of one sequence, longest first) and their counts.

    Lengths are placed from the longest to the shortest. Each goes to the pack
    that is shortest so far, if it fits there, else it opens new packs.
    """
    # packs by length, the shortest on top; equal patterns share an entry
    packs: list[tuple[int, int, int, tuple]] = []
    done: list[tuple[list[int], int]] = []
    serial = 0
    shortest = min(histogram, default=0)

    def put(used: int, count: int, pattern: tuple) -> None:
        nonlocal serial
        if used + shortest > limit:  # nothing fits any more
            done.append((_unfold(pattern), count))
        else:
            heapq.heappush(packs, (used, serial, count, pattern))
            serial += 1

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            if packs and packs[0][0] + length <= limit:
                # one into each of the packs that are equally short, which may be the shortest again
                used, _, count, pattern = heapq.heappop(packs)
                taken = min(count, left)
                if taken < count:
                    put(used, count - taken, pattern)
                put(used + length, taken, (length, pattern))
                left -= taken
            else:
                # a new pack stays the shortest until it is full
                fits = limit // length
                full, over = divmod(left, fits)
                for copies, count in ((fits, full), (over, 1)):
                    if copies and count:
                        pattern: tuple = ()
                        for _ in range(copies):
                            pattern = (length, pattern)
                        put(copies * length, count, pattern)
                left = 0
    done.extend((_unfold(pattern), count) for _, _, count, pattern in packs)
    return done


def _unfold(pattern: tuple) -> list[int]:
    out = []
    while pattern:
        length, pattern = pattern
        out.append(length)
    return out[::-1]


def rank_ranges(patterns: list[tuple[list[int], int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, end rank, first sequence, offset) for each place."""
    used: dict[int, int] = {}
    sequence, out = 0, []
    for lengths, count in patterns:
        offset = 0
        for length in lengths:
            first = used.get(length, 0)
            out.append((length, first, first + count, sequence, offset))
            used[length] = first + count
            offset += length
        sequence += count
    return out


def pack(df: DataFrame, vocabulary: str, end_id: int = 2, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens,
    sequence_id, offset.

    Every document ends with ``end_id``, so a null or empty text is one piece of
    one token. Repeated rows and null ids are packed like any others. An empty
    table gives an empty result.
    """
    spark = df.sparkSession
    ship(spark)
    cut = Written(pieces(df, vocabulary, end_id, limit, id_col, text_col), "pieces")
    histogram = {r["length"]: r["n"] for r in cut.df.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``limit`` rows
    shares = [(length, -(-n // RANKED_TOGETHER)) for length, n in histogram.items()]
    shares = F.broadcast(spark.createDataFrame(shares or [(0, 1)], "length bigint, shares bigint"))
    salted = cut.df.join(shares, "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.col("shares"))).drop("shares")
    counts = Written(salted.groupBy("length", "salt").agg(F.count("*").alias("n")), "piece-counts")
    ranges = rank_ranges(shortest_pack_first(histogram, limit))
    places = spark.createDataFrame(ranges or [(0, 0, 0, 0, 0)], "p_length bigint, first bigint, end bigint, sequence bigint, offset bigint")
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.df.select("length", "salt", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    within = Window.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32")
    ranked = salted.withColumn("own", F.row_number().over(within) - 1).join(bases, ["length", "salt"]).withColumn("rank", F.col("own") + F.col("base"))
    if len(ranges) <= PLACES_BROADCAST:
        places = F.broadcast(places)
    placed = ranked.join(places, (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("end")))
    return placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("sequence") + F.col("rank") - F.col("first")).alias("sequence_id"), "offset")
