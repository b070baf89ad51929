"""Removal of repeated passages by sliding spans of sentences.

Every text is cut into sentences. From each sentence the shortest run of
consecutive sentences that is long enough to matter starts, and at each
sentence the shortest such run ends; both are hashed. Runs with the same hash
are the same words, wherever they stand. The first place of a run, by document
and then by position, stays; the sentences of its other places are removed.

A passage that is repeated in full sentences is covered completely, however
long it is: all its sentences but the last few start a run inside it, and those
are covered by the run that ends with its last one. The text around a removed
sentence stays as it was, so a document without repeats is returned unchanged.

A run is an aggregate of one count and one smallest place per hash, so a
passage that a third of all documents share is summed up before the shuffle;
the places to remove come from a join with the repeated runs, broadcast if they
are few, else split on common hashes.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from pagecast.cluster import Written, ship
from pagecast.llm.words import mix, strings, unused, utf8, word_hashes, worker_for

#: Fixed: a sentence ends with its last mark or at a line's end, white space after it included.
_SENTENCE = re.compile(r"(?:[^.!?\n]|[.!?]+(?![.!?\s]))*(?:[.!?]+[ \t\r\x0b\x0c]*\n?|\n|$)")
#: Repeated runs are broadcast up to this number (some 40 MB); more are joined by a shuffle, whose hot hashes Spark splits.
BROADCAST_RUNS = 1_000_000
_ODD = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class SpanPlan:
    sentences: int = 2  # of a run, at least
    words: int = 20  # of such a run, at least
    alone: int = 40  # words that make a single sentence a run


def sentences(text: str | None) -> list[str]:
    """Pieces that give the text again when joined; white space without words
    belongs to the sentence before it."""
    out: list[str] = []
    for piece in _SENTENCE.findall(text or ""):
        if not piece:
            continue
        if out and not piece.split():
            out[-1] += piece
        else:
            out.append(piece)
    return out


def runs(parts: list[str], plan: SpanPlan) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash, first and last sentence of each run of a text."""
    words = [utf8(p).lower().split() for p in parts]
    counts = np.array([len(w) for w in words], np.int64)
    n = len(parts)
    if not n or counts.sum() < plan.words:
        return np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int64)
    hashes = word_hashes([w for part in words for w in part])
    ends = np.cumsum(counts)
    starts = ends - counts
    first = np.arange(n)
    # the least last sentence at which a run from each first one is long enough, and the mirror image
    enough = np.searchsorted(ends, starts + plan.words)
    last = np.minimum(np.maximum(enough, first + plan.sentences - 1), np.searchsorted(ends, starts + plan.alone))
    need = np.searchsorted(starts, ends - plan.words, "right") - 1
    back = np.maximum(np.minimum(need, first - plan.sentences + 1), np.searchsorted(starts, ends - plan.alone, "right") - 1)
    forward, backward = last < n, back >= 0
    pairs = np.unique(np.concatenate([np.stack([first[forward], last[forward]], 1), np.stack([back[backward], first[backward]], 1)]), axis=0)
    a, b = pairs[:, 0], pairs[:, 1]
    keep = counts[a] + counts[b] > 0
    a, b = a[keep], b[keep]
    # prefix sums of words weighted by powers of an odd number; a run's sum is moved to power zero
    with np.errstate(over="ignore"):
        powers = np.full(len(hashes) + 1, _ODD, np.uint64)
        powers[0] = 1
        powers = np.multiply.accumulate(powers)
        inverse = np.full(len(hashes) + 1, pow(int(_ODD), -1, 1 << 64), np.uint64)
        inverse[0] = 1
        inverse = np.multiply.accumulate(inverse)
        sums = np.concatenate([np.zeros(1, np.uint64), np.add.accumulate(mix(hashes) * powers[:-1])])
        value = (sums[ends[b]] - sums[starts[a]]) * inverse[starts[a]]
        value = mix(value ^ (ends[b] - starts[a]).astype(np.uint64) * _ODD)
    return value, a, b


def spans(docs: DataFrame, plan: SpanPlan) -> DataFrame:
    """docs(doc_id, text) -> (hash, doc_id, first, last)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("spans", batches):
            hashes, firsts, lasts, owner = [], [], [], []
            for i, text in enumerate(strings(batch.column(1))):
                h, a, b = runs(sentences(text), plan)
                hashes.append(h.view(np.int64))
                firsts.append(a)
                lasts.append(b)
                owner.append(np.full(len(h), i))
            join = lambda xs, t: np.concatenate(xs).astype(t) if xs else np.empty(0, t)
            yield pa.RecordBatch.from_arrays(
                [pa.array(join(hashes, np.int64)), batch.column(0).take(pa.array(join(owner, np.int64))), pa.array(join(firsts, np.int32)), pa.array(join(lasts, np.int32))],
                ["hash", "doc_id", "first", "last"],
            )

    return docs.mapInArrow(run, "hash bigint, doc_id bigint, first int, last int")


def _covered(spans_of: list[dict]) -> set[int]:
    return {k for s in spans_of for k in range(s["first"], s["last"] + 1)}


def removals(docs: DataFrame, plan: SpanPlan) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, gone: runs to remove) for documents that
    lose a sentence; marked for broadcast if it is small."""
    found = Written(spans(docs, plan), "span-runs")
    place = F.struct("doc_id", "first")
    repeated = found.df.groupBy("hash").agg(F.count("*").alias("n"), F.min(place).alias("kept")).where("n > 1").select("hash", "kept")
    known = Written(repeated, "span-repeats")
    first = F.broadcast(known.df) if known.df.count() <= BROADCAST_RUNS else known.df
    later = found.df.join(first, "hash").where(place != F.col("kept")).select("doc_id", "first", "last")
    out = Written(later.groupBy("doc_id").agg(F.collect_set(F.struct("first", "last")).alias("gone")), "span-removals")
    found.drop()
    known.drop()
    runs = out.df.agg(F.sum(F.size("gone"))).first()[0] or 0
    return F.broadcast(out.df) if runs <= BROADCAST_RUNS else out.df


def remove_repeats(df: DataFrame, plan: SpanPlan = SpanPlan(), id_col: str = "doc_id", text_col: str = "text", counts: tuple[str, str] | None = None) -> DataFrame:
    """``df`` with the repeated sentences gone from its texts.

    With ``counts`` = names for (number of sentences, number removed), these
    columns are added. Null texts stay null, empty ones empty; a document may
    become empty. Rows with a null id are returned as they are and take no part.
    Rows that repeat an id with the same text are one document to this
    operator: each keeps what that document keeps.
    """
    spark = df.sparkSession
    ship(spark)
    key, gone = unused("_span_doc", df), unused("_span_gone", df)
    docs = df.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    cut = removals(docs, plan)
    cut = cut.select(F.col("doc_id").alias(key), F.col("gone").alias(gone))
    both = df.join(cut, df[id_col] == F.col(key), "left").drop(key)
    at, names = df.columns.index(text_col), df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("spans", batches):
            texts, total, lost = [], [], []
            for text, marked in zip(strings(batch.column(at)), strings(batch.column(len(names)))):
                if marked or counts:
                    parts = sentences(text)
                    away = _covered(marked or [])
                    total.append(len(parts))
                    lost.append(len(away))
                    if away:
                        text = "".join(p for k, p in enumerate(parts) if k not in away)
                texts.append(text)
            columns = list(batch.columns[: len(names)])
            columns[at] = pa.array(texts, pa.string())
            if counts:
                columns += [pa.array(total, pa.int64()), pa.array(lost, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, [*names, *(counts or ())])

    schema = StructType([*df.schema])
    for name in counts or ():
        schema = StructType([*schema, *spark.createDataFrame([], f"`{name}` bigint").schema])
    return both.mapInArrow(run, schema)
