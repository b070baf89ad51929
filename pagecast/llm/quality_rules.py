"""Quality rules with thresholds that the corpus itself sets.

Each document gets a handful of measures. Instead of one fixed cutoff per
measure, the documents of every (language, source) pair set their own: a KLL
quantile sketch per measure and pair is built by partial aggregation, the
sketches of pairs are merged into sketches of languages and of the corpus, and
a fence is read from each, three quartile distances beyond the outer quartile.
A pair with few documents uses its language's fence, a small language the
corpus's. The fences are joined back and filter the documents.

Repeated lines and passages are absent from most documents, so their quartiles
are often equal. Their fence also looks at the tail of the documents that pass
the base rule: it lies half as far again beyond the outer quartile as the last
hundredth of those documents begins.

Sketches merge in any order and hold a bounded number of values, so a pair with
a third of all documents costs one sketch per task and no group is collected.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from pagecast.cluster import Written, ship
from pagecast.llm.words import strings, unused_prefix, utf8, window_hashes, word_hashes, worker_for

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
_SYMBOLS = re.compile(rb"[#*$%&|<>]")
_WINDOW = 5
#: Fences of at most so many (language, source) pairs are broadcast (under 10 MB); more are joined by a shuffle.
BROADCAST_PAIRS = 50_000


def measure(text: str | None) -> tuple[int, int, int, int, int]:
    """The five counts of one text, in the order of ``COUNTS``."""
    raw = utf8(text)
    words = raw.split()
    n = len(words)
    joined = b"".join(words)
    # code points: the bytes that do not continue a UTF-8 character
    chars = len(joined) - int(np.count_nonzero((np.frombuffer(joined, np.uint8) & 0xC0) == 0x80))
    lines = [line for line in raw.split(b"\n") if line.split()]
    repeated = 0
    if n >= _WINDOW:
        windows = window_hashes(word_hashes(words), _WINDOW)
        order = np.argsort(windows, kind="stable")
        same = windows[order][1:] == windows[order][:-1]
        twice = np.zeros(len(windows) + 1, bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        starts = np.flatnonzero(twice)
        edge = np.zeros(n + 1, np.int64)
        np.add.at(edge, starts, 1)
        np.add.at(edge, starts + _WINDOW, -1)
        repeated = int(np.count_nonzero(np.cumsum(edge[:n])))
    return n, chars, len(_SYMBOLS.findall(joined)), len(lines) - len(set(lines)), repeated


def with_counts(df: DataFrame, text_col: str = "text", prefix: str = "") -> DataFrame:
    """All columns of ``df`` and the counts (named ``prefix`` + count)."""
    ship(df.sparkSession)
    names = [prefix + c for c in COUNTS]
    clash = set(names) & set(df.columns)
    if clash:
        raise ValueError(f"columns exist already: {sorted(clash)}")
    at = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("rules", batches):
            values = np.array([measure(t) for t in strings(batch.column(at))], np.int64).reshape(-1, len(COUNTS))
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(v) for v in values.T)], [*batch.schema.names, *names])

    return df.mapInArrow(run, StructType([*df.schema, *(StructField(name, LongType()) for name in names)]))


#: (measure, numerator, denominator, does a low value speak against a document, least distance of the fence)
_RATIOS = (
    ("mean_word", "word_chars", "n_words", True, 2.0),
    ("symbols", "n_symbols", "word_chars", False, 0.05),
    ("dup_lines", "n_dup_lines", "n_words", False, 0.005),
    ("repeats", "n_repeat_words", "n_words", False, 0.05),
)
#: Measures that most documents have none of: sketched over what passes the base rule, which has a cutoff on the same counts.
_RARE = ("dup_lines", "repeats")
_TAIL, _TAIL_REACH = 0.99, 1.5


def _ratios(prefix: str) -> dict[str, F.Column]:
    return {name: F.col(prefix + top) / F.nullif(F.col(prefix + below), F.lit(0)) for name, top, below, _, _ in _RATIOS}


def _base_failed(prefix: str) -> F.Column:
    n, repeats = F.col(prefix + "n_words"), F.col(prefix + "n_repeat_words")
    return (n < 10) | (100 * repeats > 20 * n)


def fences(counted: DataFrame, lang_col: str, source_col: str, prefix: str, min_docs: int, k: int = 400) -> DataFrame:
    """(language, source) -> one upper and lower fence per measure.

    Rows that fail the base rule take no part in the rare measures' fences; a
    null language or source is a group of its own.
    """
    values = _ratios(prefix)
    names = [r[0] for r in _RATIOS]
    keys = [F.col(lang_col).alias("_lang"), F.col(source_col).alias("_source")]
    # a null is no value of a sketch
    taken = {n: F.when(~_base_failed(prefix), F.coalesce(v, F.lit(0.0))) if n in _RARE else v for n, v in values.items()}
    shown = counted.where(values[names[0]].isNotNull()).select(*keys, *(v.alias(n) for n, v in taken.items()))
    pair = shown.groupBy("_lang", "_source").agg(
        F.count("*").alias("_n"), *(F.kll_sketch_agg_double(n if n in _RARE else F.coalesce(n, F.lit(0.0)), F.lit(k)).alias(n) for n in names)
    )
    # read three times below; the texts are read for it once
    pair = Written(pair, "quality-sketches").df
    merged = lambda keys: pair.groupBy(*keys).agg(F.sum("_n").alias("_m"), *(F.kll_merge_agg_double(n, F.lit(k)).alias(f"{n}_up") for n in names))
    language, corpus = merged(["_lang"]), merged([])
    pick = lambda up, own, n: F.when(F.col("_n") >= min_docs, F.col(own)).otherwise(F.col(up)).alias(n)
    language = language.select(F.col("_lang"), F.col("_m").alias("_n"), *(F.col(f"{n}_up").alias(n) for n in names))
    corpus = corpus.select(*(F.col(f"{n}_up").alias(f"{n}_all") for n in names))
    language = language.join(F.broadcast(corpus)).select("_lang", *(pick(f"{n}_all", n, f"{n}_up") for n in names))
    # one row a language, and a handful of sketches in it: bounded by the number of languages
    chosen = pair.alias("p").join(language.alias("l"), F.col("p._lang").eqNullSafe(F.col("l._lang")), "left").select(
        F.col("p._lang").alias("_lang"), "_source", *(pick(f"{n}_up", n, n) for n in names)
    )
    out = []
    for name, _, _, low, least in _RATIOS:
        # an empty sketch (every document fails the base rule) gives no fence
        q = lambda at, n=name: F.when(F.kll_sketch_get_n_double(n) > 0, F.kll_sketch_get_quantile_double(F.col(n), F.lit(at)))
        reach = F.greatest(3 * (q(0.75) - q(0.25)), F.lit(least))
        if name in _RARE:
            reach = F.greatest(reach, _TAIL_REACH * (q(_TAIL) - q(0.75)))
        out.append((q(0.75) + reach).alias(f"{name}_most"))
        if low:
            out.append((q(0.25) - reach).alias(f"{name}_least"))
    return chosen.select("_lang", "_source", *out)


def judged(df: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source", min_docs: int = 200, prefix: str = "_q_") -> DataFrame:
    """All columns of ``df``, the counts, ``<prefix>base_failed`` and ``<prefix>kept``.

    A document without words fails the base rule. Null and empty texts count
    as no words; nulls in language or source form their own group; repeated
    rows are judged alike; an empty table gives an empty result.
    """
    counted = with_counts(df, text_col, prefix)
    # the second pass over the texts is cheaper than keeping or shuffling them
    bound = fences(with_counts(df.select(text_col, F.col(lang_col).alias("_l"), F.col(source_col).alias("_s")), text_col, prefix), "_l", "_s", prefix, min_docs)
    b = unused_prefix("_b_", counted)
    bound = bound.select(F.col("_lang").alias(f"{b}lang"), F.col("_source").alias(f"{b}source"), *(F.col(c).alias(f"{b}{c}") for c in bound.columns[2:]))
    bound = Written(bound, "quality-fences").df
    if bound.count() <= BROADCAST_PAIRS:
        bound = F.broadcast(bound)
    both = counted.join(bound, counted[lang_col].eqNullSafe(F.col(f"{b}lang")) & counted[source_col].eqNullSafe(F.col(f"{b}source")), "left")
    failed = _base_failed(prefix)
    inside = F.lit(True)
    for name, value in _ratios(prefix).items():
        value = F.coalesce(value, F.lit(0.0))
        inside = inside & F.coalesce(value <= F.col(f"{b}{name}_most"), F.lit(True))
        if f"{b}{name}_least" in both.columns:
            inside = inside & F.coalesce(value >= F.col(f"{b}{name}_least"), F.lit(True))
    return both.select(*counted.columns, failed.alias(prefix + "base_failed"), (~failed & inside).alias(prefix + "kept"))


def filtered(df: DataFrame, **options) -> DataFrame:
    """``df`` without the documents that the rules reject; same columns."""
    prefix = unused_prefix("_q_", df)
    return judged(df, prefix=prefix, **options).where(F.col(f"{prefix}kept")).select(*df.columns)
