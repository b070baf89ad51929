"""Document quality by attention over passages.

A document is a bag of passages and its label belongs to the bag. Every passage
of the whole text is described by counts of its characters and words, encoded
by a small layer, and weighted by gated attention: one layer says what a
passage shows, another how far to let it through, and the weights are a softmax
over the document's passages. The weighted sum of the passage codes gives the
score. Encoder, attention and scorer are learned together from document labels.

Features are made on the executors; the model (a few thousand numbers) is
fitted on a bounded sample of labelled documents on the driver and broadcast.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from pagecast.cluster import Written, ship
from pagecast.llm.words import mix, strings, utf8, worker_for

PASSAGE_WORDS = 64
#: Bytes of text whose passages are described together (some 60 bytes are held for each).
SHARE = 1 << 18
BUCKETS = 48
_HAND = 18
WIDTH = _HAND + BUCKETS


@dataclass(frozen=True)
class FitPlan:
    #: labelled documents that the model is fitted on, at most (least hash of the id first)
    documents: int = 8192
    #: passages of the fit together; documents are taken whole, in the order of
    #: their ids' hashes, until the next would go beyond
    passages: int = 250_000
    epochs: int = 24
    batch: int = 256
    code: int = 16
    gate: int = 8
    rate: float = 0.01
    decay: float = 1e-4


def _classes() -> np.ndarray:
    table = np.zeros((256, 8), bool)
    for k, chars in enumerate((b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:!?'\"()-", b"#*$%&|<>@~^_=+/\\{}[]", bytes(range(128, 256)), b"|", b"!", b".!?")):
        table[list(chars), k] = True
    return table


_CLASS = _classes()
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BYTE_VALUE = mix(np.arange(1, 257, dtype=np.uint64))
with np.errstate(over="ignore"):
    _POWER = np.multiply.accumulate(np.concatenate([[np.uint64(1)], np.full(255, 0x9E3779B97F4A7C15, np.uint64)]))


def _cut(raw: bytes) -> Iterator[bytes]:
    """A long text in parts of whole passages."""
    at, window = 0, SHARE
    while len(raw) - at > window:
        space = _IS_SPACE[np.frombuffer(raw, np.uint8, window, at)]
        starts = np.flatnonzero(~space & np.concatenate([[True], space[:-1]]))
        words = max(0, len(starts) - 1) // PASSAGE_WORDS * PASSAGE_WORDS
        if words:
            yield raw[at : at + int(starts[words])]
            at, window = at + int(starts[words]), SHARE
        else:  # less than a passage of very long words
            window *= 2
    yield raw[at:]


def bags(texts: Iterable[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """``passages`` of some whole texts at a time, in order: those of many short
    ones, or of one long text, which is described part by part."""
    held: list[bytes] = []
    size = 0
    for text in texts:
        raw = utf8(text)
        if held and size + len(raw) > SHARE:
            yield passages(held)
            held, size = [], 0
        if len(raw) > SHARE:
            parts = [passages([part])[0] for part in _cut(raw)]
            if len(parts) > 1 and not parts[-1].any():  # white space behind the last passage
                parts.pop()
            yield np.concatenate(parts), np.array([sum(map(len, parts))])
        else:
            held.append(raw)
            size += len(raw)
    if held:
        yield passages(held)


def passages(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages of all texts, and the number of passages of
    each text. A text without words is one passage of zeros."""
    sizes = np.array([len(r) + 1 for r in raw], np.int64)
    data = np.frombuffer(b"\n".join(raw) + b"\n", np.uint8) if raw else np.empty(0, np.uint8)
    space = _IS_SPACE[data]
    before = np.concatenate([[True], space[:-1]]) if len(space) else space
    starts = np.flatnonzero(~space & before)
    ends = np.flatnonzero(space & ~before)
    doc_of = np.searchsorted(np.cumsum(sizes), starts, "right")
    words_in = np.bincount(doc_of, minlength=len(raw))
    bags = np.maximum(1, -(-words_in // PASSAGE_WORDS))
    base = np.cumsum(bags) - bags
    out = np.zeros((int(bags.sum()), WIDTH), np.float32)
    if not len(starts):
        return out, bags
    place = np.arange(len(starts)) - (np.cumsum(words_in) - words_in)[doc_of]
    passage = base[doc_of] + place // PASSAGE_WORDS
    length = (ends - starts).astype(np.float64)
    kinds = np.empty((len(starts), _CLASS.shape[1]), np.int32)
    for k in range(_CLASS.shape[1]):
        total = np.concatenate([[0], np.cumsum(_CLASS[data, k], dtype=np.int32)])
        kinds[:, k] = total[ends] - total[starts]
    upper, digit, mark, symbol, wide, pipe, bang, _ = kinds.T
    within = np.arange(len(data)) - np.repeat(starts, np.diff(np.concatenate([starts, [len(data)]])))[: len(data)] if starts[0] == 0 else None
    if within is None:
        lead = starts[0]
        within = np.concatenate([np.zeros(lead, np.int64), np.arange(len(data) - lead) - np.repeat(starts - lead, np.diff(np.concatenate([starts, [len(data)]])))])
    folded = np.where((data >= 65) & (data <= 90), data + 32, data)
    with np.errstate(over="ignore"):
        value = _BYTE_VALUE[folded] * _POWER[within & 255]
        value[space] = 0
        word = mix(np.add.reduceat(value, starts))
    new = np.concatenate([[True], passage[1:] != passage[:-1]])
    edge = np.flatnonzero(new)
    rows = passage[edge]
    n = np.diff(np.concatenate([edge, [len(starts)]])).astype(np.float64)
    total = lambda x: np.add.reduceat(x.astype(np.float64), edge)
    chars = total(length)
    repeat = (word == np.concatenate([[np.uint64(0)], word[:-1]])) & ~new
    distinct = np.unique((passage.astype(np.uint64) << np.uint64(40)) | (word >> np.uint64(24))) >> np.uint64(40)
    lines = np.concatenate([[0], np.cumsum(data == 10)])
    letters = length - mark - symbol
    hand = [
        np.log1p(n) / 4,
        chars / n / 8,
        total(upper) / chars,
        total(digit) / chars,
        total(mark) / chars,
        total(symbol) / chars,
        total(wide) / chars,
        total(symbol > 0) / n,
        total((upper >= 2) & (upper + wide >= letters)) / n,
        total(letters == 0) / n,
        total(bang) / n,
        np.bincount(distinct.astype(np.int64), minlength=len(out))[rows] / n,
        total(repeat) / n,
        total(letters <= 3) / n,
        total(_CLASS[data[ends - 1], 7]) / n,
        (lines[ends[np.concatenate([edge[1:], [len(starts)]]) - 1]] - lines[starts[edge]] + 1) / n,
        total(_CLASS[data[starts], 0]) / n,
        np.sqrt(np.maximum(0, total(length**2) / n - (chars / n) ** 2)) / 4,
    ]
    out[rows, :_HAND] = np.stack(hand, 1)
    bag = np.bincount(passage * BUCKETS + (word % np.uint64(BUCKETS)).astype(np.int64), minlength=len(out) * BUCKETS).reshape(-1, BUCKETS)
    out[rows, _HAND:] = np.sqrt(bag[rows] / n[:, None])
    return out, bags


class AttentionBag:
    """Encoder, gated attention and scorer, with their gradient."""

    NAMES = ("code", "code_bias", "show", "let", "weight", "score", "bias")

    def __init__(self, plan: FitPlan = FitPlan()):
        rng = np.random.default_rng(11)
        draw = lambda a, b: rng.normal(0, 1 / np.sqrt(a), (a, b))
        self.plan = plan
        self.mean, self.scale = np.zeros(WIDTH), np.ones(WIDTH)
        self.p = {
            "code": draw(WIDTH, plan.code),
            "code_bias": np.zeros(plan.code),
            "show": draw(plan.code, plan.gate),
            "let": draw(plan.code, plan.gate),
            "weight": draw(plan.gate, 1)[:, 0],
            "score": draw(plan.code, 1)[:, 0],
            "bias": np.zeros(1),
        }

    def forward(self, x: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, tuple]:
        """x: standardised passages of all bags, starts: where each bag begins."""
        p = self.p
        h = np.tanh(x @ p["code"] + p["code_bias"])
        s, g = np.tanh(h @ p["show"]), 1 / (1 + np.exp(-np.clip(h @ p["let"], -30, 30)))
        e = (s * g) @ p["weight"]
        sizes = np.diff(np.concatenate([starts, [len(x)]]))
        bag = np.repeat(np.arange(len(starts)), sizes)
        a = np.exp(e - np.maximum.reduceat(e, starts)[bag])
        a /= np.add.reduceat(a, starts)[bag]
        z = np.add.reduceat(a[:, None] * h, starts)
        logit = z @ p["score"] + p["bias"][0]
        return 1 / (1 + np.exp(-np.clip(logit, -30, 30))), (x, starts, bag, h, s, g, a, z)

    def gradient(self, probability: np.ndarray, label: np.ndarray, kept: tuple) -> dict[str, np.ndarray]:
        x, starts, bag, h, s, g, a, z = kept
        p = self.p
        d_logit = (probability - label) / len(label)
        d_z = d_logit[:, None] * p["score"]
        d_a = (h * d_z[bag]).sum(1)
        d_e = a * (d_a - np.add.reduceat(a * d_a, starts)[bag])
        d_sg = d_e[:, None] * p["weight"]
        d_s, d_g = d_sg * g * (1 - s**2), d_sg * s * g * (1 - g)
        d_h = a[:, None] * d_z[bag] + d_s @ p["show"].T + d_g @ p["let"].T
        d_pre = d_h * (1 - h**2)
        return {
            "code": x.T @ d_pre,
            "code_bias": d_pre.sum(0),
            "show": h.T @ d_s,
            "let": h.T @ d_g,
            "weight": (s * g).T @ d_e,
            "score": z.T @ d_logit,
            "bias": np.array([d_logit.sum()]),
        }

    def scaled(self, features: np.ndarray) -> np.ndarray:
        return np.clip((features - self.mean) / self.scale, -8, 8)

    def fit(self, bags: list[np.ndarray], labels: np.ndarray) -> AttentionBag:
        plan = self.plan
        number = sum(map(len, bags))
        self.mean = sum(b.sum(0, dtype=np.float64) for b in bags) / number
        self.scale = np.sqrt(sum(((b - self.mean) ** 2).sum(0) for b in bags) / number) + 1e-3
        rng = np.random.default_rng(5)
        first = {k: np.zeros_like(v) for k, v in self.p.items()}
        second = {k: np.zeros_like(v) for k, v in self.p.items()}
        step = 0
        for epoch in range(plan.epochs):
            order = rng.permutation(len(bags))
            rate = plan.rate * (1 - epoch / plan.epochs)
            for at in range(0, len(order), plan.batch):
                chosen = order[at : at + plan.batch]
                sizes = np.array([len(bags[i]) for i in chosen])
                probability, kept = self.forward(self.scaled(np.concatenate([bags[i] for i in chosen])), np.cumsum(sizes) - sizes)
                step += 1
                for k, d in self.gradient(probability, labels[chosen], kept).items():
                    d = d + plan.decay * self.p[k]
                    first[k] = 0.9 * first[k] + 0.1 * d
                    second[k] = 0.999 * second[k] + 0.001 * d * d
                    self.p[k] -= rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def scores(self, texts: Iterable[str | None]) -> np.ndarray:
        found = [self.forward(self.scaled(features), np.cumsum(sizes) - sizes)[0] for features, sizes in bags(texts)]
        return np.concatenate(found) if found else np.empty(0)


def held_out(doc_id) -> F.Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, plan: FitPlan = FitPlan(), id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> AttentionBag | None:
    """A model from the labelled documents that are not held out; None without any.

    Null ids and labels take no part; an id with several labels counts as 1 if
    half of them are; of rows that share an id the greatest text is taken. Only
    ids, labels and texts are read, and of a document every passage.
    """
    ship(docs.sparkSession)
    known = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).alias("label")).where("doc_id is not null and label is not null")
    known = known.where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg((F.avg("label") >= 0.5).cast("int").alias("label"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(plan.documents)
    texts = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "doc_id")
    texts = texts.groupBy("doc_id", "label").agg(F.max("text").alias("text")).select(F.col("doc_id").cast("string"), F.xxhash64("doc_id").alias("place"), "label", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("classifier", batches):
            at = 0
            for features, sizes in bags(strings(batch.column("text"))):
                own = [part.astype(np.float16).tobytes() for part in np.split(features, np.cumsum(sizes)[:-1])]
                few = batch.slice(at, len(sizes))
                at += len(sizes)
                yield pa.RecordBatch.from_arrays([few.column(0), few.column(1), few.column(2), pa.array(sizes, pa.int64()), pa.array(own, pa.binary())], ["doc_id", "place", "label", "n", "features"])

    made = Written(texts.mapInArrow(run, "doc_id string, place bigint, label int, n bigint, features binary"), "quality-bags")
    # at most ``plan.documents`` short rows
    sizes = sorted((r["place"], r["doc_id"], r["n"]) for r in made.df.select("place", "doc_id", "n").collect())
    fits = int(np.searchsorted(np.cumsum([n for *_, n in sizes]), plan.passages, "right")) if sizes else 0
    if not fits:
        made.drop()
        return None
    place, doc_id, _ = sizes[fits - 1]
    upto = (F.col("place") < place) | (F.col("place") == place) & (F.col("doc_id") <= doc_id)
    rows = made.df.where(upto).collect()
    made.drop()
    rows.sort(key=lambda r: (r["place"], r["doc_id"]))
    found = [np.frombuffer(r["features"], np.float16).reshape(-1, WIDTH) for r in rows]
    return AttentionBag(plan).fit(found, np.array([r["label"] for r in rows], np.float64))


def with_scores(df: DataFrame, model: AttentionBag | None, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All columns of ``df`` and the score of the text, 0 to 1. Null and empty
    texts are scored as one passage without words; without a model every text
    scores 0.5."""
    if score_col in df.columns:
        raise ValueError(f"column {score_col} exists already")
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    at = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in worker_for("classifier", batches):
            column = batch.column(at)
            found = shared.value.scores(strings(column)) if shared.value else np.full(len(column), 0.5)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.float64())], [*batch.schema.names, score_col])

    return df.mapInArrow(run, StructType([*df.schema, StructField(score_col, DoubleType())]))
