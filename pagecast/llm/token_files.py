"""Token ids in compact binary files.

Ids are renumbered by falling frequency, so that common ones are small, and
written in byte-aligned variable-length coding: each number takes one to four
bytes, its size minus one is two bits of a control byte, and control bytes and
data bytes are two separate streams. The decoder never branches: a table gives
for each control byte the four sizes, their running sums give the place of
every number, and the bytes are gathered by numpy.

A file holds a run of documents in the order of their ids. Its ids lie in
segments of a fixed number of ids, coded one by one, so that writing and reading
hold one segment at a time and a document may reach over several. All integers
are little endian: magic, number of documents, of ids and of segments (u64
each), document ids (i64), nulls among them (u8), ends of the documents in ids
(u64), numbers of data bytes of the segments (u64), then control bytes and data
bytes of each segment.

Beside the files lie two small Parquet tables: ``index`` with the name of every
file, its place in the order and the ids it holds, and ``ranks`` with the id of
each rank. Files are written under a temporary name and renamed when complete,
so a task that is run again after a lost executor replaces a file by its equal.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pagecast.cluster import Written, full_address, scratch_path, ship
from pagecast.llm.library_tokens import library_ids
from pagecast.llm.words import worker_for

MAGIC = 0x32564B54  # "TKV2"
#: Ids in a file, about; a file holds whole documents.
FILE_IDS = 4_000_000
#: Ids in a segment.
SEGMENT = 1 << 17

_SIZES = np.array([[(c >> (2 * k) & 3) + 1 for k in range(4)] for c in range(256)], np.uint8)
_MASKS = np.array([0, 0xFF, 0xFFFF, 0xFFFFFF, 0xFFFFFFFF], np.uint32)


def pack_numbers(values: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and data bytes of unsigned 32-bit numbers."""
    values = np.ascontiguousarray(values, "<u4")
    sizes = 1 + (values > 0xFF).astype(np.uint8) + (values > 0xFFFF) + (values > 0xFFFFFF)
    padded = np.zeros(-(-len(values) // 4) * 4, np.uint8)
    padded[: len(values)] = sizes - 1
    quads = padded.reshape(-1, 4)
    control = quads[:, 0] | quads[:, 1] << 2 | quads[:, 2] << 4 | quads[:, 3] << 6
    held = np.arange(4, dtype=np.uint8)[None, :] < sizes[:, None]
    return control.astype(np.uint8).tobytes(), values.view(np.uint8).reshape(-1, 4)[held].tobytes()


def unpack_numbers(control: np.ndarray, data: np.ndarray, count: int) -> np.ndarray:
    sizes = _SIZES[control].reshape(-1)[:count]
    begins = np.cumsum(sizes, dtype=np.int64) - sizes
    padded = np.concatenate([data, np.zeros(4, np.uint8)])
    words = padded[begins].astype(np.uint32)
    for k in range(1, 4):
        words |= padded[begins + k].astype(np.uint32) << np.uint32(8 * k)
    return words & _MASKS[sizes]


class FileWriter:
    """Collects documents as coded segments and writes them as one file."""

    def __init__(self):
        self.docs: list[int | None] = []
        self.ends: list[int] = []
        self.coded: list[tuple[bytes, bytes]] = []
        self.waiting: list[np.ndarray] = []
        self.ids = self.open = 0

    def add(self, doc: int | None, ranked: np.ndarray) -> None:
        self.docs.append(doc)
        self.ids += len(ranked)
        self.ends.append(self.ids)
        self.waiting.append(ranked)
        self.open += len(ranked)
        if self.open >= SEGMENT:
            self._code(False)

    def _code(self, all_of_it: bool) -> None:
        values = np.concatenate(self.waiting) if self.waiting else np.empty(0, np.uint32)
        upto = len(values) if all_of_it else len(values) - len(values) % SEGMENT
        self.coded.extend(pack_numbers(values[at : min(at + SEGMENT, upto)]) for at in range(0, upto, SEGMENT))
        self.waiting, self.open = [values[upto:].copy()], len(values) - upto

    def write(self, out) -> None:
        self._code(True)
        out.write(np.array([MAGIC, len(self.docs), self.ids, len(self.coded)], "<u8").tobytes())
        out.write(np.array([0 if d is None else d for d in self.docs], "<i8").tobytes())
        out.write(np.array([d is None for d in self.docs], np.uint8).tobytes())
        out.write(np.array(self.ends, "<u8").tobytes())
        out.write(np.array([len(data) for _, data in self.coded], "<u8").tobytes())
        for control, data in self.coded:
            out.write(control)
            out.write(data)


def parse_file(source) -> Iterator[tuple[list[int | None], np.ndarray, list[np.ndarray]]]:
    """The documents of an open file, some at a time: their ids, where they
    begin in the file, and the rank-coded ids of each. Holds one segment and
    what has begun of a document."""

    def take(size: int, kind: str) -> np.ndarray:
        raw = source.read(size * np.dtype(kind).itemsize)
        if len(raw) != size * np.dtype(kind).itemsize:
            raise ValueError("not a complete token file")
        return np.frombuffer(raw, kind)

    magic, docs, count, segments = (int(x) for x in take(4, "<u8"))
    if magic != MAGIC:
        raise ValueError("not a token file")
    ids, nulls = take(docs, "<i8").tolist(), take(docs, "u1")
    ids = [None if n else d for d, n in zip(ids, nulls.tolist())]
    ends, sizes = take(docs, "<u8").astype(np.int64), take(segments, "<u8").tolist()
    begun: list[np.ndarray] = []
    done = at = 0
    for k, size in enumerate(sizes):
        number = min(SEGMENT, count - k * SEGMENT)
        control = take(-(-number // 4), "u1")
        values = unpack_numbers(control, take(size, "u1"), number)
        upto = int(np.searchsorted(ends, at + number, "right"))
        if upto > done:
            cuts = ends[done:upto] - at
            found = np.split(values, cuts)
            rest = found.pop()
            found[0] = np.concatenate([*begun, found[0]]) if begun else found[0]
            yield ids[done:upto], np.concatenate([[ends[done - 1] if done else 0], ends[done : upto - 1]]), found
            begun, done = ([rest] if len(rest) else []), upto
        else:
            begun.append(values)
        at += number
    if done < docs:  # only documents without ids are left
        yield ids[done:], np.full(docs - done, at, np.int64), [np.empty(0, np.uint32)] * (docs - done)


def _opened(folder: str):
    return pafs.FileSystem.from_uri(folder)


def _parts(df: DataFrame, id_col: str) -> tuple[int, np.ndarray, int]:
    """Number of parts of the id order, its cut points (one fewer, repeated
    where one id fills several parts), and how many parts null ids fill."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    own = F.col(id_col).cast("bigint")
    quantiles = [k / parts for k in range(1, parts)] or [0.5]
    cuts, total, known = df.select(F.percentile_approx(own, quantiles, 10_000), F.count("*"), F.count(own)).first()
    return parts, np.array(cuts or [], np.int64), -(-(total - known) * parts // max(1, total))


def write(df: DataFrame, folder: str, vocabulary: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encode all texts, in order of their ids, into files below ``folder``
    (a URI that all workers reach).

    Null ids come first. A null or empty text is the end id alone; rows that
    share an id follow each other, in the order of their tokens' bytes within a
    part; an id (or null) that fills several parts is dealt out among them by
    a checksum. An empty table leaves two empty tables and no file.

    Texts are encoded once and ids counted on the way; only ids are shuffled,
    once, to the part of the id order they belong to.
    """
    spark = df.sparkSession
    ship(spark)
    parts, bounds, null_parts = _parts(df, id_col)

    def ids_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = library_ids(vocabulary)
        end = np.array([end_id], np.uint32)
        total = np.zeros(0, np.int64)
        for batch in worker_for("library", batches):
            packed, salt = [], np.empty(len(batch), np.int64)
            for i, ids in enumerate(held.texts(batch.column(1))):
                ids = np.concatenate([ids, end])
                some = np.bincount(ids, minlength=len(total))
                if len(some) > len(total):
                    some[: len(total)] += total
                    total = some
                else:
                    total += some
                # the narrower form where all ids of the text fit
                packed.append(b"\2" + ids.astype("<u2").tobytes() if ids.max() < 1 << 16 else b"\4" + ids.tobytes())
                salt[i] = zlib.crc32(packed[-1])
            doc = batch.column(0)
            known = np.asarray(doc.fill_null(0), np.int64)
            low, high = np.searchsorted(bounds, known, "left"), np.searchsorted(bounds, known, "right")
            part = np.where(high - low > 1, low + 1 + salt % np.maximum(high - low, 1), high)
            part = np.where(np.asarray(doc.is_null()), -1 - salt % max(1, null_parts), part)
            yield pa.RecordBatch.from_arrays([doc, pa.array(part, pa.int32()), pa.array(packed, pa.binary()), pa.nulls(len(batch), pa.binary())], ["doc_id", "part", "ids", "counted"])
        if len(total):
            yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int32()), pa.nulls(1, pa.binary()), pa.array([total.tobytes()], pa.binary())], ["doc_id", "part", "ids", "counted"])

    def counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in batch.column(0):
                total = np.frombuffer(raw.as_py(), np.int64)
                seen = np.flatnonzero(total)
                yield pa.RecordBatch.from_arrays([pa.array(seen, pa.int64()), pa.array(total[seen], pa.int64())], ["id", "n"])

    texts = df.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    encoded = Written(texts.mapInArrow(ids_of, "doc_id bigint, part int, ids binary, counted binary"), "token-ids", "zstd")
    per_id = encoded.df.select("counted").where("counted is not null").mapInArrow(counts, "id bigint, n bigint")
    # one row per id of the vocabulary
    ranked = [r["id"] for r in per_id.groupBy("id").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "id").collect()]
    rank_of = np.zeros(max(ranked, default=0) + 1, np.uint32)
    rank_of[ranked] = np.arange(len(ranked), dtype=np.uint32)
    shared = spark.sparkContext.broadcast(rank_of)
    spark.createDataFrame(list(enumerate(ranked)), "rank bigint, id bigint").coalesce(1).write.parquet(f"{folder}/ranks")
    # the workers open the folder by its full address, whatever the default file system is
    home = full_address(spark, folder)

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _opened(home)
        file, part, number = FileWriter(), None, 0

        def close() -> pa.RecordBatch:
            nonlocal file, number
            name = f"{part}-{number}.tokens"
            temporary = f"{root}/.{name}.{uuid.uuid4().hex}"
            with fs.open_output_stream(temporary) as out:
                file.write(out)
            fs.move(temporary, f"{root}/{name}")
            row = [pa.array([v]) for v in (name, part, number, file.ids)]
            file, number = FileWriter(), number + 1
            return pa.RecordBatch.from_arrays(row, ["name", "part", "number", "n_ids"])

        for batch in batches:
            own = batch.column(1).to_pylist()
            for doc, to, raw in zip(batch.column(0).to_pylist(), own, batch.column(2)):
                if to != part or file.ids >= FILE_IDS:
                    if file.docs:
                        yield close()
                    if to != part:
                        part, number = to, 0
                raw = raw.as_buffer()
                file.add(doc, shared.value[np.frombuffer(raw, "<u2" if raw[0] == 2 else "<u4", offset=1)])
        if file.docs:
            yield close()

    whole = encoded.df.where("ids is not null").select("doc_id", "part", "ids").repartition(parts, "part").sortWithinPartitions("part", "doc_id", "ids")
    whole.mapInArrow(put, "name string, part bigint, number bigint, n_ids bigint").write.parquet(f"{folder}/index")
    encoded.drop()


def read(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids (array<int>) of all documents in the files."""
    return _decoded(spark, folder, lambda ids: ids.astype(np.int32), pa.list_(pa.int32()), "ids array<int>", "ids")


def digests(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of all documents in the files."""
    return _decoded(spark, folder, lambda ids: zlib.crc32(ids.astype("<u4")), pa.int64(), "ids_crc32 bigint", "ids_crc32")


def _decoded(spark: SparkSession, folder: str, of, kind: pa.DataType, ddl: str, name: str) -> DataFrame:
    ship(spark)
    index = spark.read.schema("name string, part bigint, number bigint, n_ids bigint").parquet(f"{folder}/index")
    ranks = spark.read.schema("rank bigint, id bigint").parquet(f"{folder}/ranks").orderBy("rank").collect()  # one row per id of the vocabulary
    table = np.array([r["id"] for r in ranks], np.int64)
    shared = spark.sparkContext.broadcast(table)
    home = full_address(spark, folder)
    # a row per part: as many as the writer's shuffle partitions
    bases, at = [], 0
    for row in index.groupBy("part").agg(F.sum("n_ids").alias("n")).orderBy("part").collect():
        bases.append((row["part"], at))
        at += row["n"]
    parts = F.broadcast(spark.createDataFrame(bases, "part bigint, base bigint"))
    earlier = Window.partitionBy("part").orderBy("number").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum("n_ids").over(earlier), F.lit(0))
    files = index.withColumn("before", before).join(parts, "part").select("name", (F.col("base") + F.col("before")).alias("base"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = _opened(home)
        for batch in batches:
            for file, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                with fs.open_input_stream(f"{root}/{file}", buffer_size=1 << 20) as source:
                    for docs, starts, ranked in parse_file(source):
                        column = [of(shared.value[r]) for r in ranked]
                        sizes = np.array([len(r) for r in ranked], np.int64)
                        yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(starts + base, pa.int64()), pa.array(sizes), pa.array(column, kind)], ["doc_id", "start", "n_tokens", name])

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return files.repartition(parts, "name").mapInArrow(run, f"doc_id bigint, start bigint, n_tokens bigint, {ddl}")


def round_trip(df: DataFrame, vocabulary: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write the files to the shared scratch folder and read them back."""
    folder = scratch_path(df.sparkSession, "token-files")
    write(df, folder, vocabulary, end_id, id_col, text_col)
    return digests(df.sparkSession, folder)
