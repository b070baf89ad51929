"""Byte-level BPE by backtracking over longest matches, and table decoding.

The merges of a byte-level BPE vocabulary, applied greedily by rank, give one
sequence of ids for a piece of text. This encoder finds it without applying
merges. An Aho-Corasick automaton over all tokens gives the longest token that
starts at each byte; the encoder takes it, and keeps it if the pair formed with
the token before is one that greedy merging would leave side by side. If not,
it tries the next shorter token that starts there, and if none is left it goes
back one token. A position whose continuation failed is never entered again, so
the work is linear in the text. Whether two tokens are compatible follows from
the merge list alone and is kept in a table.

Decoding lays the bytes of all tokens end to end in one blob with an offset
table and gathers them for a whole batch at once.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from itertools import chain

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, IntegerType, StringType, StructField, StructType

from pagecast.cluster import ship
from pagecast.llm.piecetable import SpacedPieces
from pagecast.llm.words import worker_for

_NEVER = 1 << 40


def _byte_alphabet() -> dict[str, int]:
    """The printable stand-in character of each byte in byte-level vocabularies."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class ByteBpe:
    """A vocabulary file of the tokenizers library (byte-level BPE without
    normalizer, prefix space or unknown token)."""

    #: Fixed: the pattern that splits text ahead of the merges.
    PATTERN = regex.compile(r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+""")

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        byte_of = _byte_alphabet()
        raw = lambda shown: bytes(byte_of[c] for c in shown)
        model = spec["model"]
        self.bytes_of = {i: raw(t) for t, i in model["vocab"].items()}
        id_of = {b: i for i, b in self.bytes_of.items()}
        # halves of each token and the rank at which the two halves merge
        self.halves: dict[int, tuple[int, int]] = {}
        self.merged: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = (raw(x) for x in (pair.split(" ") if isinstance(pair, str) else pair))
            left, right, whole = id_of[a], id_of[b], id_of[a + b]
            self.merged[left, right] = (rank, whole)
            self.halves.setdefault(whole, (left, right))
        self.rank = {whole: self.merged[h][0] for whole, h in self.halves.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.bytes_of |= {i: t.encode() for t, i in self.special.items()}
        self._cut_special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.trie = ahocorasick.Automaton()
        reachable = {i: b for b, i in id_of.items() if i in self.halves or len(b) == 1}
        for i, b in reachable.items():
            self.trie.add_word(b.decode("latin-1"), i)
        self.trie.make_automaton()
        # the next shorter token that is a prefix of a token
        self.shorter: dict[int, int] = {}
        for i, b in reachable.items():
            for n in range(len(b) - 1, 0, -1):
                if (j := id_of.get(b[:n])) is not None and j in reachable:
                    self.shorter[i] = j
                    break
        self.length = {i: len(b) for i, b in self.bytes_of.items()}
        self._compatible: dict[tuple[int, int], bool] = {}
        # greedy merging of a token's own bytes gives the token
        self._whole = {b: [i] for i, b in reachable.items()}

    def compatible(self, left: int, right: int) -> bool:
        """Would greedy merging leave these two tokens as neighbours?

        Undo the merges on both sides of the border from the latest to the
        earliest; at no time may the two tokens at the border have a merge of
        their own that comes before the one just undone.
        """
        key = (left, right)
        known = self._compatible.get(key)
        if known is not None:
            return known
        a, b, undone = left, right, _NEVER
        while True:
            own = self.merged.get((a, b))
            # a merge across the border wins ties only from the left
            if own is not None and own[0] < undone:
                verdict = False
                break
            rank_a, rank_b = self.rank.get(a, -1), self.rank.get(b, -1)
            if rank_a < 0 and rank_b < 0:
                verdict = True
                break
            if rank_a > rank_b:
                undone, a = rank_a, self.halves[a][1]
            else:
                # the same rank on the right side is applied after the border's
                undone, b = rank_b + 1, self.halves[b][0]
        if len(self._compatible) > 500_000:
            self._compatible.clear()
        self._compatible[key] = verdict
        return verdict

    def encode_piece(self, piece: bytes) -> list[int]:
        whole = self._whole.get(piece)
        if whole is not None:
            return whole
        n = len(piece)
        text = piece.decode("latin-1")
        longest = [-1] * n
        length = self.length
        for end, token in self.trie.iter(text):
            start = end - length[token] + 1
            # matches come by growing end, so the last one is the longest
            longest[start] = token
        dead = bytearray(n + 1)
        out: list[int] = []
        at, token = 0, longest[0]
        while at < n:
            while True:
                end = at + length[token]
                if not dead[end] and (not out or self.compatible(out[-1], token)):
                    out.append(token)
                    at = end
                    if at < n:
                        token = longest[at]
                    break
                token = self.shorter.get(token, -1)
                if token < 0:
                    dead[at] = 1
                    token = out.pop()
                    at -= length[token]
                    # the popped token leads to a dead end; the loop rejects it
        return out

    def encode(self, text: str) -> list[int]:
        ids: list[int] = []
        parts = self._cut_special.split(text) if self._cut_special and any(t in text for t in self.special) else [text]
        for part in parts:
            if part in self.special:
                ids.append(self.special[part])
            else:
                for piece in self.PATTERN.findall(part):
                    ids += self.encode_piece(piece.encode("utf-8"))
        return ids

    def offset_table(self) -> tuple[np.ndarray, np.ndarray]:
        """All tokens' bytes end to end, and where each id's bytes begin."""
        top = max(self.bytes_of) + 1
        pieces = [self.bytes_of.get(i, b"") for i in range(top)]
        offsets = np.concatenate([[0], np.cumsum([len(p) for p in pieces])]).astype(np.int64)
        return np.frombuffer(b"".join(pieces), np.uint8), offsets


class BacktrackedPieces(SpacedPieces):
    """Ids of texts whose recurring pieces this encoder has met before."""

    def __init__(self, bpe: ByteBpe):
        super().__init__(list(bpe.special))
        self.bpe = bpe

    def encode_whole(self, raw: bytes) -> np.ndarray:
        return np.array(self.bpe.encode(raw.decode("utf-8")), np.uint32)

    def encode_pieces(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        made = [self.bpe.encode(p.decode("utf-8")) for p in pieces]
        return np.arange(len(pieces)), np.array(list(chain.from_iterable(made)), np.uint32), np.array([len(m) for m in made], np.int64)


def gather(ids: np.ndarray, blob: np.ndarray, offsets: np.ndarray) -> bytes:
    """The bytes of a sequence of ids."""
    sizes = offsets[ids + 1] - offsets[ids]
    ends = np.cumsum(sizes)
    total = int(ends[-1]) if len(ends) else 0
    return blob[np.repeat(offsets[ids] - (ends - sizes), sizes) + np.arange(total)].tobytes()


_LOADED: dict[str, tuple[ByteBpe, BacktrackedPieces, np.ndarray, np.ndarray]] = {}


def loaded(path: str) -> tuple[ByteBpe, BacktrackedPieces, np.ndarray, np.ndarray]:
    if path not in _LOADED:
        bpe = ByteBpe(path)
        _LOADED[path] = (bpe, BacktrackedPieces(bpe), *bpe.offset_table())
    return _LOADED[path]


def encode(df: DataFrame, vocabulary: str, text_col: str = "text", ids_col: str = "ids") -> DataFrame:
    """All columns of ``df`` and the ids of the text (array<int>; empty for a
    null or empty text). ``vocabulary`` is a path that every worker can open."""
    if ids_col in df.columns:
        raise ValueError(f"column {ids_col} exists already")
    ship(df.sparkSession)
    at = df.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = loaded(vocabulary)[1]
        for batch in worker_for("bpe", batches):
            rows = [ids.astype(np.int32) for ids in cache.texts(batch.column(at))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(rows, pa.list_(pa.int32()))], [*batch.schema.names, ids_col])

    return df.mapInArrow(run, StructType([*df.schema, StructField(ids_col, ArrayType(IntegerType()))]))


def decode(df: DataFrame, vocabulary: str, ids_col: str = "ids", text_col: str = "decoded") -> DataFrame:
    """All columns of ``df`` and the text of its ids; null ids give an empty
    text, invalid UTF-8 becomes U+FFFD."""
    if text_col in df.columns:
        raise ValueError(f"column {text_col} exists already")
    ship(df.sparkSession)
    at = df.columns.index(ids_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, _, blob, offsets = loaded(vocabulary)
        for batch in worker_for("bpe", batches):
            texts = [gather(np.array(row or (), np.int64), blob, offsets).decode("utf-8", "replace") for row in batch.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], [*batch.schema.names, text_col])

    return df.mapInArrow(run, StructType([*df.schema, StructField(text_col, StringType())]))


def round_trip_digests(df: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, number of tokens, SHA-256 of the ids (as little-endian
    unsigned 32-bit integers) and of the text decoded from them.

    Null and empty texts have no tokens; texts of any length are encoded whole;
    repeated rows give repeated results.
    """
    ship(df.sparkSession)
    id_type = df.schema[id_col].dataType.simpleString()
    names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, cache, blob, offsets = loaded(vocabulary)
        sha = lambda b: hashlib.sha256(b).hexdigest()
        for batch in worker_for("bpe", batches):
            counts, of_ids, of_text = [], [], []
            for ids in cache.texts(batch.column(1)):
                decoded = gather(ids.astype(np.int64), blob, offsets).decode("utf-8", "replace")
                counts.append(len(ids))
                of_ids.append(sha(ids.astype("<u4").tobytes()))
                of_text.append(sha(decoded.encode("utf-8")))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(of_ids, pa.string()), pa.array(of_text, pa.string())], names)

    return df.select(id_col, text_col).mapInArrow(run, f"{id_col} {id_type}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
