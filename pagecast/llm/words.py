"""Words of a text, their 64-bit hashes and the hashes of word windows.

A word is a maximal run of characters other than space and U+0009..U+000D.
``bytes.split()`` cuts at exactly these six bytes, and UTF-8 never uses them
inside a longer character, so all work is done on bytes.
"""

from __future__ import annotations

import ctypes
import gc
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash

_CACHE_LIMIT = 150_000
_STEP = np.uint64(0x9E3779B97F4A7C15)
_MIX_A = np.uint64(0xBF58476D1CE4E5B9)
_MIX_B = np.uint64(0x94D049BB133111EB)


class _HashOfWord(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_LIMIT:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


_HASHES = _HashOfWord()


_LAST = [""]


def worker_for(kind: str, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches of a task, with the worker's memory kept for this kind of
    work only: workers live on from stage to stage, and what they remember of
    another stage's words would add up."""
    if _LAST[0] != kind:
        _LAST[0] = kind
        if kind in ("bpe", "library", "classifier"):
            _HASHES.clear()
        for name, own in (("bpe", "bpe"), ("library_tokens", "library")):
            module = sys.modules.get(f"pagecast.llm.{name}")
            if module is not None and kind != own:
                module._LOADED.clear()
        _give_back()
    yield from batches
    _give_back()


def _give_back() -> None:
    """Freed memory back to the system, as far as the allocators can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def unused(name: str, *frames) -> str:
    """A column name that none of the tables has."""
    taken = {c.lower() for f in frames for c in f.columns}
    while name in taken:
        name += "_"
    return name


def unused_prefix(prefix: str, *frames) -> str:
    """A prefix that no column of the tables begins with."""
    taken = [c.lower() for f in frames for c in f.columns]
    while any(c.startswith(prefix) for c in taken):
        prefix = "_" + prefix
    return prefix


def strings(column: pa.Array) -> Iterator[str | None]:
    """The texts of a column, few at a time as Python strings."""
    for at in range(0, len(column), 256):
        yield from column.slice(at, 256).to_pylist()


def utf8(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))


def mix(values: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every input bit."""
    with np.errstate(over="ignore"):
        values = (values ^ (values >> np.uint64(30))) * _MIX_A
        values = (values ^ (values >> np.uint64(27))) * _MIX_B
        return values ^ (values >> np.uint64(31))


def window_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """One hash for each run of ``width`` neighbours (none if there are fewer)."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    total = hashes[:n].copy()
    with np.errstate(over="ignore"):
        for k in range(1, width):
            total = mix(total) * _STEP + hashes[k : k + n]
    return mix(total)


def shingle_set(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct window hashes of the A-Z lower-cased words; a shorter
    text is one shingle, a text without words has none."""
    words = utf8(text).lower().split()
    if not words:
        return np.empty(0, np.uint64)
    return np.unique(window_hashes(word_hashes(words), min(width, len(words))))
