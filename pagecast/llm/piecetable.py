"""Ids of recurring pieces of text, held in arrays and found for many at once.

A share of the texts is cut into pieces by comparing neighbouring bytes. A piece
of at most sixteen bytes is its own key: two 64-bit words, zero behind its end
(texts with NUL are not cut), so equal keys are equal pieces and no hash has to
be trusted. Keys lie in an open-addressing table whose slots say where in a pool
the piece's ids are; all pieces of a share are probed together and their ids are
gathered from the pool in one step. Only pieces that the table does not hold
reach the encoder, each once. Longer pieces are encoded once a share.

The table's size is fixed. When it is full, the pieces asked for since the last
time stay; if those are more than half, all go.
"""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_SPACE, _LETTER, _MARK = 1, 2, 3
_SHIFT = (np.arange(9, dtype=np.uint64) * np.uint64(8)) % np.uint64(64)
#: Bits of the first n bytes of a little-endian word.
_FIRST = np.concatenate([(np.uint64(1) << _SHIFT[:8]) - np.uint64(1), [np.uint64(0xFFFFFFFFFFFFFFFF)]])
_ODD_A, _ODD_B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def _classes() -> np.ndarray:
    table = np.zeros(256, np.uint8)
    table[[9, 10, 13, 32]] = _SPACE
    for c in range(33, 127):
        if chr(c).isalpha():
            table[c] = _LETTER
        elif not chr(c).isdigit() and c != 95:
            table[c] = _MARK
    return table


_CLASS = _classes()


class PieceTable:
    """Pieces of one to sixteen bytes -> ids, for a worker's lifetime."""

    def __init__(self, bits: int = 20):
        self.bits, self.slots = bits, 1 << bits
        self.most = self.slots * 6 // 10
        self._empty()

    def _empty(self) -> None:
        self.low = np.zeros(self.slots, np.uint64)
        self.high = np.zeros(self.slots, np.uint64)
        self.begin = np.zeros(self.slots, np.int32)
        self.count = np.zeros(self.slots, np.uint16)
        self.asked = np.zeros(self.slots, bool)
        self.pool = np.zeros(1 << 16, np.uint32)
        self.used = self.held = 0

    def _home(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            mixed = (low ^ (high * _ODD_B)) * _ODD_A
            mixed = (mixed ^ (mixed >> np.uint64(32))) * _ODD_B
        return (mixed >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """The slot of each key, -1 where it is not held."""
        slot = self._home(low, high)
        held = self.low[slot]
        same = (held == low) & (self.high[slot] == high)
        out = np.where(same, slot, -1)
        open_ = np.flatnonzero(~same & (held != 0))
        at = slot[open_]
        while len(open_):
            at = (at + 1) & (self.slots - 1)
            held = self.low[at]
            same = (held == low[open_]) & (self.high[at] == high[open_])
            out[open_[same]] = at[same]
            go = ~same & (held != 0)
            open_, at = open_[go], at[go]
        self.asked[out[out >= 0]] = True
        return out

    def _place(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Slots for distinct keys that are not held."""
        at = self._home(low, high)
        out = np.empty(len(low), np.int64)
        left = np.arange(len(low))
        while len(left):
            free = self.low[at] == 0
            # of several keys that want one slot the first wins
            _, first = np.unique(at, return_index=True)
            won = np.zeros(len(left), bool)
            won[first] = True
            won &= free
            self.low[at[won]], self.high[at[won]] = low[left[won]], high[left[won]]
            out[left[won]] = at[won]
            left, at = left[~won], (at[~won] + 1) & (self.slots - 1)
        return out

    def make_room(self, number: int) -> None:
        """Called before keys are looked up whose slots are used later."""
        if self.held + number <= self.most:
            return
        keep = np.flatnonzero(self.asked & (self.low != 0))
        old = (self.low[keep], self.high[keep], self.begin[keep].astype(np.int64), self.count[keep], self.pool)
        self._empty()
        if len(keep) + number <= self.most // 2:
            low, high, begin, count, pool = old
            ids, _ = gathered(pool, begin, count.astype(np.int64))
            self.add(low, high, ids, count)

    def add(self, low: np.ndarray, high: np.ndarray, ids: np.ndarray, count: np.ndarray) -> None:
        """Distinct new keys with their ids one after the other."""
        slot = self._place(low, high)
        if self.used + len(ids) > len(self.pool):
            grown = np.zeros(max(2 * len(self.pool), self.used + len(ids)), np.uint32)
            grown[: self.used] = self.pool[: self.used]
            self.pool = grown
        self.pool[self.used : self.used + len(ids)] = ids
        self.begin[slot] = self.used + np.cumsum(count, dtype=np.int64) - count
        self.count[slot] = count
        self.asked[slot] = True
        self.used += len(ids)
        self.held += len(low)


def gathered(pool: np.ndarray, begin: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Runs of the pool one after the other, and their ends."""
    ends = np.cumsum(count)
    total = int(ends[-1]) if len(ends) else 0
    return pool[np.repeat(begin - (ends - count), count) + np.arange(total)], ends


class PieceIds:
    """Ids of whole texts from the ids of their pieces."""

    #: Bytes of text handled together.
    SHARE = 1_000_000

    def __init__(self, special: list[str], bits: int = 20):
        self.table = PieceTable(bits)
        self.special = [s.encode() for s in special]

    # what a vocabulary's kind decides
    def prepared(self, raw: bytes) -> bytes | None:
        """The bytes to cut into pieces; None if the text is encoded whole."""
        raise NotImplementedError

    def spans(self, kind: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Begin and length of all pieces of texts that begin at ``starts``."""
        raise NotImplementedError

    def encode_pieces(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Encodes distinct pieces in an order of its own: that order (indices),
        all ids one after the other, and the number of ids of each."""
        raise NotImplementedError

    def encode_whole(self, raw: bytes) -> np.ndarray:
        raise NotImplementedError

    def has_special(self, raw: bytes) -> bool:
        return any(s in raw for s in self.special)

    def texts(self, column: pa.Array) -> Iterator[np.ndarray]:
        """Ids (uint32) of each text of a string column; null is empty."""
        column = column.cast(pa.binary()) if not pa.types.is_binary(column.type) else column
        sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
        ends, at = np.cumsum(sizes), 0
        while at < len(column):
            # at least one text, else as many as fill a share
            end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + self.SHARE, "right")))
            yield from self.share(column.slice(at, end - at).to_pylist())
            at = end

    def share(self, texts: list[bytes | None]) -> Iterator[np.ndarray]:
        ready = [self.prepared(t) if t else b"" for t in texts]
        joined = b"".join([r or b"" for r in ready])
        size = np.array([len(r or b"") for r in ready], np.int64)
        first = np.cumsum(size) - size
        data = np.frombuffer(joined + bytes(16), np.uint8)
        begin, length = self.spans(_CLASS[data[: len(joined)]], first[size > 0]) if joined else (np.empty(0, np.int64),) * 2
        ids, ends = self._of_spans(joined, data, begin, length)
        upto = np.concatenate([[0], ends])[np.searchsorted(begin, first + size, "left")]
        last = 0
        for raw, one, end in zip(texts, ready, upto.tolist()):
            yield self.encode_whole(raw) if one is None else ids[last:end]
            last = end

    def _of_spans(self, joined: bytes, data: np.ndarray, begin: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        # every byte offset as the begin of an 8-byte word
        words = np.lib.stride_tricks.as_strided(data.view(np.uint64) if len(data) % 8 == 0 else data[: len(data) // 8 * 8].view(np.uint64), (len(data) - 7,), (1,))
        short = length <= 16
        b, n = (begin, length) if short.all() else (begin[short], length[short])
        low = words[b] & _FIRST[np.minimum(n, 8)]
        high = words[b + 8] & _FIRST[np.clip(n - 8, 0, 8)] if len(b) else low
        table = self.table
        table.make_room(len(b))
        slot = table.find(low, high)
        new = np.flatnonzero(slot < 0)
        if len(new):
            order = new[np.lexsort((high[new], low[new]))]
            a, z = low[order], high[order]
            keep = order[np.concatenate([[True], (a[1:] != a[:-1]) | (z[1:] != z[:-1])])]
            at, ids, count = self.encode_pieces([joined[s : s + k] for s, k in zip(b[keep].tolist(), n[keep].tolist())])
            table.add(low[keep[at]], high[keep[at]], ids, count)
            slot[new] = table.find(low[new], high[new])
        if len(b) == len(begin):
            return gathered(table.pool, table.begin[slot].astype(np.int64), table.count[slot].astype(np.int64))
        # longer pieces: once a share, laid over the gap left for them
        far = np.flatnonzero(~short)
        texts = [joined[s : s + k] for s, k in zip(begin[far].tolist(), length[far].tolist())]
        distinct = list(dict.fromkeys(texts))
        at, ids, number = self.encode_pieces(distinct)
        made = dict(zip((distinct[i] for i in at.tolist()), np.split(ids, np.cumsum(number)[:-1])))
        own = [made[t] for t in texts]
        where, count = np.zeros(len(begin), np.int64), np.empty(len(begin), np.int64)
        where[short], count[short] = table.begin[slot], table.count[slot]
        count[far] = [len(o) for o in own]
        base = len(table.pool)
        where[far] = base + np.cumsum(count[far]) - count[far]
        ends = np.cumsum(count)
        index = np.repeat(where - (ends - count), count) + np.arange(int(ends[-1]))
        far_id = index >= base
        ids = table.pool[np.where(far_id, 0, index)]
        ids[far_id] = np.concatenate(own)
        return ids, ends


#: White space beyond space, tab, newline and return, and NUL: such texts are encoded whole.
_RARE = [chr(c) for c in (0, 0x0B, 0x0C, 0x1C, 0x1D, 0x1E, 0x1F, 0x85, 0xA0, 0x1680, 0x180E, *range(0x2000, 0x200C), 0x2028, 0x2029, 0x202F, 0x205F, 0x2060, 0x3000, 0xFEFF)]
_RARE_BYTES = re.compile(b"[" + re.escape("".join(_RARE[:7]).encode()) + b"]")


def rare_space(text: str) -> bool:
    # single-character searches scan many bytes at a time, a character class one by one
    return any(map(text.__contains__, _RARE))


def _rare_ascii(raw: bytes) -> bool:
    return any(c in raw for c in (b"\0", b"\x0b", b"\x0c", b"\x1c", b"\x1d", b"\x1e", b"\x1f"))


class SpacedPieces(PieceIds):
    """Vocabularies that set the space before a word into its token.

    No token spans the border between a visible character and the white space
    after it, nor that between an ASCII letter and an ASCII mark after it, as
    both are borders of the pieces that come ahead of the merges. White space
    belongs to the word behind it. A text that holds a special token's string,
    or unusual white space, is encoded whole.
    """

    def prepared(self, raw: bytes) -> bytes | None:
        if self.has_special(raw) or (_rare_ascii(raw) if raw.isascii() else rare_space(raw.decode("utf-8", "surrogatepass"))):
            return None
        return raw

    def spans(self, kind: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        space = kind == _SPACE
        border = np.empty(len(kind), bool)
        border[1:] = (space[1:] & ~space[:-1]) | ((kind[1:] == _MARK) & (kind[:-1] == _LETTER))
        border[starts] = True
        begin = np.flatnonzero(border)
        return begin, np.diff(begin, append=len(kind))


class LoweredPieces(PieceIds):
    """Vocabularies that lower-case, drop white space and mark word ends: the
    words themselves, cut where an ASCII mark follows an ASCII letter.

    Texts that are not in NFC, hold the capital sigma (the only letter lowered
    by its place), a special token's string or unusual white space are encoded
    whole.
    """

    def prepared(self, raw: bytes) -> bytes | None:
        if raw.isascii():
            return None if _rare_ascii(raw) or self.has_special(raw.lower()) else raw.lower()
        text = raw.decode("utf-8", "surrogatepass")
        if rare_space(text) or "Σ" in text or not unicodedata.is_normalized("NFC", text):
            return None
        lowered = text.lower().encode("utf-8", "surrogatepass")
        return None if self.has_special(lowered) else lowered

    def spans(self, kind: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        space = kind == _SPACE
        border = np.empty(len(kind), bool)
        border[1:] = (space[1:] != space[:-1]) | ((kind[1:] == _MARK) & (kind[:-1] == _LETTER))
        border[starts] = True
        begin = np.flatnonzero(border)
        length = np.diff(begin, append=len(kind))
        word = ~space[begin]
        return begin[word], length[word]


def in_one_call(encode: Callable[[str], np.ndarray], text: str, edge: np.ndarray, ends: bool, number: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids of many words written one after the other, and how many each has.

    ``edge`` tells of each id whether it begins (or ends) a word.
    """
    ids = encode(text)
    marks = np.flatnonzero(edge[ids])
    if len(marks) != number:
        raise ValueError("the words' pieces are not what was assumed")
    return ids, np.diff(marks, prepend=-1) if ends else np.diff(marks, append=len(ids))


def two_ways(words: list[int], number: int, together, alone) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Encode some pieces in one call and the others one by one."""
    plain = np.zeros(number, bool)
    plain[words] = True
    other = np.flatnonzero(~plain)
    ids, count = together(words) if words else (np.empty(0, np.uint32), np.empty(0, np.int64))
    more = alone(other.tolist())
    order = np.concatenate([np.array(words, np.int64), other])
    return order, np.concatenate([ids, *more]), np.concatenate([count, [len(m) for m in more]]).astype(np.int64)
