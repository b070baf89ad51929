"""Ids from the tokenizers library, with the ids of recurring pieces kept."""

from __future__ import annotations

import os

import numpy as np

from pagecast.llm.piecetable import LoweredPieces, PieceIds, SpacedPieces, in_one_call, two_ways

_LOADED: dict[str, PieceIds] = {}


class _Library:
    """The tokenizer and the two ways in which it is called."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # one task, one core
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.names = [self.tokenizer.id_to_token(i) or "" for i in range(self.tokenizer.get_vocab_size(with_added_tokens=True))]

    def one(self, text: str) -> np.ndarray:
        return self.many([text])[0]

    def many(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]


class LibrarySpaced(SpacedPieces):
    """New words go to the library in one text; a word begins where a token
    that holds the space does."""

    def __init__(self, library: _Library):
        super().__init__(library.special)
        self.library = library
        self.starts = np.array([n.startswith("Ġ") for n in library.names])

    def encode_whole(self, raw: bytes) -> np.ndarray:
        return self.library.one(raw.decode("utf-8"))

    def encode_pieces(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        # white space stands only at a piece's front
        words = [i for i, p in enumerate(pieces) if p[:1] == b" " and p[1:2].strip()]
        return two_ways(words, len(pieces), lambda at: in_one_call(self.library.one, b"".join([pieces[i] for i in at]).decode(), self.starts, False, len(at)), lambda at: self.library.many([pieces[i].decode() for i in at]))


class LibraryLowered(LoweredPieces):
    """New words of ASCII letters go to the library in one text; each ends with
    the one token that holds the word end."""

    def __init__(self, library: _Library):
        super().__init__(library.special)
        self.library = library
        self.ends = np.array([n.endswith("</w>") for n in library.names])

    def encode_whole(self, raw: bytes) -> np.ndarray:
        return self.library.one(raw.decode("utf-8"))

    def encode_pieces(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        words = [i for i, p in enumerate(pieces) if p.isalpha()]  # of bytes: ASCII letters only
        return two_ways(words, len(pieces), lambda at: in_one_call(self.library.one, b" ".join([pieces[i] for i in at]).decode(), self.ends, True, len(at)), lambda at: self.library.many([pieces[i].decode() for i in at]))


def library_ids(path: str) -> PieceIds:
    """The library's ids for the vocabulary file at ``path``, without
    truncation, padding or tokens added at the ends.

    Both kinds of vocabulary given cut a text into pieces ahead of the merges,
    so the library encodes each new piece once, many in one call, and recurring
    pieces come from a table. Texts with unusual white space go to it whole.
    """
    if path not in _LOADED:
        library = _Library(path)
        _LOADED[path] = (LibrarySpaced if library.tokenizer.normalizer is None else LibraryLowered)(library)
    return _LOADED[path]
