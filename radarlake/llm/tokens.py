"""Token ids of whole texts by the `tokenizers` library, chunk by chunk.

Byte-pair merges never cross a pre-token, so the ids of a text are those of its
pre-tokens after each other. Texts within Latin-1 are cut into pre-tokens here, by
numpy, under the rule that the tokenizer file states, and the library's model is asked
once for each distinct pre-token. Any other text (other signs, contractions, what may
be a special token, rare control signs) goes to the library whole. Both ways give the
library's ids.
"""

from __future__ import annotations

import os
import unicodedata
from functools import lru_cache

import numpy as np

from radarlake.llm.common import HashIndex, prefix_hashes, same_bytes, span_hashes

#: Distinct pre-tokens that a worker keeps before it starts anew.
CACHE_SIZE = 1 << 19
_LETTER, _NUMBER, _SPACE, _OTHER = range(4)
#: Signs of Latin-1 whose class the libraries may see in different ways, and the sign that opens special tokens.
_ODD = [*range(0x1C, 0x20), 0x85]


def _kind(c: int) -> int:
    if c in (0x20, 0xA0, 0x85, *range(0x09, 0x0E)):
        return _SPACE
    return {"L": _LETTER, "N": _NUMBER}.get(unicodedata.category(chr(c))[0], _OTHER)


_KIND = np.array([_kind(c) for c in range(256)], np.uint8)
_LOWER = np.array([ord(chr(c).lower()) for c in range(256)], np.uint8)


class Encoder:
    """`path` names a tokenizer file: byte-level pairs with leading spaces, or lower-cased words without white space."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, pre_tokenizers

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.lower = "Lowercase" in str(self.library.normalizer)
        level = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.signs = {c: level.pre_tokenize_str(chr(c))[0][0] for c in range(256)}
        self._clear()

    def _clear(self) -> None:
        self.index = HashIndex(CACHE_SIZE)
        self.first = np.zeros(CACHE_SIZE + 1, np.int64)
        self.pool = np.zeros(1 << 16, np.uint32)
        #: The bytes of the known pre-tokens, and where each begins.
        self.raw, self.raw_first = np.zeros(1 << 16, np.uint8), np.zeros(CACHE_SIZE + 1, np.int64)

    def whole(self, text: str) -> np.ndarray:
        """The library's ids of one text."""
        return np.array(self.library.encode(text, add_special_tokens=False).ids, np.uint32)

    def _add(self, hashed: np.ndarray, tokens: list[bytes]) -> None:
        signs, tokenize, size = self.signs, self.model.tokenize, self.index.size
        ids = [[x.id for x in tokenize(token.decode("latin-1").translate(signs))] for token in tokens]
        first = self.first[size] + np.cumsum([len(x) for x in ids])
        while first[-1] > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.first[size] : first[-1]] = [i for x in ids for i in x]
        self.first[size + 1 : size + 1 + len(ids)] = first
        raw = np.frombuffer(b"".join(tokens), np.uint8)
        end = int(self.raw_first[size]) + len(raw)
        while end > len(self.raw):
            self.raw = np.concatenate([self.raw, np.zeros_like(self.raw)])
        self.raw[end - len(raw) : end] = raw
        self.raw_first[size + 1 : size + 1 + len(ids)] = self.raw_first[size] + np.cumsum([len(t) for t in tokens])
        self.index.add(hashed)

    def _cut(self, code: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and ends of the pre-tokens of Latin-1 texts."""
        kind = _KIND[code]
        start = np.ones(len(code) + 1, bool)
        start[1:-1] = kind[1:] != kind[:-1]
        edge = np.zeros(len(code) + 1, bool)
        edge[offsets] = True
        start |= edge
        if self.lower:
            start[:-1] |= kind == _NUMBER
        else:
            after = np.flatnonzero(start[1:-1] & ~edge[1:-1] & (kind[1:] != _SPACE) & (kind[:-1] == _SPACE)) + 1
            start[after - 1] = True
            start[after[code[after - 1] == 0x20]] = False
        at = np.flatnonzero(start)
        a, b = at[:-1], at[1:]
        if self.lower:
            keep = kind[a] != _SPACE
            a, b = a[keep], b[keep]
        return a, b

    def _rows_for_library(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        odd = (data >= 0xC4) | ((data >= 0x1C) & (data < 0x20))
        odd[1:] |= (data[1:] == 0x85) & (data[:-1] == 0xC2)
        odd[:-1] |= (data[:-1] == 0x3C) & (data[1:] == 0x7C)
        mark = np.flatnonzero(data[:-1] == 0x27)
        odd[mark[np.isin(_LOWER[data[mark + 1]], np.frombuffer(b"strvmld", np.uint8))]] = True
        return np.unique(np.searchsorted(offsets, np.flatnonzero(odd), "right") - 1)

    def chunk(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows after each other (unsigned, 32 bits) and the offsets of the rows."""
        slow = self._rows_for_library(data, offsets) if len(data) else np.zeros(0, np.int64)
        keep = (data & 0xC0) != 0x80
        if len(slow):
            for r in slow:
                keep[offsets[r] : offsets[r + 1]] = False
        code = data.copy()
        lead = np.flatnonzero(keep & (data >= 0xC2))
        code[lead] = ((data[lead] & 3) << 6) | (data[lead + 1] & 0x3F)
        code = code[keep]
        at = np.concatenate([[0], np.cumsum(keep)])[offsets]
        if self.lower:
            code = _LOWER[code]
        a, b = self._cut(code, at)
        hashed = span_hashes(prefix_hashes(code), a, b)
        found = self.index.find(hashed)
        if (found < 0).any():
            new, where = np.unique(hashed[found < 0], return_index=True)
            if self.index.size + len(new) > CACHE_SIZE:
                self._clear()
                new, where = np.unique(hashed, return_index=True)
                lost = np.arange(len(hashed))
            else:
                lost = np.flatnonzero(found < 0)
            if len(new) > CACHE_SIZE:
                return self._pieces([self.whole(bytes(data[x:y]).decode()) for x, y in zip(offsets[:-1], offsets[1:], strict=True)])
            raw = code.tobytes()
            self._add(new, [raw[a[i] : b[i]] for i in lost[where].tolist()])
            found = self.index.find(hashed)
        size = b - a
        known = self.raw_first[found + 1] - self.raw_first[found] == size
        known[known] = same_bytes(code, a[known], self.raw, self.raw_first[found[known]], size[known])
        if not known.all():
            slow = np.union1d(slow, np.searchsorted(at, a[~known], "right") - 1)
        length = self.first[found + 1] - self.first[found]
        total = np.concatenate([[0], np.cumsum(length)])
        ids = self.pool[np.arange(total[-1]) + np.repeat(self.first[found] - total[:-1], length)]
        rows = total[np.searchsorted(a, at, "left")]
        if not len(slow):
            return ids, rows
        pieces = [ids[x:y] for x, y in zip(rows[:-1], rows[1:], strict=True)]
        for r in slow:
            pieces[r] = self.whole(bytes(data[offsets[r] : offsets[r + 1]]).decode())
        return self._pieces(pieces)

    @staticmethod
    def _pieces(pieces: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return np.concatenate([np.zeros(0, np.uint32), *pieces]), np.concatenate([[0], np.cumsum([len(x) for x in pieces])]).astype(np.int64)


@lru_cache(maxsize=4)
def encoder(path: str) -> Encoder:
    """The worker's encoder for a file; it stays while the worker process lives."""
    return Encoder(path)


def with_end(ids: np.ndarray, rows: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """The same with one more id after each row."""
    out = np.full(len(ids) + len(rows) - 1, end, np.uint32)
    keep = np.ones(len(out), bool)
    after = rows + np.arange(len(rows))
    keep[after[1:] - 1] = False
    out[keep] = ids
    return out, after
