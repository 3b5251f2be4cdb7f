"""Vectorised tokenising over Arrow string columns.

Texts are read as the UTF-8 bytes that Arrow already holds.  A word is a maximal run of bytes that a
256-entry table accepts and never crosses a document.  All work is NumPy over chunks of bounded
size, so a worker's memory does not depend on the number or length of documents (one document is
the smallest chunk).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 2 << 20
_MULT = 0x9E3779B97F4A7C15 | 1


def fold_table() -> np.ndarray:
    """Maps A-Z to a-z and every other byte to itself."""
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


def alnum_table() -> np.ndarray:
    """Words of 0-9, a-z (after folding) and all bytes of non-ASCII characters."""
    table = np.zeros(256, dtype=bool)
    table[48:58] = table[97:123] = table[128:] = True
    return table


def blank_table() -> np.ndarray:
    """Words of everything but the space and the controls 9 to 13."""
    table = np.ones(256, dtype=bool)
    table[[32, 9, 10, 11, 12, 13]] = False
    return table


FOLD, ALNUM, NONBLANK = fold_table(), alnum_table(), blank_table()


@dataclass
class Chunk:
    """Some consecutive documents: bytes ``buf``, document borders ``cuts`` (n+1), first row ``row``."""

    row: int
    buf: np.ndarray
    cuts: np.ndarray

    @property
    def n(self) -> int:
        return len(self.cuts) - 1

    def words(self, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends (bytes) of all words, and the first word of each document (n+1)."""
        buf, cuts = self.buf, self.cuts
        if not len(buf):
            return np.empty(0, np.int64), np.empty(0, np.int64), np.zeros(self.n + 1, np.int64)
        inside = table[buf]
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        last = inside.copy()
        last[:-1] &= ~inside[1:]
        begin, end = cuts[:-1], cuts[1:]
        full = end > begin
        first[begin[full]] = inside[begin[full]]
        last[end[full] - 1] = inside[end[full] - 1]
        starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
        return starts, ends, np.searchsorted(starts, cuts)


def chunks(texts: pa.Array, limit: int = CHUNK_BYTES) -> Iterator[Chunk]:
    """Cut an Arrow string array into chunks of at most ``limit`` bytes, or one longer document."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_binary()) if not pa.types.is_large_binary(texts.type) else texts
    if texts.null_count:
        texts = texts.fill_null(b"")
    _, off, data = texts.buffers()
    cuts = np.frombuffer(off, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    row = 0
    while row < len(texts):
        last = int(np.searchsorted(cuts, cuts[row] + limit, side="right")) - 1
        last = min(max(last, row + 1), len(texts))
        yield Chunk(row, data[cuts[row] : cuts[last]], cuts[row : last + 1] - cuts[row])
        row = last


class _Powers:
    """Growing table of powers of the odd multiplier and of its inverse, modulo 2**64."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def of(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, CHUNK_BYTES + 1)
            inverse = pow(_MULT, -1, 1 << 64)
            with np.errstate(over="ignore"):
                self.up, self.down = (np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(size - 1, m, np.uint64)])) for m in (_MULT, inverse))
        return self.up[:n], self.down[:n]


_POWERS = _Powers()


def mixed(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit values (a public finaliser: xor-shift and multiply, twice)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
        x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash for each word: a polynomial of its bytes, independent of where it stands."""
    if not len(starts):
        return np.empty(0, np.uint64)
    up, down = _POWERS.of(len(buf) + 1)
    with np.errstate(over="ignore"):
        total = np.empty(len(buf) + 1, np.uint64)
        total[0] = 0
        np.cumsum((buf.astype(np.uint64) + np.uint64(1)) * up[: len(buf)], out=total[1:])
        h = (total[ends] - total[starts]) * down[starts]
        return mixed(h + (ends - starts).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))


def gram_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n words that start at each position; the last n-1 positions are left out."""
    out = h[: max(0, len(h) - n + 1)].copy()
    with np.errstate(over="ignore"):
        for k in range(1, n):
            out = mixed(out * np.uint64(0x9E3779B97F4A7C15) + h[k : k + len(out)])
    return out
