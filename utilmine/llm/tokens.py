"""Words and their hashes for blocks of texts, as numpy arrays over the bytes of an Arrow column.

A block is a run of whole texts of about half a megabyte (or one longer text), so that memory stays bounded by the longest text. Word
hashes are 64-bit polynomial hashes over random byte codes, and runs of words hash the same way over word hashes, so
any span of a block hashes in constant time from prefix sums.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1 << 19
BASE, SEQUENCE_BASE = 0x9E3779B97F4A7C15 | 1, 0xD6E8FEB86659FD93 | 1

#: Byte tables: True where a byte belongs to a word.
ANY_WORD = np.ones(256, bool)
ANY_WORD[[0x20, *range(0x09, 0x0E)]] = False
ALNUM_WORD = np.zeros(256, bool)
ALNUM_WORD[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (the finalizer of splitmix64)."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


@lru_cache(maxsize=2)
def codes(fold: bool) -> np.ndarray:
    """Random odd codes of the 256 bytes; with fold, A to Z have those of a to z."""
    out = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x632BE59BD9B4E019)) | np.uint64(1)
    if fold:
        out[65:91] = out[97:123]
    return out


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown when asked for more."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << max(16, (n - 1).bit_length())
            for name, base in (("up", self.base), ("down", self.inverse)):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps, dtype=np.uint64))
        return self.up, self.down


BYTE_POWERS, WORD_POWERS = Powers(BASE), Powers(SEQUENCE_BASE)


def prefix(values: np.ndarray, powers: Powers) -> np.ndarray:
    up, _ = powers.to(len(values) + 1)
    out = np.empty(len(values) + 1, np.uint64)
    out[0] = 0
    np.cumsum(values * up[: len(values)], out=out[1:])
    return out


def span_hashes(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray, powers: Powers) -> np.ndarray:
    _, down = powers.to(len(sums))
    return mix((sums[ends] - sums[starts]) * down[starts])


class Block:
    """Texts first to last (exclusive) of an Arrow column; words: starts and ends in data; at: for each text the first of its words, and one more."""

    def __init__(self, first: int, last: int, data: np.ndarray, bounds: np.ndarray):
        self.first, self.last, self.data, self.bounds = first, last, data, bounds

    def __len__(self) -> int:
        return self.last - self.first

    def text(self, i: int) -> bytes:
        return self.data[self.bounds[i] : self.bounds[i + 1]].tobytes()

    def words(self, table: np.ndarray = ANY_WORD) -> None:
        inside = table[self.data]
        before, after = np.zeros(len(inside), bool), np.zeros(len(inside), bool)
        before[1:], after[:-1] = inside[:-1], inside[1:]
        cut = self.bounds[:-1][self.bounds[:-1] < len(inside)]
        before[cut] = False
        after[self.bounds[1:][self.bounds[1:] > 0] - 1] = False
        self.starts, self.ends = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
        self.at = np.searchsorted(self.starts, self.bounds)
        self.counts = np.diff(self.at)

    def hashes(self, fold: bool = False) -> np.ndarray:
        """A hash for each word."""
        return span_hashes(prefix(codes(fold)[self.data], BYTE_POWERS), self.starts, self.ends, BYTE_POWERS)

    def shingles(self, hashes: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all runs of width words inside a text, and the text of each, in order."""
        n = np.maximum(self.counts - width + 1, 0)
        owner = np.repeat(np.arange(len(self)), n)
        starts = np.arange(len(owner)) + np.repeat(self.at[:-1] - (np.cumsum(n) - n), n)
        return span_hashes(prefix(hashes, WORD_POWERS), starts, starts + width, WORD_POWERS), owner


def blocks(column: pa.Array, most: int = BLOCK_BYTES, most_texts: int | None = None) -> Iterator[Block]:
    """Consecutive blocks of a string column, of up to `most` bytes (or one text) and most_texts texts; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    if not n:
        return
    offsets = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    first = 0
    while first < n:
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + most, "right")) - 1)
        last = min(last, first + (most_texts or n))
        yield Block(first, last, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first])
        first = last
