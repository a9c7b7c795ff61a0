"""Arrow string columns as flat byte blocks, and hashes of the words in them.

A worker never holds more than one Arrow batch plus the temporaries of one block; a block has
about BLOCK_BYTES of text, or one document if that document alone is longer.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1 << 20

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on unsigned 64-bit values, in place where x may be overwritten."""
    x = x ^ (x >> _U(33))
    x *= _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


def seeds(n: int, stream: int = 0) -> np.ndarray:
    """n fixed pseudo-random unsigned 64-bit values; another stream gives others."""
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * _BASE + _U(stream * 0x632BE59BD9B4E019 % (1 << 64)))


_BYTE_CODE = seeds(256, 1)


@lru_cache(maxsize=4)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n of the odd base modulo 2^64, and of its inverse."""
    inverse = pow(int(_BASE), -1, 1 << 64)
    up, down = np.full(n + 1, _BASE, np.uint64), np.full(n + 1, _U(inverse), np.uint64)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The tables are built for the next power of two, so that few are built."""
    return _powers(max(BLOCK_BYTES * 2, 1 << int(n).bit_length()))


@dataclass
class Block:
    """Documents first..first+n-1 of a batch: their bytes back to back and n+1 offsets."""

    first: int
    data: np.ndarray
    offsets: np.ndarray

    @property
    def n(self) -> int:
        return len(self.offsets) - 1

    @property
    def lengths(self) -> np.ndarray:
        return np.diff(self.offsets)


def blocks(column: pa.Array | pa.ChunkedArray, block_bytes: int = BLOCK_BYTES) -> Iterator[Block]:
    """Nulls count as empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if len(column) == 0:
        return
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, places, values = column.buffers()
    at = np.frombuffer(places, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(values, np.uint8) if values is not None else np.zeros(0, np.uint8)
    i, n = 0, len(column)
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + block_bytes, side="right")) - 1)
        j = min(j, n)
        yield Block(i, data[at[i] : at[j]], at[i : j + 1] - at[i])
        i = j


#: Space, tab, line feed, vertical tab, form feed, carriage return.
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


@dataclass
class Words:
    """Runs of kept bytes inside documents: byte ranges, and per document the range of its words."""

    start: np.ndarray
    end: np.ndarray
    first: np.ndarray  # n + 1 offsets into start

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))


def runs(block: Block, keep: np.ndarray) -> Words:
    """keep: for each byte of the block, whether it belongs to a word. Words don't cross documents."""
    n = len(keep)
    if n == 0:
        none = np.zeros(0, np.int64)
        return Words(none, none, np.zeros(block.n + 1, np.int64))
    edge = np.zeros(n + 1, bool)
    edge[block.offsets] = True
    opens = keep.copy()
    opens[1:] &= ~keep[:-1] | edge[1:n]
    shuts = keep.copy()
    shuts[:-1] &= ~keep[1:] | edge[1:n]
    start = np.flatnonzero(opens)
    return Words(start, np.flatnonzero(shuts) + 1, np.searchsorted(start, block.offsets))


def spaced_words(block: Block) -> Words:
    """Words are runs of bytes other than space and 0x09 to 0x0D."""
    return runs(block, ~_SPACE[block.data])


def prefix_code(data: np.ndarray) -> np.ndarray:
    """Prefix sums from which the code of any byte range follows (range_code)."""
    up, _ = powers(len(data))
    out = np.empty(len(data) + 1, np.uint64)
    out[0] = 0
    np.cumsum(_BYTE_CODE[data] * up[: len(data)], out=out[1:])
    return out


def range_code(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte range; equal bytes give equal hashes in every block."""
    _, down = powers(len(prefix) - 1)
    return mix64((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64))


def word_codes(block: Block, words: Words, lower: bool = True) -> np.ndarray:
    data = LOWER[block.data] if lower else block.data
    return range_code(prefix_code(data), words.start, words.end)


def shingles(codes: np.ndarray, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of width consecutive words, and offsets by document.

    A document with fewer words, but at least one, has one shingle: the whole sequence.
    """
    count = np.diff(first)
    n_out = np.where(count >= width, count - width + 1, np.minimum(count, 1))
    out_first = np.concatenate(([0], np.cumsum(n_out)))
    doc = np.repeat(np.arange(len(count)), n_out)
    at = first[:-1][doc] + np.arange(len(doc)) - out_first[:-1][doc]
    left = np.minimum(width, first[1:][doc] - at)
    weights = seeds(width + 1, 7)
    total = left.astype(np.uint64) * weights[width]
    for k in range(width):
        use = left > k
        if use.all():
            total += codes[at + k] * weights[k]
        else:
            total[use] += codes[at[use] + k] * weights[k]
    return mix64(total), out_first


def sorted_sets(values: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each document's distinct values, ascending, back to back, and their offsets."""
    if not len(values):
        return values, np.zeros(len(first), np.int64)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    order = np.argsort(values, kind="stable")
    order = order[np.argsort(doc[order], kind="stable")]
    values, doc = values[order], doc[order]
    new = np.ones(len(values), bool)
    new[1:] = (values[1:] != values[:-1]) | (doc[1:] != doc[:-1])
    values, doc = values[new], doc[new]
    return values, np.searchsorted(doc, np.arange(len(first)))


def sums(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of each document's values; 0 where it has none."""
    out = np.zeros(len(first) - 1, np.float64)
    some = np.flatnonzero(np.diff(first))
    if len(some):
        out[some] = np.add.reduceat(values, first[:-1][some], dtype=np.float64)
    return out
