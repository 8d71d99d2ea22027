"""Arrow text columns as flat numpy arrays, in bounded chunks.

A chunk holds whole texts only: at most ``max_rows`` of them, added until about
``max_bytes`` of UTF-8 are reached; a longer single text makes a chunk of its own.  Nulls
read as empty texts; invalid UTF-8 is replaced by U+FFFD.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK_BYTES = 1 << 20
CHUNK_ROWS = 1024


class TextChunk:
    """Texts ``start .. start + n`` of a batch, concatenated."""

    def __init__(self, raw: bytes, byte_off: np.ndarray) -> None:
        self.raw, self.byte_off, self.n = raw, byte_off, len(byte_off) - 1
        try:
            self.text = raw.decode("utf-8")
        except UnicodeDecodeError:
            parts = [raw[a:b].decode("utf-8", "replace").encode() for a, b in zip(byte_off[:-1], byte_off[1:], strict=True)]
            self.raw = b"".join(parts)
            self.byte_off = np.concatenate([[0], np.cumsum([len(p) for p in parts], dtype=np.int64)])
            self.text = self.raw.decode("utf-8")

    @cached_property
    def codes(self) -> np.ndarray:
        return np.frombuffer(self.text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)

    @cached_property
    def char_off(self) -> np.ndarray:
        """Start of each text in ``codes``, and their number."""
        if len(self.text) == len(self.raw):
            return self.byte_off
        b = np.frombuffer(self.raw, dtype=np.uint8)
        count = np.concatenate([[0], np.cumsum((b & 0xC0) != 0x80, dtype=np.int64)])
        return count[self.byte_off]


def text_chunks(column: pa.Array, max_bytes: int = CHUNK_BYTES, max_rows: int = CHUNK_ROWS) -> Iterator[tuple[int, TextChunk]]:
    """(first row, chunk) over one Arrow text column."""
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if not len(column):
        return
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    view = memoryview(data) if data is not None else memoryview(b"")
    row, n = 0, len(column)
    while row < n:
        end = int(np.searchsorted(off, off[row] + max_bytes, side="right")) - 1
        end = min(n, max(end, row + 1), row + max_rows)
        yield row, TextChunk(bytes(view[off[row] : off[end]]), off[row : end + 1] - off[row])
        row = end


def binary_array(flat: bytes, off: np.ndarray) -> pa.Array:
    """A binary column from concatenated bytes and their offsets."""
    if off[-1] < 2**31:
        return pa.BinaryArray.from_buffers(pa.binary(), len(off) - 1, [None, pa.py_buffer(off.astype(np.int32).tobytes()), pa.py_buffer(flat)])
    return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(off) - 1, [None, pa.py_buffer(off.astype(np.int64).tobytes()), pa.py_buffer(flat)]).cast(pa.binary())


def binary_flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a binary column; nulls read as empty."""
    column = pc.fill_null(column.cast(pa.large_binary()), b"")
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    flat = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return flat[off[0] : off[-1]], off - off[0]


def ranges(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """All indices start[i] .. start[i] + length[i], one range after another."""
    end = np.cumsum(length)
    total = int(end[-1]) if len(end) else 0
    return np.repeat(start - (end - length), length) + np.arange(total)


_GOLDEN = np.uint64(0x9E3779B97F4A7C15)
_MASKS = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_keys(values: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, exact) of values[start:end], the same wherever the span stands; spans come in order and don't overlap.

    Up to eight values below 256 are packed: among such spans of one length the
    hash is exact.  Of other spans each value is scrambled with its place in the
    span before it is added, so that no arrangement of a few letters cancels out,
    as it does in a polynomial.
    """
    size = end - start
    if not len(size):
        return np.zeros(0, np.uint64), np.zeros(0, bool)
    exact = size <= 8
    if values.max(initial=0) > 255:
        wide = np.concatenate([[0], np.cumsum(values > 255)])
        exact &= wide[end] == wide[start]
    low = np.zeros(len(values) + 8, np.uint8)
    low[: len(values)] = values.astype(np.uint8)
    eight = np.ndarray(len(values) + 1, "<u8", low.tobytes(), strides=(1,))  # the eight values from each place on
    sums = eight[start] & _MASKS[np.minimum(size, 8)]
    rest = np.flatnonzero(~exact)
    if len(rest):
        n = size[rest]
        upto = np.cumsum(n)
        place = np.arange(int(upto[-1])) - np.repeat(upto - n, n)
        x = mix64(values[place + np.repeat(start[rest], n)].astype(np.uint64) + (place.astype(np.uint64) + np.uint64(1)) * _GOLDEN)
        running = np.concatenate([np.zeros(1, np.uint64), np.cumsum(x)])
        sums[rest] = running[upto] - running[upto - n]
    return mix64(sums + size.astype(np.uint64) * _GOLDEN), exact


def span_hashes(values: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return span_keys(values, start, end)[0]


def same_spans(a: np.ndarray, a_start: np.ndarray, a_size: np.ndarray, b: np.ndarray, b_start: np.ndarray, b_size: np.ndarray) -> np.ndarray:
    """Which spans a[a_start : a_start + a_size] equal those of b, value by value."""
    same = a_size == b_size
    size = np.where(same, a_size, 0)
    differ = a[ranges(a_start, size)] != b[ranges(b_start, size)]
    if differ.any():
        same[np.repeat(np.arange(len(size)), size)[differ]] = False
    return same
