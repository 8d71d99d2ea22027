"""Runs of characters of many texts at once, as arrays: code points, words that order as text does, counts, MD5.

A run of k characters is k code points in words of 64 bits: 8 bits each where all
are below 256, else 21 bits.  Either way words compare as the texts do.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

CHUNK = 1 << 22
NARROW, WIDE = 8, 21

Words = list[np.ndarray]


def points(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all texts, one after another, and each text's length; null ones are empty."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    if not len(texts):
        return np.empty(0, np.uint32), np.empty(0, np.int64)
    ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = texts.buffers()[2]
    return decoded(memoryview(data)[ends[0] : ends[-1]] if data else b""), pc.utf8_length(texts).to_numpy(zero_copy_only=False)


def decoded(data) -> np.ndarray:
    return np.frombuffer(str(data, "utf-8").encode("utf-32-le"), np.uint32)


def encoded(codes: np.ndarray) -> bytes:
    return codes.astype(np.uint8).tobytes() if not len(codes) or codes.max() < 128 else codes.astype("<u4").tobytes().decode("utf-32-le").encode()


def widths(codes: np.ndarray) -> np.ndarray:
    """Bytes of each code point in UTF-8."""
    size = 1 + (codes >= 0x80).astype(np.int64)
    return size if codes.dtype == np.uint8 else size + (codes >= 0x800) + (codes >= 0x10000)


def chunks(texts: Iterable[pa.Array], overlap: int, size: int = CHUNK) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(code points, lengths, own): pieces of texts, ``size`` characters together; each has ``own`` characters and what follows them, up to ``overlap``."""
    parts, lengths, own, room = [], [], [], 0
    for array in texts:
        codes, sizes = points(array)
        at = 0
        for n in sizes.tolist():
            s = 0
            while s < n:
                take = min(size - room, n - s)
                parts.append(codes[at + s : min(at + n, at + s + take + overlap)])
                lengths.append(len(parts[-1]))
                own.append(take)
                s, room = s + take, room + take
                if room >= size:
                    yield np.concatenate(parts), np.array(lengths), np.array(own)
                    parts, lengths, own, room = [], [], [], 0
            at += n
    if parts:
        yield np.concatenate(parts), np.array(lengths), np.array(own)


def within(lengths: np.ndarray, counted: np.ndarray) -> np.ndarray:
    """Marks the first ``counted`` places of each piece."""
    ends = np.cumsum(lengths)
    n, first = int(ends[-1]) + 1 if len(ends) else 1, ends - lengths
    marks = np.bincount(first, minlength=n) - np.bincount(first + counted, minlength=n)
    return np.cumsum(marks[:-1], dtype=np.int8).astype(bool)


def span(codes: np.ndarray, n: int, bits: int) -> np.ndarray:
    """``n`` characters from each place on in one word."""
    if n == 1:
        return codes
    h = n // 2
    a = span(codes, n - h, bits)
    b = a if h == n - h else span(codes, h, bits)
    out = max(0, len(codes) - n + 1)
    return a[:out] << np.uint64(bits * h) | b[n - h : n - h + out]


def words(codes: np.ndarray, k: int, bits: int) -> Words:
    """The run of k characters from each place on, where there are k."""
    codes, per, out = codes.astype(np.uint64), 64 // bits, max(0, len(codes) - k + 1)
    return [span(codes, min(per, k - j), bits)[j : j + out] for j in range(0, k, per)]


def letters(key: Words, k: int, bits: int) -> np.ndarray:
    """Code points of runs, a row each."""
    if bits == 8 and k % 8 == 0:
        return np.stack(key, axis=1).byteswap().view(np.uint8)
    per, out = 64 // bits, np.empty((len(key[0]), k), np.uint8 if bits <= 8 else np.uint32)
    for i in range(k):
        n = min(per, k - i // per * per)
        out[:, i] = key[i // per] >> np.uint64(bits * (n - 1 - i % per)) & np.uint64((1 << bits) - 1)
    return out


def mixed(key: Words) -> np.ndarray:
    h = np.zeros(len(key[0]), np.uint64)
    for w in key:
        h = (h ^ w) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(32)
    return h * np.uint64(0xD6E8FEB86659FD93)


def changes(key: Words) -> np.ndarray:
    """Marks the rows that differ from the one before."""
    return np.concatenate([[True], np.logical_or.reduce([w[1:] != w[:-1] for w in key])])


def by_head(head: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in order of the leading bits that leave room for a place, and these bits: one sort of plain numbers."""
    room = np.uint64(max(1, (len(head) - 1).bit_length()))
    head = head >> room << room | np.arange(len(head), dtype=np.uint64)
    head.sort()
    return (head & ((np.uint64(1) << room) - np.uint64(1))).astype(np.int64), head >> room


def ordered(key: Words, head: np.ndarray) -> np.ndarray:
    """Places in order of ``head``'s leading bits, then of the words; equal words must have equal heads."""
    order, bits = by_head(head)
    same = bits[1:] == bits[:-1]
    tied = np.flatnonzero(same)
    differ = np.logical_or.reduce([w[order[tied + 1]] != w[order[tied]] for w in key])
    if differ.any():
        group = np.concatenate([[0], np.cumsum(~same)])
        mixed_up = np.zeros(group[-1] + 1, bool)
        mixed_up[group[tied[differ]]] = True
        at = np.flatnonzero(mixed_up[group])
        inner = order[at]
        order[at] = inner[np.lexsort([w[inner] for w in reversed(key)] + [group[at]])]
    return order


def added(key: Words, n: np.ndarray, head: np.ndarray | None = None) -> tuple[Words, np.ndarray]:
    """Different runs and the sums of their n."""
    if not len(n):
        return key, n
    order = ordered(key, mixed(key) if head is None else head)
    key = [w.take(order) for w in key]
    first = np.flatnonzero(changes(key))
    return [w[first] for w in key], np.add.reduceat(n.take(order), first)


class Counts:
    """Adds runs up within bounded memory: beyond ``most`` different ones they go to local files by hash, which are added up one by one."""

    FILES = 16

    def __init__(self, most: int = 3 * CHUNK) -> None:
        self.most, self.held, self.new, self.added, self.files, self.width = most, None, [], 0, [], 0

    def add(self, key: Words, n: np.ndarray) -> None:
        self.new.append((key, n))
        self.width = len(key) + 1
        self.added += len(n)
        if self.added >= max(CHUNK, len(self.held[1]) if self.held else 0):
            self._merge()
            if len(self.held[1]) > self.most:
                self._spill()

    def _merge(self) -> None:
        all_ = ([self.held] if self.held else []) + self.new
        self.new, self.added, self.held = [], 0, None
        if all_:
            self.held = added([np.concatenate(w) for w in zip(*(k for k, _ in all_))], np.concatenate([n for _, n in all_]))

    def _spill(self) -> None:
        self.files = self.files or [tempfile.TemporaryFile() for _ in range(self.FILES)]
        if self.held:
            key, n = self.held
            at = (mixed(key) >> np.uint64(7)).astype(np.int64) % self.FILES
            for f, file in enumerate(self.files):
                chosen = at == f
                for x in (*(w[chosen] for w in key), n[chosen]):
                    np.save(file, x)
        self.held = None

    def result(self) -> Iterator[tuple[Words, np.ndarray]]:
        self._merge()
        if not self.files:
            if self.held:
                yield self.held
            return
        self._spill()
        for file in self.files:
            end, got = file.tell(), []
            file.seek(0)
            while file.tell() < end:
                got.append(np.load(file))
            width = self.width
            rows = [got[i : i + width] for i in range(0, len(got), width)]
            yield added([np.concatenate([r[j] for r in rows]) for j in range(width - 1)], np.concatenate([r[-1] for r in rows]))
            file.close()


_S = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_K = [int(abs(np.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64)]
_START = [0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476]


def _md5_first(blocks: np.ndarray) -> np.ndarray:
    """First word of the MD5 of padded messages of one block each: 16 words a row."""
    m = [np.ascontiguousarray(blocks[:, i]) for i in range(16)]
    live = [w.any() for w in m]
    a, b, c, d = (np.full(len(blocks), x, np.uint32) for x in _START)
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f += a
        f += np.uint32(_K[i])
        if live[g]:
            f += m[g]
        turned = f << np.uint32(_S[i])
        f >>= np.uint32(32 - _S[i])
        turned |= f
        turned += b
        a, d, c, b = d, c, b, turned
    return a + np.uint32(_START[0])


def md5_head(rows: np.ndarray, lanes: int = 1 << 15) -> np.ndarray:
    """The first two bytes, as a number, of the MD5 of each row of code points in UTF-8."""
    out, high = np.empty(len(rows), np.int64), np.zeros(len(rows), rows.dtype)
    for i in range(rows.shape[1]):
        high |= rows[:, i]
    if rows.shape[1] <= 55 and 0 < (other := high >= 128).sum() < len(rows):  # one byte a character, or not
        for chosen in (other, ~other):
            out[chosen] = md5_head(rows[chosen], lanes)
        return out
    for s in range(0, len(rows), lanes):
        part = rows[s : s + lanes]
        n, k = part.shape
        text = np.zeros((n, 64), np.uint8)
        long = np.empty(0, np.int64)
        size = np.full(n, k)
        if part.max(initial=0) < 128 and k <= 55:
            text[:, :k] = part
        else:
            size = sum((widths(part[:, i]) for i in range(k)), np.zeros(n, np.int64))
            data = np.frombuffer(encoded(part.ravel()), np.uint8)
            long = np.flatnonzero(size > 55)
            if len(long):
                data = data[np.repeat(size <= 55, size)]
            kept = np.where(size <= 55, size, 0)
            text.ravel()[np.repeat(np.arange(n) * 64 - (np.cumsum(kept) - kept), kept) + np.arange(len(data))] = data
        text[np.arange(n), np.minimum(size, 55)] = 128
        blocks = text.view("<u4")
        blocks[:, 14] = size * 8
        head = _md5_first(blocks)
        out[s : s + n] = (head & 255).astype(np.int64) << 8 | (head >> 8 & 255)
        for i in long:
            out[s + i] = int.from_bytes(hashlib.md5(encoded(part[i])).digest()[:2], "big")
    return out
