"""Pre-tokens of byte-level tokenizers and ids of distinct pre-tokens.

``split`` finds the matches of the usual byte-level pattern (contractions,
letters, digits, other signs, white space) over a whole chunk at once from
character classes, without a regular expression; tests hold it against
``regex`` on ``public_tokenizers.PATTERN``.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Callable
from functools import cache

import numpy as np

from .textbatch import TextChunk, ranges, same_spans, span_keys

OTHER, LETTER, NUMBER, SPACE = 0, 1, 2, 3
PART = 4096
#: Code points of Unicode's White_Space property.
WHITE_SPACE = (9, 10, 11, 12, 13, 32, 0x85, 0xA0, 0x1680, 0x2000, 0x2001, 0x2002, 0x2003, 0x2004, 0x2005, 0x2006, 0x2007, 0x2008, 0x2009, 0x200A, 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)


@cache
def class_table() -> np.ndarray:
    first = {"L": LETTER, "N": NUMBER}
    t = np.fromiter((first.get(unicodedata.category(chr(c))[0], OTHER) for c in range(0x110000)), np.uint8, 0x110000)
    t[list(WHITE_SPACE)] = SPACE
    return t


def split(chunk: TextChunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, text number) of each pre-token, in characters of the chunk."""
    codes, off = chunk.codes, chunk.char_off
    n = len(codes)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, none
    kind = class_table()[codes]
    first = np.zeros(n + 1, bool)
    first[off] = True  # texts' starts, and the end
    cut = first.copy()
    cut[1:n] |= kind[1:] != kind[:-1]
    # the last white-space character before a non-space starts a pre-token; a blank takes what follows along
    e = np.flatnonzero((kind[1:] != SPACE) & (kind[:-1] == SPACE) & ~first[1:n]) + 1
    cut[e - 1] = True
    cut[e] = codes[e - 1] != 0x20
    # contractions: an apostrophe that starts a pre-token, with s t m d re ve ll after it
    a = np.flatnonzero((codes[:-1] == 0x27) & cut[: n - 1] & ~first[1:n])
    if len(a):
        one = codes[a + 1]
        two_at = np.minimum(a + 2, n - 1)
        two = np.where((a + 2 < n) & ~first[two_at], codes[two_at], 0)
        c = {x: ord(x) for x in "stmdrevl"}
        short = (one == c["s"]) | (one == c["t"]) | (one == c["m"]) | (one == c["d"])
        long = ((one == c["r"]) & (two == c["e"])) | ((one == c["v"]) & (two == c["e"])) | ((one == c["l"]) & (two == c["l"]))
        size = np.where(short, 2, np.where(long, 3, 0))
        a, size = a[size > 0], size[size > 0]
        cut[a + 1] = False
        cut[a + size] = True
    cut[n] = True
    at = np.flatnonzero(cut)
    start, end = at[:-1], at[1:]
    return start, end, np.searchsorted(off, start, side="right") - 1


class Grown:
    """A flat array that grows by doubling."""

    def __init__(self, kind: type) -> None:
        self.room, self.n = np.zeros(1 << 12, kind), 0

    def add(self, more: np.ndarray) -> int:
        """Append; returns where it begins."""
        begin, self.n = self.n, self.n + len(more)
        if self.n > len(self.room):
            room = np.zeros(max(self.n, 2 * len(self.room)), self.room.dtype)
            room[:begin] = self.room[:begin]
            self.room = room
        self.room[begin : self.n] = more
        return begin


class Spans:
    """Distinct character spans by 64-bit hash, each with its characters: a hit is one only if those agree.

    ``settled`` holds many entries by hash, ``recent`` new ones that join them in bulk.
    """

    def __init__(self) -> None:
        none = np.zeros(0, np.uint64), np.zeros((0, 3), np.int32)
        self.settled, self.recent, self.chars = none, none, Grown(np.uint32)

    def __len__(self) -> int:
        return len(self.settled[0]) + len(self.recent[0])

    def find(self, hashes: np.ndarray, codes: np.ndarray, start: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(entry, taken): the entry's number of each span, -1 where it has none; whether another span has its hash."""
        entry, taken = np.full(len(hashes), -1), np.zeros(len(hashes), bool)
        for keys, rows in (self.settled, self.recent):
            if len(keys):
                pos = np.minimum(np.searchsorted(keys, hashes), len(keys) - 1)
                hit = np.flatnonzero(keys[pos] == hashes)
                found = rows[pos[hit]].astype(np.int64)
                same = same_spans(self.chars.room, found[:, 1], found[:, 2], codes, start[hit], size[hit])
                entry[hit[same]], taken[hit[~same]] = found[same, 0], True
        return entry, taken

    def add(self, hashes: np.ndarray, number: np.ndarray, codes: np.ndarray, start: np.ndarray, size: np.ndarray) -> None:
        """Entries for ascending hashes that aren't taken."""
        begin = self.chars.add(codes[ranges(start, size)])
        self.recent = _merged(self.recent, (hashes, np.stack([number, begin + np.cumsum(size) - size, size], axis=1).astype(np.int32)))
        if len(self.recent[0]) > max(1 << 16, len(self.settled[0]) // 4):
            self.settled, self.recent = _merged(self.settled, self.recent), (np.zeros(0, np.uint64), np.zeros((0, 3), np.int32))


def _merged(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    keys = np.concatenate([a[0], b[0]])
    order = np.argsort(keys, kind="stable")
    return keys[order], np.concatenate([a[1], b[1]])[order]


class Memo:
    """What ``make`` found for each distinct span met so far.

    ``make`` gets the codes, starts and sizes of new spans and returns the first
    of their consecutive numbers.  At ``limit`` entries, or characters, the memo starts
    anew, which bounds memory and changes no result; so do spans whose hash another one
    has: they are made each time they come.
    """

    def __init__(self, limit: int = 1_000_000, chars: int = 1 << 23) -> None:
        self.limit, self.most_chars = limit, chars
        self.clear()

    def clear(self) -> None:
        self.spans = Spans()

    def make(self, codes: np.ndarray, start: np.ndarray, size: np.ndarray) -> int:
        raise NotImplementedError

    def numbers(self, codes: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The number of each span, which is the same for equal spans or was made anew."""
        if len(self.spans) > self.limit or self.spans.chars.n > self.most_chars:
            self.clear()
        size = end - start
        keys, exact = span_keys(codes, start, end)
        hashes, at, back = np.unique(keys, return_index=True, return_inverse=True)
        first, length = start[at], size[at]
        entry, taken = self.spans.find(hashes, codes, first, length)
        new = np.flatnonzero(entry < 0)
        if len(new):
            entry[new] = self.make(codes, first[new], length[new]) + np.arange(len(new))
            keep = new[~taken[new]]
            if len(keep):
                self.spans.add(hashes[keep], entry[keep], codes, first[keep], length[keep])
        number = entry[back]
        check = np.flatnonzero(~exact | ~exact[at][back] | (size != length[back]))
        check = check[at[back[check]] != check]
        same = same_spans(codes, start[check], size[check], codes, first[back[check]], length[back[check]])
        odd = check[~same]
        if len(odd):  # equal hashes inside this chunk
            number[odd] = self.make(codes, start[odd], size[odd]) + np.arange(len(odd))
        return number


class IdMemo(Memo):
    """Ids of pre-tokens.  ``encode`` gets new ones as strings."""

    def __init__(self, encode: Callable[[list[str]], list[list[int]]], limit: int = 1_000_000) -> None:
        self.encode = encode
        super().__init__(limit)

    def clear(self) -> None:
        super().clear()
        self.ids, self.begin, self.size = Grown(np.uint32), Grown(np.int64), Grown(np.int32)

    def make(self, codes: np.ndarray, start: np.ndarray, size: np.ndarray) -> int:
        flat = codes[ranges(start, size)].astype("<u4").tobytes().decode("utf-32-le")
        cut = np.concatenate([[0], np.cumsum(size)]).tolist()
        number = self.begin.n
        for k in range(0, len(size), PART):  # the library's results are far larger than ids
            found = self.encode([flat[a:b] for a, b in zip(cut[k : k + PART], cut[k + 1 : k + PART + 1], strict=False)])
            n = np.fromiter(map(len, found), np.int32, len(found))
            begin = self.ids.add(np.fromiter((i for x in found for i in x), np.uint32, int(n.sum())))
            self.begin.add(begin + np.cumsum(n, dtype=np.int64) - n)
            self.size.add(n)
        return number

    def tokens(self, chunk: TextChunk) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another, and each text's offset there."""
        start, end, doc = split(chunk)
        if not len(start):
            return np.zeros(0, np.uint32), np.zeros(chunk.n + 1, np.int64)
        number = self.numbers(chunk.codes, start, end)
        size = self.size.room[number].astype(np.int64)
        ids = self.ids.room[ranges(self.begin.room[number], size)]
        count = np.bincount(doc, weights=size, minlength=chunk.n).astype(np.int64)
        return ids, np.concatenate([[0], np.cumsum(count)])
