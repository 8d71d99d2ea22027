"""Hashed character n-grams of whole texts, over Arrow chunks."""

from __future__ import annotations

from functools import cache

import numpy as np

from .pretokens import LETTER, SPACE, class_table
from .textbatch import TextChunk


@cache
def lower_table() -> np.ndarray:
    """Each code point's lower-case form where that's one character, else itself."""
    t = np.arange(0x110000, dtype=np.uint32)
    for c in range(0x110000):
        if not 0xD800 <= c < 0xE000 and len(low := chr(c).lower()) == 1:
            t[c] = ord(low)
    return t


def folded(chunk: TextChunk, letters_only: bool = False) -> np.ndarray:
    """Lower-case characters; white space, or all that aren't letters, as a blank."""
    codes = chunk.codes
    kind = class_table()[codes]
    return np.where(kind != LETTER if letters_only else kind == SPACE, np.uint32(0x20), lower_table()[codes])


def ngram_hashes(codes: np.ndarray, off: np.ndarray, n: int, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash below 2^bits, text number) of each run of n characters within a text."""
    m = len(codes) - n + 1
    if m <= 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    x = codes * np.uint32(0x9E3779B1)
    x ^= x >> np.uint32(15)
    h = np.full(m, n * 0x1000193 & 0xFFFFFFFF, np.uint32)
    for k in range(n):
        h = h * np.uint32(0x01000193 | 1) + x[k : m + k]
    h ^= h >> np.uint32(16)
    h *= np.uint32(0x85EBCA6B)
    h ^= h >> np.uint32(13)
    size = np.diff(off)
    doc = np.repeat(np.arange(len(size)), size)
    inside = np.ones(m, bool)
    for k in range(1, n):  # the last n - 1 characters of a text start none, nor do those that would reach past it
        at = off[1:] - k
        at = at[(at >= 0) & (at < m)]
        inside[at] = False
    return (h >> np.uint32(32 - bits))[inside], doc[:m][inside]


#: A feature stands for an n-gram that a text has at least so many times.
LEVELS = (1, 2, 4, 8)


def level_features(chunk: TextChunk, orders: tuple[int, ...], bits: int, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct (text, feature) pairs; a feature is level << bits | hash.  ``keep`` marks the hashes wanted."""
    codes, off = folded(chunk, letters_only=True), chunk.char_off
    found = []
    for n in orders:
        h, doc = ngram_hashes(codes, off, n, bits)
        if keep is not None:
            at = np.flatnonzero(keep[h])
            h, doc = h[at], doc[at]
        found.append(doc.astype(np.int64) << bits | h)
    key, count = np.unique(np.concatenate(found), return_counts=True)
    docs, features = [], []
    for level, least in enumerate(LEVELS):
        key, count = key[count >= least], count[count >= least]
        docs.append(key >> bits)
        features.append(level << bits | key & ((1 << bits) - 1))
    doc = np.concatenate(docs)
    order = np.argsort(doc, kind="stable")
    return doc[order], np.concatenate(features)[order]
