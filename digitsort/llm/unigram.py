"""Token counts of a unigram tokenizer by dynamic programming over a trie.

A text's pre-tokens are its words, each behind one U+2581.  The distinct ones
that a chunk brings are inserted in a trie, level by level; the best score of
each shared prefix is computed once, for all nodes of a level together, from
the scores of its shorter prefixes and the vocabulary piece that ends there.
Terminal nodes give a pre-token's score and its number of tokens, which a memo
keeps.  A character that no piece covers counts as its UTF-8 bytes.

Scores are log probabilities.  A piece file that holds merge ranks instead
gets those of Zipf's law over ranks (``zipf_scores``).

Defined results: null, empty and white-space texts have no pre-tokens, no
tokens and score 0.  Equal scores: the path whose last piece is longest.
Rows repeat if the input's do; other columns of the input are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..session import ship_package
from .pretokens import SPACE, Grown, Memo, class_table
from .textbatch import TextChunk, mix64, ranges, text_chunks

MARK = "▁"


def zipf_scores(pieces: list[str]) -> dict[str, float]:
    """Log probabilities that fall off with the rank in the list."""
    total = math.log(sum(1 / (k + 1) for k in range(len(pieces))))
    return {p: -math.log(k + 1) - total for k, p in enumerate(pieces)}


@lru_cache(maxsize=2)
def vocabulary(path: str) -> tuple[dict[str, float], float]:
    """Scores of ordinary pieces and the score of one fallback byte."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    # user-defined pieces (runs of marks) stand outside of the ranks
    plain = [i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i) or not sp.id_to_piece(i).strip(MARK) and len(sp.id_to_piece(i)) > 1)]
    scores = zipf_scores([sp.id_to_piece(i) for i in plain])
    return scores, min(scores.values()) - 10.0


class PieceTrie:
    """Pieces read from their last character: (state, character) leads to a state, which may have a piece's score.

    Steps are looked up by that pair itself, in open slots of 2^bits, so none is
    mistaken for another.  State 0 is the root; 0 also says that no step leads on.
    """

    def __init__(self, scores: dict[str, float]) -> None:
        self.longest = max(map(len, scores), default=1)
        step: dict[int, int] = {}
        ends = [-np.inf]
        for piece, score in scores.items():
            state = 0
            for c in reversed(piece):
                key = state << 21 | ord(c)
                if key not in step:
                    step[key] = len(ends)
                    ends.append(-np.inf)
                state = step[key]
            ends[state] = score
        self.score = np.array(ends)
        bits = max(4, (4 * len(step)).bit_length())
        self.shift = np.uint64(64 - bits)
        key, to = np.fromiter(step, np.int64, len(step)), np.fromiter(step.values(), np.int64, len(step))
        slot = self._slot(key)
        order = np.argsort(slot, kind="stable")
        first = order[np.concatenate([[True], slot[order][1:] != slot[order][:-1]])] if len(order) else order
        self.slot_key, self.slot_to = np.full(1 << bits, -1), np.zeros(1 << bits, np.int64)
        self.slot_key[slot[first]], self.slot_to[slot[first]] = key[first], to[first]
        spare = np.ones(len(key), bool)
        spare[first] = False
        by = np.argsort(key[spare])
        self.spare_key, self.spare_to = key[spare][by], to[spare][by]

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return (mix64(key.astype(np.uint64) + np.uint64(1)) >> self.shift).astype(np.int64)

    def step(self, state: np.ndarray, letter: np.ndarray) -> np.ndarray:
        """The next states, 0 where there's none."""
        key = state << 21 | letter
        slot = self._slot(key)
        held = self.slot_key[slot]
        out = np.where(held == key, self.slot_to[slot], 0)
        rest = np.flatnonzero((held != key) & (held >= 0))
        if len(rest) and len(self.spare_key):
            at = np.minimum(np.searchsorted(self.spare_key, key[rest]), len(self.spare_key) - 1)
            out[rest] = np.where(self.spare_key[at] == key[rest], self.spare_to[at], 0)
        return out


@lru_cache(maxsize=2)
def piece_trie(path: str) -> tuple[PieceTrie, float]:
    scores, byte = vocabulary(path)
    return PieceTrie(scores), byte


def trie_counts(codes: np.ndarray, start: np.ndarray, size: np.ndarray, pieces: PieceTrie, byte: float) -> tuple[np.ndarray, np.ndarray, int]:
    """(tokens, score) of each distinct pre-token codes[start : start + size], and the trie's number of nodes.

    A node is its parent's number and its letter.  Levels hold only nodes of
    pre-tokens that go on.  ``window`` keeps, for the last levels, each node's best
    score and tokens; ``letters`` and ``parents`` what led there.
    """
    n = len(start)
    count, score = np.zeros(n, np.int64), np.zeros(n)
    word = np.flatnonzero(size > 0)
    node = np.zeros(len(word), np.int64)  # of each going word, at the level before
    window: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(1), np.zeros(1, np.int64))]
    letters: list[np.ndarray] = []
    parents: list[np.ndarray] = []
    nodes, depth = 0, 0
    while len(word):
        uniq, back = np.unique(node << 21 | codes[start[word] + depth].astype(np.int64), return_inverse=True)
        nodes += len(uniq)
        parents.append(uniq >> 21)
        letters.append(uniq & ((1 << 21) - 1))
        depth += 1
        best, tokens = np.full(len(uniq), -np.inf), np.zeros(len(uniq), np.int64)
        # candidates: pieces of 1, 2, ... characters that end here, longest last; nodes that no longer piece can reach drop out
        at = up = np.arange(len(uniq))
        state = np.zeros(len(uniq), np.int64)
        for length in range(1, min(depth, pieces.longest) + 1):
            c = letters[-length][up]
            state = pieces.step(state, c)
            up = parents[-length][up]
            value = pieces.score[state]
            before, used = window[-length]
            step = 1
            if length == 1:
                width = np.where(c < 0x80, 1, np.where(c < 0x800, 2, np.where(c < 0x10000, 3, 4)))
                missing = np.isneginf(value) | (state == 0)
                value, step = np.where(missing, width * byte, value), np.where(missing, width, 1)
            value = value + before[up]
            better = (value >= best[at]) & ((state > 0) | (length == 1))
            best[at[better]] = value[better]
            tokens[at[better]] = (used[up] + step)[better]
            on = state > 0
            at, up, state = at[on], up[on], state[on]
            if not len(at):
                break
        window.append((best, tokens))
        if len(window) > pieces.longest:
            window.pop(0)
        if len(letters) >= pieces.longest:
            letters.pop(0)
            parents.pop(0)
        ended = size[word] == depth
        count[word[ended]], score[word[ended]] = tokens[back[ended]], best[back[ended]]
        word, node = word[~ended], back[~ended]
    return count, score, nodes


def words(chunk: TextChunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, text number) of each run of characters that aren't white space."""
    codes, off = chunk.codes, chunk.char_off
    n = len(codes)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, none
    solid = class_table()[codes] != SPACE
    first = np.zeros(n + 1, bool)
    first[off] = True
    begins = solid.copy()
    begins[1:] &= ~solid[:-1] | first[1:n]
    ends = np.zeros(n + 1, bool)
    ends[1:n] = solid[:-1] & (~solid[1:] | first[1:n])
    ends[n] = solid[-1]
    start = np.flatnonzero(begins)
    return start, np.flatnonzero(ends), np.searchsorted(off, start, side="right") - 1


class CountMemo(Memo):
    """Tokens and scores of pre-tokens."""

    def __init__(self, path: str, limit: int = 1_000_000) -> None:
        self.pieces, self.byte = piece_trie(path)
        super().__init__(limit)

    def clear(self) -> None:
        super().clear()
        self.count, self.score = Grown(np.int32), Grown(np.float64)

    def make(self, codes: np.ndarray, start: np.ndarray, size: np.ndarray) -> int:
        room = np.full(int((size + 1).sum()), ord(MARK), np.uint32)  # each behind its mark
        begin = np.cumsum(size + 1) - size - 1
        room[ranges(begin + 1, size)] = codes[ranges(start, size)]
        count, score, _ = trie_counts(room, begin, size + 1, self.pieces, self.byte)
        self.score.add(score)
        return self.count.add(count)

    def totals(self, chunk: TextChunk) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Each text's pre-tokens, tokens and score."""
        start, end, doc = words(chunk)
        if not len(start):
            return np.zeros(chunk.n, np.int64), np.zeros(chunk.n, np.int64), np.zeros(chunk.n)
        number = self.numbers(chunk.codes, start, end)
        count, score = self.count.room[number], self.score.room[number]
        return np.bincount(doc, minlength=chunk.n), np.bincount(doc, count, chunk.n).astype(np.int64), np.bincount(doc, score, chunk.n)


@lru_cache(maxsize=2)
def memo(path: str) -> CountMemo:
    return CountMemo(path)


def count_tokens(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_pretokens, n_tokens, log_prob) of every text."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, chunk in text_chunks(batch.column(1)):
                found = memo(path).totals(chunk)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, chunk.n), *map(pa.array, found)], [id_col, "n_pretokens", "n_tokens", "log_prob"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_pretokens long, n_tokens long, log_prob double")
