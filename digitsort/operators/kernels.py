"""Local sorting kernels on keys held in numpy arrays or lists.

Each finisher sorts a list of (key, place) pairs in place and returns how many
comparisons and moves it made; splits return a stable order by one digit.
"""

from __future__ import annotations

import numpy as np

Pairs = list[tuple[int, int]]


def insertion(a: Pairs, low: int = 0, high: int | None = None, gap: int = 1) -> tuple[int, int]:
    """Insertion along every ``gap``-th place of a[low:high]."""
    high = len(a) if high is None else high
    compared = moved = 0
    for i in range(low + gap, high):
        x, j = a[i], i
        while j - gap >= low:
            compared += 1
            if a[j - gap] <= x:
                break
            a[j] = a[j - gap]
            moved += 1
            j -= gap
        a[j] = x
    return compared, moved


def shell(a: Pairs, gaps: tuple[int, ...] = (8, 1)) -> tuple[int, int]:
    """Insertion with falling gaps."""
    parts = [insertion(a, gap=g) for g in gaps]
    return sum(c for c, _ in parts), sum(m for _, m in parts)


def _sift(a: Pairs, low: int, root: int, n: int) -> tuple[int, int]:
    compared = moved = 0
    x = a[low + root]
    while (child := 2 * root + 1) < n:
        if child + 1 < n:
            compared += 1
            child += a[low + child] < a[low + child + 1]
        compared += 1
        if a[low + child] <= x:
            break
        a[low + root] = a[low + child]
        moved += 1
        root = child
    a[low + root] = x
    return compared, moved


def heap(a: Pairs, low: int = 0, high: int | None = None) -> tuple[int, int]:
    n = (len(a) if high is None else high) - low
    parts = [_sift(a, low, root, n) for root in range(n // 2 - 1, -1, -1)]
    for end in range(n - 1, 0, -1):
        a[low], a[low + end] = a[low + end], a[low]
        parts.append(_sift(a, low, 0, end))
    return sum(c for c, _ in parts), sum(m for _, m in parts) + max(0, n - 1)


def introspective(a: Pairs, small: int = 16) -> tuple[int, int]:
    """Quicksort with the median of three; heapsort below 2 log2 n levels; insertion for short parts."""
    todo, compared, moved = [(0, len(a), 2 * max(1, len(a)).bit_length())], 0, 0
    while todo:
        low, high, depth = todo.pop()
        while high - low > small:
            if not depth:
                c, m = heap(a, low, high)
                compared, moved, low = compared + c, moved + m, high
                break
            depth -= 1
            pivot = sorted((a[low], a[(low + high) // 2], a[high - 1]))[1]
            compared += 3
            i, j = low, high - 1
            while i <= j:
                while a[i] < pivot:
                    i += 1
                    compared += 1
                while pivot < a[j]:
                    j -= 1
                    compared += 1
                compared += 2
                if i <= j:
                    a[i], a[j] = a[j], a[i]
                    moved += 1
                    i, j = i + 1, j - 1
            todo.append((i, high, depth))
            high = j + 1
        if high > low:
            c, m = insertion(a, low, high)
            compared, moved = compared + c, moved + m
    return compared, moved


FINISHERS = {"insertion": insertion, "shell": shell, "introspective": introspective}


def digits(keys: np.ndarray, position: int) -> np.ndarray:
    return ((keys.view(np.uint64) ^ np.uint64(1 << 63)) >> np.uint64(8 * position)).astype(np.int64) & 255


def split_plain(keys: np.ndarray, position: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, offsets of the 256 bins): counting, then placing, without buffers.

    The stable order by an eight-bit digit is numpy's own counting sort.
    """
    d = digits(keys, position).astype(np.uint8)
    base = np.concatenate([[0], np.cumsum(np.bincount(d, minlength=256))])
    return np.argsort(d, kind="stable"), base


def split_staged(keys: np.ndarray, position: int, staging: int = 256, record: int = 16, piece: int = 1 << 14) -> tuple[np.ndarray, np.ndarray, int]:
    """The same through per-digit buffers: (order, offsets, flushes).

    Rows come in pieces; each digit's rows collect in its buffer of ``staging``
    bytes, and every full one goes out as a block; at the end the rest does.
    """
    d = digits(keys, position)
    count = np.bincount(d, minlength=256)
    base = np.concatenate([[0], np.cumsum(count)])
    slots = max(1, staging // record)
    order = np.empty(len(keys), np.int64)
    at, held, flushes = base[:-1].copy(), [np.zeros(0, np.int64)] * 256, 0
    for k in range(0, len(keys), piece):
        local = np.argsort(d[k : k + piece].astype(np.uint8), kind="stable")
        cut = np.concatenate([[0], np.cumsum(np.bincount(d[k : k + piece], minlength=256))])
        for v in np.flatnonzero(np.diff(cut)).tolist():
            rows = np.concatenate([held[v], local[cut[v] : cut[v + 1]] + k])
            full = len(rows) // slots * slots
            order[at[v] : at[v] + full] = rows[:full]
            at[v] += full
            flushes += full // slots
            held[v] = rows[full:]
    for v, rows in enumerate(held):
        if len(rows):
            order[at[v] : at[v] + len(rows)] = rows
            flushes += 1
    return order, base, flushes


def light_pass(keys: np.ndarray, position: int, total: int, rules, cache_bytes: int = 256 << 10, record: int = 16, key_bytes: int = 8) -> tuple[np.ndarray, dict[str, int]]:
    """Sorted order of a bin's keys by one worker, and counts of what it did.

    Bins wait in a queue, largest first; those under ``total`` / queue_div go on at
    once instead, without passing through it.
    """
    import heapq

    from ..plans.bins import pick_split, pick_tiny

    order = np.arange(len(keys))
    tally = {"plain": 0, "staged": 0, "insertion": 0, "shell": 0, "introspective": 0, "queued": 0, "recursed": 0, "compared": 0, "moved": 0}
    queue = [(-len(keys), 0, len(keys), position)]
    while queue:
        _, *first = heapq.heappop(queue)
        mine = [tuple(first)]
        while mine:
            low, high, p = mine.pop()
            part = order[low:high]
            kind = pick_split((high - low) * record, cache_bytes)
            tally[kind] += 1
            new, base = split_plain(keys[part], p) if kind == "plain" else split_staged(keys[part], p)[:2]
            order[low:high] = part[new]
            if p == 0:
                continue
            for v in np.flatnonzero(np.diff(base)).tolist():
                a, b = low + int(base[v]), low + int(base[v + 1])
                n = b - a
                strong = rules.narrow is not None and high - low > rules.narrow * n
                if rules.tiny and (n <= rules.small if strong else n < rules.tiny):
                    name = pick_tiny(n, key_bytes, rules)
                    rows = list(zip(keys[order[a:b]].tolist(), order[a:b].tolist(), strict=True))
                    c, m = FINISHERS[name](rows)
                    order[a:b] = [r[1] for r in rows]
                    tally[name] += 1
                    tally["compared"] += c
                    tally["moved"] += m
                elif n * rules.queue_div < total:
                    tally["recursed"] += 1
                    mine.append((a, b, p - 1))
                else:
                    tally["queued"] += 1
                    heapq.heappush(queue, (-n, a, b, p - 1))
    return order, tally


def in_place_radix(keys: list[int], rows: list, position: int = 7, small: int = 32) -> None:
    """Sorts both lists in place by cycles of swaps: besides them only 256 counters a level."""
    bias = 1 << 63
    todo = [(0, len(keys), position)]
    while todo:
        low, high, p = todo.pop()
        if high - low <= small:
            part = sorted(zip(keys[low:high], range(low, high), strict=True))
            moved = [rows[j] for _, j in part]
            keys[low:high], rows[low:high] = [k for k, _ in part], moved
            continue
        shift = 8 * p
        count = [0] * 256
        for k in keys[low:high]:
            count[(k + bias >> shift) & 255] += 1
        nxt, end, at = [0] * 256, [0] * 256, low
        for v in range(256):
            nxt[v] = at
            at += count[v]
            end[v] = at
        for v in range(256):
            while nxt[v] < end[v]:
                i = nxt[v]
                k, r = keys[i], rows[i]
                while (d := (k + bias >> shift) & 255) != v:
                    j = nxt[d]
                    nxt[d] += 1
                    keys[j], k = k, keys[j]
                    rows[j], r = r, rows[j]
                keys[i], rows[i] = k, r
                nxt[v] += 1
        if p:
            start = low
            for v in range(256):
                if end[v] - start > 1:
                    todo.append((start, end[v], p - 1))
                start = end[v]
