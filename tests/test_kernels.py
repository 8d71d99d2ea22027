import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from digitsort.operators import kernels
from digitsort.plans.bins import Rules

SIZES = [0, 1, 2, 31, 32, 33, 99, 100, 179, 180, 383, 384, 385]
LONGS = st.integers(-(1 << 63), (1 << 63) - 1)


@pytest.mark.parametrize("name", list(kernels.FINISHERS))
@pytest.mark.parametrize("n", SIZES)
@pytest.mark.parametrize("shape", ["random", "sorted", "reversed", "equal"])
def test_finishers(name, n, shape):
    rng = random.Random(n)
    values = {"random": [rng.randrange(50) for _ in range(n)], "sorted": list(range(n)), "reversed": list(range(n, 0, -1)), "equal": [3] * n}[shape]
    pairs = [(v, k) for k, v in enumerate(values)]
    compared, moved = kernels.FINISHERS[name](pairs)
    assert pairs == sorted((v, k) for k, v in enumerate(values))
    assert compared >= max(0, n - 1) * (n > 1) // 2 and moved >= 0


def test_introspective_falls_back_to_heap():
    pairs = [(v, k) for k, v in enumerate([5, 3, 9, 1] * 40)]
    assert kernels.heap(pairs) and pairs == sorted(pairs)


@given(st.lists(LONGS, max_size=400), st.integers(0, 7))
@settings(max_examples=40, deadline=None)
def test_splits_agree_and_are_stable(values, position):
    k = np.array(values, np.int64)
    order, base = kernels.split_plain(k, position)
    digits = [(v + (1 << 63)) >> 8 * position & 255 for v in values]
    assert order.tolist() == sorted(range(len(values)), key=digits.__getitem__)
    staged, base2, flushes = kernels.split_staged(k, position, 64, 16, piece=50)
    assert staged.tolist() == order.tolist() and base.tolist() == base2.tolist()
    assert flushes == sum(-(-digits.count(v) // 4) for v in set(digits))


@given(st.lists(st.one_of(LONGS, st.integers(0, 3)), max_size=600))
@settings(max_examples=40, deadline=None)
def test_light_pass_and_in_place(values):
    k = np.array(values, np.int64)
    order, tally = kernels.light_pass(k, 7, len(k), Rules(tiny=40, small=8))
    assert k[order].tolist() == sorted(values)
    keys, rows = list(values), list(range(len(values)))
    kernels.in_place_radix(keys, rows, small=4)
    assert keys == sorted(values) and [values[r] for r in rows] == keys and sorted(rows) == list(range(len(values)))
