"""The direct sort of the two-stage suffix array holds no copy of each suffix, and is right at every depth."""

from __future__ import annotations

import tracemalloc

import numpy as np
import pytest

from rgsketch.llm import suffix_dedup


def test_direct_sort_copies_no_suffixes():
    rng = np.random.default_rng(5)
    text = np.tile(rng.integers(97, 123, 20_000).astype(np.uint8), 4)
    text[rng.integers(0, len(text), 200)] = 65
    tracemalloc.start()
    order = suffix_dedup.two_stage_suffix_array(text, 400)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150 * len(text)  # 400 bytes for each suffix that is sorted directly were over 180 a byte
    data = text.tobytes()
    keys = [data[i : i + 400] for i in order.tolist()]
    assert sorted(order.tolist()) == list(range(len(text))) and all(a <= b for a, b in zip(keys, keys[1:]))


@pytest.mark.parametrize("symbols", [(0, 1, 97, 254, 255), (0, 255), (97, 98, 99)])
def test_suffix_array_is_right_to_its_depth(symbols):
    rng = np.random.default_rng(11)
    for _ in range(150):
        n = int(rng.integers(1, 80))
        text = np.repeat(rng.choice(symbols, n), rng.integers(1, 25, n) if rng.random() < 0.5 else 1).astype(np.uint8)
        text = np.concatenate([text, np.full(int(rng.integers(0, 20)), rng.choice([0, 255]))]).astype(np.uint8)
        for depth in (1, 8, 9, 50, len(text)):
            order = suffix_dedup.two_stage_suffix_array(text, depth).tolist()
            data = text.tobytes()
            keys = [data[i : i + depth] for i in order]
            assert sorted(order) == list(range(len(text))) and all(a <= b for a, b in zip(keys, keys[1:]))


def test_runs_of_repeated_strings():
    """Three fragments of two texts: what repeats at all, and what repeats in another text, run by run."""
    a, b = b"abcdefghijklmnopqrst", b"0123456789!?+*#%&=()"
    parts = [a + b"-" + b, b + b"/" + a[:12], b"xx" + b[:9]]
    origin = (np.array([0, 0, 1]) << 40) + np.array([0, 100, 0])
    no = np.zeros(3, bool)
    gone, across = suffix_dedup.repeated_strings(parts, np.zeros(3, np.int64), origin, no, no, 8, 50)
    runs = lambda x: list(zip(*(v.tolist() for v in x), strict=True))
    assert runs(gone) == [(0, 0, 12), (0, 21, 41), (1, 0, 20), (1, 21, 33), (2, 2, 11)]
    assert runs(across) == [(0, 21, 30), (1, 0, 9), (2, 2, 11)]
