"""Bucket pointers against comparison of all strings."""

from __future__ import annotations

import numpy as np
import pytest

from motif_spark.llm.suffix_dedup import refine_buckets


@pytest.mark.parametrize("length", [9, 16, 33, 100])
@pytest.mark.parametrize("kind", ["random", "periodic", "copies", "one"])
def test_pointers_are_equal_exactly_for_equal_strings(kind, length):
    rng = np.random.default_rng(length)
    data = {
        "random": rng.integers(0, 2, 700),
        "periodic": np.tile(rng.integers(0, 200, 37), 20),
        "copies": np.concatenate([rng.integers(0, 250, 260)] * 2 + [rng.integers(0, 250, 50)] * 3),
        "one": np.zeros(400, int),
    }[kind].astype(np.uint8)
    pointer, raw = refine_buckets(data, length), data.tobytes()
    whole = range(len(data) - length + 1)
    by_bytes, by_pointer = {}, {}
    for i in whole:
        by_bytes.setdefault(raw[i : i + length], []).append(i)
        by_pointer.setdefault(int(pointer[i]), []).append(i)
    assert sorted(by_bytes.values()) == sorted(by_pointer.values())
    order = sorted(whole, key=lambda i: raw[i : i + length])
    assert [int(pointer[i]) for i in order] == sorted(int(pointer[i]) for i in whole)
