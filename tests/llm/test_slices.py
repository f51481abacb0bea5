"""Undecided strings of a part that do not fit one slice."""

from __future__ import annotations

import tracemalloc

import numpy as np
import pyarrow as pa

from motif_spark.llm import suffix_dedup as S

HEADS = ["part", "kind", "blob"]


def undecided(docs: int, pieces: int) -> pa.RecordBatch:
    """Texts of common passages in any order: places share anchors but seldom whole strings."""
    rng = np.random.default_rng(5)
    words = [rng.integers(97, 123, 45).astype(np.uint8).tobytes().decode() for _ in range(12)]
    texts = ["".join(words[w] for w in rng.integers(0, 12, pieces)) for _ in range(docs)]
    return pa.RecordBatch.from_arrays([pa.array(range(docs), pa.int64()), pa.array(texts)], ["doc_id", "text"])


def first_places(batch: pa.RecordBatch) -> set[tuple[int, int]]:
    """Where strings occur first, by the kernels of all stages with one part."""
    runs = list(S._anchor_rows(1)(iter([batch])))
    held = [*S._decide_runs(1)(iter(runs)), *S._text_rows(1)(iter([batch]))]
    firsts = list(S._decide_strings(1)(S._open_strings(1)((0,), iter(held))))
    doc, place, size = S._first_runs([b.as_py() for x in firsts for b in x.column(2)])
    d, p, more, several = S._gather([b.as_py() for x in held for k, b in zip(x.column(1), x.column(2)) if k.as_py() == 0], S.DECIDED)
    spans = [*zip(doc, place, size), *((a, b, c + 1) for a, b, c, e in zip(d, p, more.astype(int), several) if not e)]
    return {(int(a), int(b) + i) for a, b, n in spans for i in range(int(n))}


def test_small_slices_find_the_same(monkeypatch):
    batch = undecided(30, 12)
    known: dict[str, tuple[int, int]] = {}
    for doc, text in enumerate(batch.column(1).to_pylist()):
        for at in range(len(text) - S.LENGTH + 1):
            known.setdefault(text[at : at + S.LENGTH], (doc, at))
    assert first_places(batch) == set(known.values())
    monkeypatch.setattr(S, "SLICE_BYTES", 1_000)
    monkeypatch.setattr(S, "SLICE_ROWS", 700)
    assert first_places(batch) == set(known.values())


def test_a_slice_is_held_at_a_time(monkeypatch):
    """A part of undecided runs is worked on in slices; all at once took some 400 bytes for each byte of text."""
    batch = undecided(40, 1_000)
    held = [*S._decide_runs(1)(S._anchor_rows(1)(iter([batch]))), *S._text_rows(1)(iter([batch]))]
    monkeypatch.setattr(S, "SLICE_BYTES", 1 << 18)
    monkeypatch.setattr(S, "SLICE_ROWS", 1 << 17)
    tracemalloc.start()
    rows = sum(1 for _ in S._open_strings(1)((0,), iter(held)))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    text = sum(map(len, batch.column(1).to_pylist()))
    assert rows and peak < 100 * text
