"""Exact canonical codes of small labelled graphs, their automorphisms and orbits.

Colours start from labels and are refined by neighbour colours; where cells remain, each member is made
single in turn and refinement goes on. Every leaf of that tree is an order of the nodes; the least form is
the code, and the leaves that reach it are the automorphisms. Interchangeable nodes (twins) are set in one
order, which keeps stars cheap.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LABEL_BITS = 5


def _ranks(keys: list) -> list[int]:
    order = {key: i for i, key in enumerate(sorted(set(keys)))}
    return [order[key] for key in keys]


def _refined(colour: list[int], near: list[list[int]]) -> list[int]:
    count = len(set(colour))
    while count < len(colour):
        colour = _ranks([(c, *sorted(colour[j] for j in near[i])) for i, c in enumerate(colour)])
        now = len(set(colour))
        if now == count:
            break
        count = now
    return colour


def _twins(cell: list[int], adj: list[int]) -> bool:
    first = cell[0]
    for x in cell[1:]:
        both = ~(1 << first | 1 << x)
        if (adj[first] ^ adj[x]) & both:
            return False
    return True


def _form(order: list[int], adj: list[int]) -> int:
    bits = 0
    for i, x in enumerate(order):
        row = adj[x]
        for y in order[i + 1 :]:
            bits = bits << 1 | (row >> y & 1)
    return bits


def canonical(labels: tuple[int, ...], adj: list[int]) -> tuple[tuple[int, ...], int, int, list[int], list[int]]:
    """labels and upper-triangle bits in canonical order, number of automorphisms, that order, orbit of each node."""
    k = len(labels)
    near = [[j for j in range(k) if a >> j & 1] for a in adj]
    best, leaves, factor = None, [], 1
    twin_pairs: list[tuple[int, int]] = []

    def walk(colour: list[int], factor: int) -> None:
        nonlocal best, leaves
        cells: dict[int, list[int]] = {}
        for i, c in enumerate(colour):
            cells.setdefault(c, []).append(i)
        open_ = [cells[c] for c in sorted(cells) if len(cells[c]) > 1]
        if not open_:
            order = sorted(range(k), key=colour.__getitem__)
            form = _form(order, adj)
            if best is None or form < best:
                best, leaves = form, []
            if form == best:
                leaves.append((order, factor))
            return
        cell = open_[0]
        alike = _twins(cell, adj)
        if alike:
            twin_pairs.extend((cell[0], x) for x in cell[1:])
        for x in cell[:1] if alike else cell:
            single = [2 * c + (1 if c == colour[x] and i != x else 0) for i, c in enumerate(colour)]
            walk(_refined(_ranks(single), near), factor * (len(cell) if alike else 1))

    walk(_refined(_ranks(list(labels)), near), 1)
    order = leaves[0][0]
    orbit = list(range(k))

    def find(x: int) -> int:
        while orbit[x] != x:
            x = orbit[x]
        return x

    pairs = twin_pairs + [(a, b) for other, _ in leaves[1:] for a, b in zip(order, other)]
    for a, b in pairs:
        a, b = find(a), find(b)
        orbit[max(a, b)] = min(a, b)
    return tuple(labels[i] for i in order), best or 0, sum(f for _, f in leaves), order, [find(i) for i in range(k)]


def rows_of_bits(k: int, bits: int) -> list[int]:
    """Adjacency rows from upper-triangle bits."""
    adj, at = [0] * k, k * (k - 1) // 2
    for i in range(k):
        for j in range(i + 1, k):
            at -= 1
            if bits >> at & 1:
                adj[i] |= 1 << j
                adj[j] |= 1 << i
    return adj


@lru_cache(maxsize=200_000)
def canonical_of(labels: tuple[int, ...], bits: int) -> tuple[str, int, tuple[int, ...], tuple[int, ...]]:
    """Printable code, automorphisms, canonical order and orbits; remembered by each worker."""
    got, form, automorphisms, order, orbit = canonical(labels, rows_of_bits(len(labels), bits))
    return code_text(got, form), automorphisms, tuple(order), tuple(orbit)


def code_text(labels: tuple[int, ...], bits: int) -> str:
    return ".".join(map(str, labels)) + ":" + str(bits)


def parse_code(code: str) -> tuple[tuple[int, ...], int]:
    labels, bits = code.split(":")
    return tuple(map(int, labels.split("."))), int(bits)


def is_isomorphic(a: str, b: str) -> bool:
    return canonical_of(*parse_code(a))[0] == canonical_of(*parse_code(b))[0]


def automorphisms(codes: DataFrame) -> DataFrame:
    """code, n_aut, orbits for a table of codes."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [canonical_of(*parse_code(c)) for c in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([g[1] for g in got], pa.int64()), pa.array([list(g[3]) for g in got], pa.list_(pa.int32()))], ["code", "n_aut", "orbits"])

    return codes.select("code").distinct().mapInArrow(kernel, "code string, n_aut bigint, orbits array<int>")


def add_codes(raw: DataFrame) -> DataFrame:
    """Adds code and n_aut to rows with labels (array) and bits; meant for rows already grouped by both."""
    schema = raw.schema

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [canonical_of(tuple(x), b) for x, b in zip(batch.column("labels").to_pylist(), batch.column("bits").to_pylist())]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.int64())], [*batch.schema.names, "code", "n_aut"])

    from pyspark.sql import types as T

    return raw.mapInArrow(kernel, T.StructType([*schema.fields, T.StructField("code", T.StringType()), T.StructField("n_aut", T.LongType())]))


def small_code(labels: str, bits: str, k: int):
    """Native code for k <= 5: the least (labels, bits) over all orders of the nodes."""
    from itertools import permutations

    at = {}
    n = k * (k - 1) // 2
    for i in range(k):
        for j in range(i + 1, k):
            at[i, j] = n - 1 - len(at)
    bit = lambda i, j: F.shiftright(F.col(bits), at[min(i, j), max(i, j)]).bitwiseAND(F.lit(1).cast("long"))
    forms = []
    for p in permutations(range(k)):
        form = F.lit(0).cast("long")
        for i in range(k):
            for j in range(i + 1, k):
                form = form * 2 + bit(p[i], p[j])
        forms.append(F.struct(F.array(*[F.element_at(labels, x + 1) for x in p]).alias("l"), form.alias("b")))
    least = F.array_min(F.array(*forms))
    return F.concat(F.array_join(F.transform(least["l"], lambda x: x.cast("string")), "."), F.lit(":"), least["b"].cast("string"))
