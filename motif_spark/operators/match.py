"""Induced pattern matching: all places of a pattern in a graph, and frequencies from them."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vector as V
from .canonical import canonical_of, code_text, parse_code, rows_of_bits
from .graphs import dealt, rows_of, shuffled
from .vector import Classes


def _order(labels: tuple[int, ...], adj: list[int], have: dict[int, int]) -> list[int]:
    """A connected order of the pattern's nodes from its rarest label on."""
    k = len(labels)
    order = [min(range(k), key=lambda i: (have.get(labels[i], 0), i))]
    while len(order) < k:
        reach = [i for i in range(k) if i not in order and any(adj[i] >> j & 1 for j in order)]
        order.append(min(reach, key=lambda i: (have.get(labels[i], 0), i)))
    return order


@lru_cache(maxsize=50_000)
def breaking(code: str) -> tuple[tuple[int, int], ...]:
    """Pairs (a, b) of places; with node(a) < node(b) for all of them, one mapping of each node set is left.

    The place with the widest orbit is held to the least node of its orbit, then those that leave it in place go on.
    """
    want, bits = parse_code(code)
    adj = rows_of_bits(len(want), bits)
    group = list(mappings(code, list(want), [[j for j in range(len(want)) if a >> j & 1] for a in adj]))
    pairs: list[tuple[int, int]] = []
    while len(group) > 1:
        orbits = [{g[i] for g in group} for i in range(len(want))]
        lead = max(range(len(want)), key=lambda i: len(orbits[i]))
        pairs += [(lead, x) for x in sorted(orbits[lead] - {lead})]
        group = [g for g in group if g[lead] == lead]
    return tuple(pairs)


def mappings(code: str, labels: list[int], nbrs: list[list[int]], below: tuple[tuple[int, int], ...] = ()) -> Iterator[tuple[int, ...]]:
    """Every isomorphism of the pattern onto an induced subgraph, as nodes in pattern order, that meets the pairs `below`."""
    want, bits = parse_code(code)
    adj, k = rows_of_bits(len(want), bits), len(want)
    have: dict[int, list[int]] = {}
    for node, x in enumerate(labels):
        have.setdefault(x, []).append(node)
    near = [set(r) for r in nbrs]
    order = _order(want, adj, {x: len(nodes) for x, nodes in have.items()})
    got = [0] * k
    # What is asked of each place, given the places before it.
    steps = []
    for at, p in enumerate(order):
        linked, apart = ([q for q in order[:at] if (adj[p] >> q & 1) == bit] for bit in (1, 0))
        steps.append((p, linked, apart, [a for a, b in below if b == p and a in order[:at]], [b for a, b in below if a == p and b in order[:at]]))

    def grow(at: int) -> Iterator[tuple[int, ...]]:
        if at == k:
            yield tuple(got)
            return
        p, linked, apart, above, under = steps[at]
        options = have.get(want[p], ()) if not at else set.intersection(*[near[got[q]] for q in linked])
        for x in options:
            if labels[x] != want[p] or any(x <= got[q] for q in above) or any(x >= got[q] for q in under):
                continue
            if any(x == got[q] or x in near[got[q]] for q in apart) or any(x == got[q] for q in linked):
                continue
            got[p] = x
            yield from grow(at + 1)

    yield from grow(0)


@lru_cache(maxsize=50_000)
def automorphisms_of(k: int, bits: int) -> tuple[tuple[int, ...], ...]:
    """All automorphisms of a shape, its labels left out, as the place that each place is put on."""
    nbrs = [[j for j in range(k) if a >> j & 1] for a in rows_of_bits(k, bits)]
    return tuple(mappings(code_text((0,) * k, bits), [0] * k, nbrs))


def label_counts(graphs: DataFrame, labels: set[int]) -> dict[int, int]:
    """Nodes of each of a pattern's labels: at most as many rows as labels."""
    each = graphs.select(F.explode("label_ids").alias("l")).filter(F.col("l").isin(*labels)).groupBy("l").count()
    return {r["l"]: r["count"] for r in each.collect()}


def match_pattern(graphs: DataFrame, code: str, once: bool = False, have: dict[int, int] | None = None) -> DataFrame:
    """graph_id, mapping for every isomorphism, or with `once` for one of each node set.

    Nodes are placed in a connected order from the rarest label on (by `have`, nodes of each label). Labels,
    edges and non-edges are tested on packed neighbour lists, so each step is a narrow explode.
    """
    want, bits = parse_code(code)
    adj = rows_of_bits(len(want), bits)
    order = _order(want, adj, have or {})
    pairs = breaking(code) if once else ()
    label = lambda x: F.element_at("label_ids", x + 1)
    near = lambda x: F.element_at("nbrs", x + 1)
    df = graphs.select("graph_id", "label_ids", "nbrs", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias(f"p{order[0]}"))
    df = df.filter(label(F.col(f"p{order[0]}")) == want[order[0]])
    for at, p in enumerate(order[1:], 1):
        anchor = next(q for q in order[:at] if adj[p] >> q & 1)
        df = df.withColumn(f"p{p}", F.explode(near(F.col(f"p{anchor}")))).filter(label(F.col(f"p{p}")) == want[p])
        for q in order[:at]:
            held = F.array_contains(near(F.col(f"p{q}")), F.col(f"p{p}"))
            df = df.filter((F.col(f"p{p}") != F.col(f"p{q}")) & (held if adj[p] >> q & 1 else ~held))
        for a, b in pairs:
            if p in (a, b) and {a, b} <= set(order[: at + 1]):
                df = df.filter(F.col(f"p{a}") < F.col(f"p{b}"))
    return df.select("graph_id", F.array(*[F.col(f"p{i}") for i in range(len(want))]).alias("mapping"))


def frequency(graphs: DataFrame, code: str) -> DataFrame:
    """graph_id, freq: different node sets that induce the pattern."""
    sets = match_pattern(graphs, code, True, label_counts(graphs, set(parse_code(code)[0])))
    return sets.groupBy("graph_id").agg(F.count(F.lit(1)).alias("freq"))


def mapping_count(census: DataFrame) -> DataFrame:
    """Isomorphisms of each class: frequency times automorphisms."""
    return census.select("graph_id", "k", "code", (F.col("freq") * F.col("n_aut")).alias("mappings"))


def embeddings(near: np.ndarray, adj: list[int], allowed: np.ndarray) -> Iterator[np.ndarray]:
    """Arrays of the isomorphisms of a shape onto induced subgraphs, a column for each place; allowed: its nodes.

    Places are taken in a connected order and whole arrays grow by a place, depth first in blocks.
    """
    k, n = allowed.shape
    order = _order((0,) * k, adj, {})
    most = max(1, CELLS // max(n, 1))
    todo = [np.flatnonzero(allowed[order[0]])[:, None]]
    while todo:
        got = todo.pop()
        if len(got) > most:
            todo += [got[a : a + most] for a in range(0, len(got), most)]
            continue
        at = got.shape[1]
        if at == k:
            yield got[:, np.argsort(order)]
            continue
        p = order[at]
        free = np.repeat(allowed[p][None], len(got), 0)
        for i, q in enumerate(order[:at]):
            free &= near[got[:, i]] if adj[p] >> q & 1 else ~near[got[:, i]]
            free[np.arange(len(got)), got[:, i]] = False
        row, node = np.nonzero(free)
        if len(row):
            todo.append(np.concatenate([got[row], node[:, None]], 1))


#: Codes from which a shape is grown once for all of them, the largest size for it, and cells that are grown at once.
SHARED, LARGEST, CELLS = 4, 11, 4_000_000


@lru_cache(maxsize=50_000)
def _shape(k: int, bits: int) -> tuple[int, tuple[int, ...]]:
    """Canonical bits of a pattern without its labels, and the place that stands at each of their places."""
    code, _, order, _ = canonical_of((0,) * k, bits)
    return parse_code(code)[1], tuple(order)


#: Cells of a shape's places in a structure that are remembered, and of all that a worker remembers.
GROWN, ALL_GROWN = 400_000, 25_000_000
_grown: dict[tuple, np.ndarray | None] = {}


def everywhere(key: tuple, near: np.ndarray, k: int, shape: int) -> np.ndarray | None:
    """All isomorphisms of a shape onto induced subgraphs of a structure that was met before; none where it is new or they
    are too many. Graphs with the same neighbour lists share them."""
    at = (key, k, shape)
    if at not in _grown:
        if sum(x.size for x in _grown.values() if x is not None) + 100 * len(_grown) > ALL_GROWN:
            _grown.clear()
        _grown[at] = np.zeros((0, 0), np.int32)
        return None
    if _grown[at] is not None and not _grown[at].shape[1]:
        parts, cells = [np.zeros((0, k), np.int64)], 0
        for spots in embeddings(near, rows_of_bits(k, shape), np.ones((k, len(near)), bool)):
            parts.append(spots)
            cells += spots.size
            if cells > GROWN:
                break
        _grown[at] = np.concatenate(parts).astype(np.int32) if cells <= GROWN else None
    return _grown[at]


def matched(codes: list[str], label_ids: list[int], nbrs: list[list[int]]) -> list[int]:
    """Frequencies of codes of one size in a graph. Codes that differ in labels alone share one growth of their
    shape: its isomorphisms by their labels, over each code's automorphisms."""
    out, shapes = [0] * len(codes), {}
    k = codes[0].count(".") + 1 if codes else 0
    for i, code in enumerate(codes):
        labels, bits = parse_code(code)
        shape, order = _shape(k, bits) if k <= LARGEST else (code, range(k))
        shapes.setdefault(shape, []).append((i, [labels[x] for x in order]))
    have, near, key = np.array(label_ids, np.int64), V.adjacency(nbrs), tuple(map(tuple, nbrs))
    for shape, held in shapes.items():
        if len(held) < SHARED or k > LARGEST:
            for i, _ in held:
                out[i] = sum(1 for _ in mappings(codes[i], label_ids, nbrs, breaking(codes[i])))
            continue
        want = np.array([labels for _, labels in held], np.int64)
        found = np.zeros(len(want), np.int64)
        whole = everywhere(key, near, k, shape)
        grown = [whole] if whole is not None else embeddings(near, rows_of_bits(k, shape), np.stack([np.isin(have, want[:, p]) for p in range(k)]))
        for spots in grown:
            labels = np.concatenate([want, have[spots]])
            first, which = V.alike(labels, np.zeros(len(labels), np.int64))
            found += np.bincount(which[len(want) :], minlength=len(first))[which[: len(want)]]
        found //= Classes(want, np.full(len(want), shape)).automorphisms
        for (i, _), n in zip(held, found.tolist()):
            out[i] = n
    return out


def frequency_many(graphs: DataFrame, patterns: DataFrame) -> DataFrame:
    """Adds freq to rows with graph_id, k and code, by matching the patterns in their graph, each node set once.

    Patterns of a graph that differ in labels alone are matched together, so a graph's list of them travels with it.
    """
    listed = patterns.groupBy("graph_id", "k").agg(F.collect_list("code").alias("codes"))
    held = listed.join(shuffled(graphs.select("graph_id", "label_ids", "nbrs")), "graph_id").select("graph_id", "k", "codes", "label_ids", "nbrs")
    held = dealt(held, "graph_id", "k")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                rows = batch.slice(at, 256)
                codes = rows.column("codes")
                freq = [x for r in rows.to_pylist() for x in matched(r["codes"], r["label_ids"], r["nbrs"])]
                own = pc.list_parent_indices(codes)
                yield pa.RecordBatch.from_arrays([rows.column("graph_id").take(own), rows.column("k").take(own), codes.flatten(), pa.array(freq, pa.int64())], ["graph_id", "k", "code", "freq"])

    return held.mapInArrow(kernel, "graph_id bigint, k int, code string, freq bigint")


#: Patterns for each graph and size from which one walk over all sets is cheaper than matching each pattern.
MANY = 24


def _found(graph: int, sizes: list[int], codes: list[str], freq: list[int]) -> pa.RecordBatch:
    cols = [pa.array([graph] * len(codes), pa.int64()), pa.array(sizes, pa.int32()), pa.array(codes, pa.string()), pa.array(freq, pa.int64())]
    return pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "code", "freq"])


def frequency_listed(graphs: DataFrame, patterns: DataFrame, sizes: list[int]) -> DataFrame:
    """frequency_many() by one walk over the connected sets of each graph, of which only the listed classes are counted.

    A graph's list travels with each of its units, so it should be bounded, as samples are.
    """
    from . import shared
    from .census import GUARD, _by_size, work_units

    listed = patterns.groupBy("graph_id").agg(F.collect_set(F.struct("k", "code")).alias("wanted"))
    units = work_units(graphs, max(sizes)).join(shuffled(listed), "graph_id")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in rows_of([batch]):
                held = shared.levels(row["label_ids"], row["nbrs"], set(sizes)) if row["units"] == 1 else None
                if held is not None:
                    at = [held[w["k"]].find(w["code"]) if w["k"] in held else None for w in row["wanted"]]
                    freq = [0 if i is None else int(held[w["k"]].freq[i]) for w, i in zip(row["wanted"], at)]
                    yield _found(row["graph_id"], [w["k"] for w in row["wanted"]], [w["code"] for w in row["wanted"]], freq)
                    continue
                counts = {(w["k"], w["code"]): 0 for w in row["wanted"]}
                forms: dict[int, set[int]] = {}
                for w in row["wanted"]:
                    forms.setdefault(w["k"], set()).add(int(w["code"].split(":")[1]))
                for k, labels, bits, cnt, _ in _by_size(row, set(forms), GUARD) if forms else ():
                    kinds = Classes(labels, bits)
                    some = np.flatnonzero(np.isin(kinds.form, list(forms[k])))
                    for code, n in zip(kinds.texts(some), cnt[some].tolist()):
                        if (k, code) in counts:
                            counts[k, code] += n
                keys = list(counts)
                yield _found(row["graph_id"], [k for k, _ in keys], [c for _, c in keys], [counts[x] for x in keys])

    found = units.mapInArrow(kernel, "graph_id bigint, k int, code string, freq bigint")
    return found.groupBy("graph_id", "k", "code").agg(F.sum("freq").alias("freq"))


def frequencies(graphs: DataFrame, patterns: DataFrame) -> DataFrame:
    """frequency_many() or frequency_listed(), by how many patterns a graph and size has on average."""
    load = patterns.groupBy("graph_id", "k").agg(F.count(F.lit(1)).alias("n")).groupBy("k").agg(F.avg("n").alias("n"))
    many = {r["k"]: r["n"] for r in load.collect()}  # one row for each size
    dense, rest = [k for k, n in many.items() if n >= MANY], [k for k, n in many.items() if n < MANY]
    rows = patterns.select("graph_id", "k", "code")
    if not dense:
        return frequency_many(graphs, rows)
    found = frequency_listed(graphs, rows.filter(F.col("k").isin(dense)), dense)
    return found.unionByName(frequency_many(graphs, rows.filter(F.col("k").isin(rest)))) if rest else found


def frequency_lookup(found: DataFrame, census: DataFrame) -> DataFrame:
    """Adds freq from a census to rows with graph_id, k and code."""
    return found.join(shuffled(census.select("graph_id", "k", "code", "freq")), ["graph_id", "k", "code"])
