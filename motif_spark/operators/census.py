"""Exact census: connected induced subgraphs, each enumerated once, counted by isomorphism class.

A set is grown only from its smallest node: a child takes one node of the frontier, keeps the frontier after
it, and adds that node's neighbours that are larger than the root and were not yet seen. The unit of work is
a block of a graph's roots, so a hub's load is dealt out; whole arrays of sets are grown and keyed at once, and
counts are summed in the unit before they are shuffled.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import shared
from . import vector as V
from .canonical import add_codes, canonical_of, parse_code
from .graphs import dealt, rows_of, saved
from .vector import SearchSpaceTooLarge

#: Sets that one unit of work may have before the census stops with an error.
GUARD = 50_000_000
#: Squared degrees, times the largest size, that one unit of work takes on.
UNIT = 8_192
#: Rows that a task holds before it hands them on.
HELD = 20_000


def masks(nbrs: list[list[int]]) -> list[int]:
    return [sum(1 << j for j in row) for row in nbrs]


def enumerate_sets(near: list[int], k_max: int, root: int | None = None, guard: int = GUARD) -> Iterator[tuple[int, ...]]:
    """Connected sets of 1..k_max nodes in the order they were grown, each once; of one root or of all."""
    made = 0
    for r in range(len(near)) if root is None else [root]:
        above = ~((1 << (r + 1)) - 1)
        stack = [((r,), near[r] & above, near[r] | 1 << r)]
        while stack:
            members, frontier, seen = stack.pop()
            made += 1
            if made > guard:
                raise SearchSpaceTooLarge(f"over {guard} connected sets; raise the guard or sample instead")
            yield members
            if len(members) == k_max:
                continue
            while frontier:
                low = frontier & -frontier
                frontier ^= low
                w = low.bit_length() - 1
                stack.append(((*members, w), frontier | (near[w] & above & ~seen), seen | near[w]))


def raw_key(members: tuple[int, ...], labels: list[int], near: list[int]) -> tuple[tuple[int, ...], int]:
    """Labels and adjacency bits in ascending order of the members."""
    order, bits = sorted(members), 0
    for i, x in enumerate(order):
        row = near[x]
        for y in order[i + 1 :]:
            bits = bits << 1 | (row >> y & 1)
    return tuple(labels[x] for x in order), bits


def units_of(k_max: int) -> Column:
    """Units of work that a graph is dealt out in."""
    work = F.aggregate("nbrs", F.lit(0).cast("long"), lambda a, x: a + F.size(x) * F.size(x)) * k_max
    return F.least(F.col("n"), F.greatest(F.lit(1), F.ceil(work / UNIT))).cast("int")


def work_units(graphs: DataFrame, k_max: int = 1) -> DataFrame:
    """Rows with every units-th root of a graph from `unit` on, dealt by hash so that a large graph is spread.

    The number of units follows the graph's squared degrees and the size; a graph has at most a unit for each node.
    """
    units = units_of(k_max)
    df = graphs.filter("n > 0").select("graph_id", "label_ids", "nbrs", units.alias("units"))
    df = df.select("*", F.explode(F.sequence(F.lit(0), F.col("units") - 1)).alias("unit"))
    return dealt(df, "graph_id", "unit")


def _blocks(row: dict, k_max: int, guard: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Labels, adjacency and an array of sets, again and again, for one unit of work."""
    near, labels = V.adjacency(row["nbrs"]), np.array(row["label_ids"], np.int64)
    for members in V.connected_sets(near, k_max, np.arange(row["unit"], len(labels), row["units"]), guard):
        yield labels, near, members


def _by_size(row: dict, sizes: set[int], guard: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """size, labels, bits, counts and least sets of the distinct keys of one unit, summed in blocks."""
    held: dict[int, list[np.ndarray]] = {k: [] for k in sizes}
    rows = dict.fromkeys(sizes, 0)
    labels = near = None
    for labels, near, members in _blocks(row, max(sizes), guard):
        k = members.shape[1]
        if k in sizes:
            held[k].append(members)
            rows[k] += len(members)
            if rows[k] > 200_000:
                yield k, *V.counted(np.concatenate(held[k]), labels, near)
                held[k], rows[k] = [], 0
    for k, parts in held.items():
        if parts:
            yield k, *V.counted(np.concatenate(parts), labels, near)


RAW = "graph_id bigint, k int, labels array<int>, bits bigint, cnt bigint, sample array<int>"


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(x.ravel(), pa.int32()))


def raw_counts(graphs: DataFrame, sizes: list[int], guard: int = GUARD) -> DataFrame:
    """Counts of (labels, bits) by graph and size, with the least set of each, partly summed by the kernel."""
    wanted = set(sizes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                for k, labels, bits, cnt, sample in _by_size(row, wanted, guard):
                    cols = [pa.array(np.full(len(bits), row["graph_id"])), pa.array(np.full(len(bits), k), pa.int32()), _lists(labels), pa.array(bits), pa.array(cnt), _lists(sample)]
                    yield pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "labels", "bits", "cnt", "sample"])

    raw = work_units(graphs, max(wanted)).mapInArrow(kernel, RAW)
    return raw.groupBy("graph_id", "k", "labels", "bits").agg(F.sum("cnt").alias("cnt"), F.min("sample").alias("sample"))


CODED = "graph_id bigint, k int, code string, cnt bigint, n_aut bigint, sample array<int>"


def _classes(row: dict, wanted: set[int], guard: int) -> Iterator[tuple[int, list[str], np.ndarray, np.ndarray, np.ndarray]]:
    """size, codes, counts, automorphisms and least sets of the classes of one unit, in parts that may share classes."""
    held = shared.levels(row["label_ids"], row["nbrs"], wanted) if row["units"] == 1 else None
    if held is not None:
        for k, level in held.items():
            yield k, level.texts(np.arange(len(level.first))), level.freq, level.automorphisms(), level.sample
        return
    yield from _parts(row, wanted, guard)


def _parts(row: dict, wanted: set[int], guard: int) -> Iterator[tuple[int, list[str], np.ndarray, np.ndarray, np.ndarray]]:
    """_classes() of a unit whose sets are not shared."""
    for k, labels, bits, cnt, sample in _by_size(row, wanted, guard):
        kinds = V.Classes(labels, bits)
        first, which = V.alike(kinds.labels, kinds.form)
        order = np.lexsort([*sample.T[::-1], which])
        least = order[np.flatnonzero(np.diff(which[order], prepend=-1))]
        total = np.bincount(which, cnt, len(first)).astype(np.int64)
        yield k, kinds.texts(first), total, kinds.automorphisms[first], sample[least]


def _summed(parts: Iterator[tuple]) -> Iterator[tuple]:
    """A part for each size, of the _parts() of a whole graph."""
    found: dict[int, list[tuple]] = {}
    for k, *part in parts:
        found.setdefault(k, []).append(part)
    for k, held in found.items():
        if len(held) == 1:
            yield k, *held[0]
            continue
        texts, first, which = np.unique(np.concatenate([np.array(p[0], object) for p in held]), return_index=True, return_inverse=True)
        total = np.zeros(len(texts), np.int64)
        np.add.at(total, which, np.concatenate([p[1] for p in held]))
        sample = np.concatenate([p[3] for p in held])
        order = np.lexsort([*sample.T[::-1], which])
        yield k, texts.tolist(), total, np.concatenate([p[2] for p in held])[first], sample[order[np.flatnonzero(np.diff(which[order], prepend=-1))]]


def _coded(parts: list[tuple]) -> pa.RecordBatch:
    """A batch of (graph, *_classes()) parts."""
    rows = [len(p[2]) for p in parts]
    nodes = np.repeat([p[1] for p in parts], rows)
    sample = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *nodes]), pa.int32()), pa.array(np.concatenate([p[5].ravel() for p in parts]), pa.int32()))
    cols = [pa.array(np.repeat([p[0] for p in parts], rows), pa.int64()), pa.array(nodes, pa.int32()), pa.array([c for p in parts for c in p[2]], pa.string())]
    cols += [pa.array(np.concatenate([p[i] for p in parts]), pa.int64()) for i in (3, 4)]
    return pa.RecordBatch.from_arrays([*cols, sample], ["graph_id", "k", "code", "cnt", "n_aut", "sample"])


#: A class has a code and a sample, or the form and word of its name (which are of the row's width) and its least set as bits.
WHOLE = "graph_id bigint, k int, width int, classes array<struct<cnt: bigint, n_aut: bigint, form: bigint, word: bigint, nodes: bigint, code: string, sample: array<int>>>"


def _rows(heads: list[tuple], rows: list[int], fields: list[pa.Array]) -> pa.RecordBatch:
    """A batch of WHOLE with a row for each (graph, size, width) and its classes."""
    cols = [pa.array([x[i] for x in heads], kind) for i, kind in enumerate((pa.int64(), pa.int32(), pa.int32()))]
    classes = pa.StructArray.from_arrays(fields, ["cnt", "n_aut", "form", "word", "nodes", "code", "sample"])
    return pa.RecordBatch.from_arrays([*cols, pa.ListArray.from_arrays(pa.array(np.cumsum([0, *rows]), pa.int32()), classes)], ["graph_id", "k", "width", "classes"])


def _named(parts: list[tuple[int, shared.Level]]) -> pa.RecordBatch:
    """A batch of all classes of (graph, level) parts, which words name."""
    cells = zip(*[(x.freq, x.automorphisms(), *x.words(), x.plan.masks[x.first]) for _, x in parts])
    rows = [len(x.first) for _, x in parts]
    fields = [pa.array(np.concatenate(c), pa.int64()) for c in cells]
    return _rows([(graph, x.size, x.width) for graph, x in parts], rows, [*fields, pa.nulls(sum(rows), pa.string()), pa.nulls(sum(rows), pa.list_(pa.int32()))])


def _spelled(parts: list[tuple]) -> pa.RecordBatch:
    """A batch of (graph, *_parts()) parts, each of a whole graph."""
    _, _, code, cnt, turns, sample = _coded(parts).columns
    none = pa.nulls(len(code), pa.int64())
    return _rows([(p[0], p[1], None) for p in parts], [len(p[2]) for p in parts], [cnt, turns, none, none, none, code, sample])


def _texts(k: pa.Array, width: pa.Array, form: pa.Array, word: pa.Array) -> pa.Array:
    """Codes of the classes that words name; null for the others."""
    out = np.full(len(k), None, object)
    named = np.flatnonzero(width.is_valid().to_numpy(zero_copy_only=False))
    k, width, form, word = (x.take(pa.array(named)).to_numpy(zero_copy_only=False) for x in (k, width, form, word))
    for size, bits in sorted(set(zip(k.tolist(), width.tolist()))):
        own = np.flatnonzero((k == size) & (width == bits))
        out[named[own]] = shared.texts_of(size, bits, form[own], word[own])
    return pa.array(out, pa.string())


def exact_census(graphs: DataFrame, sizes: list[int], guard: int = GUARD) -> DataFrame:
    """graph_id, k, code, freq, n_aut, sample (the least set) for every class of every graph.

    A graph of one unit is counted in its task and its classes are not shuffled. Those that words name get their code and
    their sample from expressions, so that Spark makes neither where nobody reads it.
    """
    wanted = set(sizes)

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        named, parts, rows = [], [], [0, 0]
        for row in rows_of(batches):
            held = shared.levels(row["label_ids"], row["nbrs"], wanted)
            for level in (held or {}).values():
                named.append((row["graph_id"], level))
                rows[0] += len(level.first)
                if rows[0] >= HELD:
                    yield _named(named)
                    named, rows[0] = [], 0
            for k, *part in _summed(_parts(row, wanted, guard)) if held is None else []:
                for at in range(0, len(part[0]), HELD):
                    parts.append((row["graph_id"], k, *[x[at : at + HELD] for x in part]))
                    rows[1] += len(parts[-1][2])
                    if rows[1] >= HELD:
                        yield _spelled(parts)
                        parts, rows[1] = [], 0
        if named:
            yield _named(named)
        if parts:
            yield _spelled(parts)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, rows = [], 0
        for row in rows_of(batches):
            for part in _parts(row, wanted, guard):
                parts.append((row["graph_id"], *part))
                rows += len(part[1])
                if rows >= HELD:
                    yield _coded(parts)
                    parts, rows = [], 0
        if parts:
            yield _coded(parts)

    units, k_max = units_of(max(wanted)), max(wanted)
    counted = work_units(graphs.filter(units <= 1), k_max).mapInArrow(whole, WHOLE).select("graph_id", "k", "width", F.inline("classes"))
    code = F.coalesce("code", F.arrow_udf(_texts, "string")("k", "width", "form", "word"))
    nodes = F.filter(F.sequence(F.lit(0), F.lit(61)), lambda x: F.expr("nodes").bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), x)) != 0)
    counted = counted.select("graph_id", "k", code.alias("code"), F.col("cnt").alias("freq"), "n_aut", F.coalesce("sample", nodes).alias("sample"))
    coded = work_units(graphs.filter(units > 1), k_max).mapInArrow(kernel, CODED)
    return counted.unionByName(coded.groupBy("graph_id", "k", "code").agg(F.sum("cnt").alias("freq"), F.first("n_aut").alias("n_aut"), F.min("sample").alias("sample")))


def _best(row: dict, wanted: set[int], guard: int, then: str) -> Iterator[tuple]:
    """size, frequency, (labels, bits), automorphisms and least sets of the most frequent classes of a whole graph."""
    held = shared.levels(row["label_ids"], row["nbrs"], wanted)
    if held is not None:
        for k, level in held.items():
            top = np.flatnonzero(level.freq == level.freq.max())
            if then == "sample":
                top = top[[level.first[top].argmin()]]
            yield k, int(level.freq[top[0]]), level.raw(top), level.automorphisms(top), level.sample[top]
        return
    found: dict[int, dict[str, tuple[int, int, tuple[int, ...]]]] = {}
    for k, texts, cnt, turns, sample in _classes(row, wanted, guard):
        own = found.setdefault(k, {})
        for code, n, a, s in zip(texts, cnt.tolist(), turns.tolist(), map(tuple, sample.tolist())):
            own[code] = (n + own[code][0], a, min(s, own[code][2])) if code in own else (n, a, s)
    for k, own in found.items():
        code, (n, a, s) = min(own.items(), key=lambda x: (-x[1][0], x[0] if then == "code" else x[1][2]))
        labels, bits = parse_code(code)
        yield k, n, (np.array([labels]), np.array([bits])), np.array([a]), np.array([s])


def _least(graphs: list[int], k: int, freq: list[int], raw: list[tuple], turns: list[np.ndarray], sample: list[np.ndarray]) -> pa.RecordBatch:
    """A batch of the class of least code of each graph, of equals that _best() gives."""
    codes, at = shared.least_codes(raw)
    nodes = np.stack([s[i] for s, i in zip(sample, at)])
    cols = [pa.array(graphs, pa.int64()), pa.array([k] * len(graphs), pa.int32()), pa.array(codes, pa.string()), pa.array(freq, pa.int64()), pa.array([int(a[i]) for a, i in zip(turns, at)], pa.int64()), _lists(nodes)]
    return pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "code", "cnt", "n_aut", "sample"])


def best_census(graphs: DataFrame, sizes: list[int], then: str = "code", guard: int = GUARD) -> DataFrame:
    """most_frequent(exact_census()), where a graph of one unit gives its best classes alone out of its task."""
    wanted = set(sizes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {k: [] for k in wanted}
        rows = dict.fromkeys(wanted, 0)
        for row in rows_of(batches):
            for k, *best in _best(row, wanted, guard, then):
                held[k].append((row["graph_id"], *best))
                rows[k] += len(best[2])
                if rows[k] >= HELD:
                    graph, *rest = zip(*held[k])
                    yield _least(graph, k, *rest)
                    held[k], rows[k] = [], 0
        for k, parts in held.items():
            if parts:
                graph, *rest = zip(*parts)
                yield _least(graph, k, *rest)

    units = units_of(max(wanted))
    whole = work_units(graphs.filter(units <= 1), max(wanted)).mapInArrow(kernel, CODED).withColumnRenamed("cnt", "freq")
    return whole.unionByName(most_frequent(exact_census(graphs.filter(units > 1), sizes, guard), then=then))


def most_frequent(census: DataFrame, ties: bool = False, then: str = "code") -> DataFrame:
    """The most frequent class of each graph and size, by `then` (code or sample) among equals; or all equals."""
    w = Window.partitionBy("graph_id", "k").orderBy(F.desc("freq"), *([] if ties else [then]))
    return census.withColumn("_r", F.rank().over(w)).filter("_r = 1").drop("_r")


def search_space(graphs: DataFrame, sizes: list[int], guard: int = GUARD) -> DataFrame:
    """graph_id, k, sets: how many connected sets there are."""
    k_max, wanted = max(sizes), set(sizes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts: Counter = Counter()
            for row in batch.to_pylist():
                for _, _, members in _blocks(row, k_max, guard):
                    counts[row["graph_id"], members.shape[1]] += len(members)
            keys = [x for x in counts if x[1] in wanted]
            yield pa.RecordBatch.from_arrays([pa.array([g for g, _ in keys], pa.int64()), pa.array([k for _, k in keys], pa.int32()), pa.array([counts[x] for x in keys], pa.int64())], ["graph_id", "k", "sets"])

    return work_units(graphs, k_max).mapInArrow(kernel, "graph_id bigint, k int, sets bigint").groupBy("graph_id", "k").agg(F.sum("sets").alias("sets"))


def enumerate_rows(graphs: DataFrame, k: int) -> DataFrame:
    """graph_id, members of every connected k-set by array expressions: the same rule, one narrow step a level."""
    near = lambda x: F.element_at("nbrs", x + 1)
    df = graphs.select("graph_id", "label_ids", "nbrs", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("root"))
    df = df.withColumns({"members": F.array("root"), "frontier": F.filter(near(F.col("root")), lambda x: x > F.col("root")), "seen": F.array_union(F.array("root"), near(F.col("root")))})
    for _ in range(k - 1):
        df = df.select("*", F.posexplode("frontier").alias("_i", "_w"))
        rest = F.slice("frontier", F.col("_i") + 2, F.size("frontier"))
        new = F.array_except(F.filter(near(F.col("_w")), lambda x: x > F.col("root")), "seen")
        df = df.select("graph_id", "label_ids", "nbrs", "root", F.array_append("members", F.col("_w")).alias("members"), F.concat(rest, new).alias("frontier"), F.array_union("seen", near(F.col("_w"))).alias("seen"))
    return df.select("graph_id", F.array_sort("members").alias("members"))


def enumerate_levels(nodes: DataFrame, edges: DataFrame, k: int) -> DataFrame:
    """graph_id, members by joins that grow every set by every neighbour, with repeats removed at each level."""
    both = edges.select("graph_id", F.col("u").alias("a"), F.col("v").alias("b")).unionByName(edges.select("graph_id", F.col("v").alias("a"), F.col("u").alias("b")))
    df = nodes.select("graph_id", F.array("node").alias("members"))
    for _ in range(k - 1):
        grown = df.withColumn("a", F.explode("members")).join(both, ["graph_id", "a"]).filter(~F.array_contains("members", F.col("b")))
        df = grown.select("graph_id", F.array_sort(F.array_append("members", F.col("b"))).alias("members")).distinct()
    return df


def code_sets(sets: DataFrame, graphs: DataFrame) -> DataFrame:
    """Adds labels, bits, code and n_aut to rows with graph_id and members."""
    from .graphs import induce, shuffled

    held = sets.join(shuffled(graphs.select("graph_id", "label_ids", "nbrs")), "graph_id")
    return add_codes(induce(held).select("graph_id", "members", "labels", "bits"))


def dataset_support(census: DataFrame, least: int = 1) -> DataFrame:
    """Graphs that hold each class at least once."""
    return census.groupBy("k", "code").agg(F.count_distinct("graph_id").alias("support")).filter(F.col("support") >= least)


def two_stage(graphs: DataFrame, k: int) -> DataFrame:
    """The slow check: a miner with threshold one lists the classes of each graph, then each is counted by matching it."""
    from .match import frequency_many
    from .mni import mine

    listed = saved(mine(graphs, k, 1).filter(F.col("k") == k).select("graph_id", "k", "code"))
    return frequency_many(graphs, listed)


def code_of(members: list[int], labels: list[int], nbrs: list[list[int]]) -> str:
    return canonical_of(*raw_key(tuple(members), labels, masks(nbrs)))[0]
