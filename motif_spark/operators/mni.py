"""Minimum image support, its level-wise miner, and the baseline that trusts it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import shared
from . import vector as V
from .census import units_of, work_units
from .graphs import dealt, rows_of, saved, shuffled

#: Sets that one unit of work may hold at once before it stops with an error.
GUARD = 5_000_000
#: A graph of more units (see census.UNIT) than this is counted unit by unit and its images are merged by Spark.
WHOLE = 16
#: Rows that a task holds before it hands them on.
HELD = 20_000
CENSUS = "graph_id bigint, k int, code string, freq bigint, mni bigint"
MASKS = "graph_id bigint, k int, code string, cnt bigint, place int, word int, mask bigint"


class Level:
    """Classes of an array of sets of one size, with frequency and image support.

    Automorphisms move each place of an orbit over the whole orbit, so an orbit's image is the union of the
    nodes that its places take, and no mapping has to be listed.
    """

    def __init__(self, members: np.ndarray, labels: np.ndarray, near: np.ndarray):
        s, own, bits = V.keys(members, labels, near)
        first, which = V.alike(own, bits)
        self.kinds = V.Classes(own[first], bits[first])
        self.first, kind = V.alike(self.kinds.labels, self.kinds.form)
        self.size, self.nodes = s.shape[1], len(labels)
        self.of = kind[which]
        self.freq = np.bincount(self.of, minlength=len(self.first))
        spot = (self.of[:, None] * self.size + self.kinds.place[which]) * self.nodes + s
        #: Which class, place (of an orbit's first node) and node go together.
        self.cells = np.unique(spot)
        seen = np.bincount(self.cells // self.nodes, minlength=len(self.first) * self.size).reshape(-1, self.size)
        self.support = np.where(seen, seen, self.nodes + 1).min(1)

    def raw(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Labels and bits of classes."""
        return self.kinds.labels[self.first[rows]], self.kinds.form[self.first[rows]]

    def rows(self, graph: int, kept: np.ndarray) -> list[tuple]:
        texts = self.kinds.texts(self.first[kept])
        return [(graph, self.size, c, f, m) for c, f, m in zip(texts, self.freq[kept].tolist(), self.support[kept].tolist())]

    def masks(self, graph: int) -> pa.RecordBatch:
        """Images as 63-bit words."""
        group, node = np.divmod(self.cells, self.nodes)
        word, bit = np.divmod(node, 63)
        key = group * (self.nodes // 63 + 1) + word
        at = np.flatnonzero(np.diff(key, prepend=-1))
        mask = np.bitwise_or.reduceat(np.left_shift(np.int64(1), bit), at)
        kind, place = np.divmod(group[at], self.size)
        lead = np.diff(kind, prepend=-1) != 0  # the class is counted in one of its rows
        cnt = np.where(lead, self.freq[kind], 0)
        texts = np.array(self.kinds.texts(self.first), object)[kind]
        cols = [pa.array(np.full(len(at), graph)), pa.array(np.full(len(at), self.size), pa.int32()), pa.array(texts, pa.string()), pa.array(cnt), pa.array(place, pa.int32()), pa.array(word[at], pa.int32()), pa.array(mask)]
        return pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "code", "cnt", "place", "word", "mask"])


def _whole_levels(row: dict, sizes: set[int], guard: int) -> Iterator[Level | shared.Level]:
    """Levels of a whole graph, read off its structure where that is shared."""
    held = shared.levels(row["label_ids"], row["nbrs"], sizes)
    yield from _levels(row, sizes, guard) if held is None else held.values()


def _levels(row: dict, sizes: set[int], guard: int) -> Iterator[Level]:
    near, labels = V.adjacency(row["nbrs"]), np.array(row["label_ids"], np.int64)
    held: dict[int, list[np.ndarray]] = {k: [] for k in sorted(sizes)}
    for members in V.connected_sets(near, max(sizes), np.arange(row["unit"], len(labels), row["units"]), guard):
        if members.shape[1] in held:
            held[members.shape[1]].append(members)
    for parts in held.values():
        if parts:
            yield Level(np.concatenate(parts), labels, near)


def mni_census(graphs: DataFrame, sizes: list[int], guard: int = GUARD, whole_units: int = WHOLE) -> DataFrame:
    """graph_id, k, code, freq, mni for every class. Large graphs are dealt out by roots and their images merged."""
    wanted = set(sizes)

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for row in rows_of(batches):
            for level in _whole_levels(row, wanted, guard):
                rows += level.rows(row["graph_id"], np.arange(len(level.first)))
            if len(rows) >= HELD:
                yield _rows(rows)
                rows = []
        yield _rows(rows)

    def parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                for level in _levels(row, wanted, guard):
                    yield level.masks(row["graph_id"])

    units = work_units(graphs, max(wanted))
    once = units.filter(f"units <= {whole_units} and unit = 0").withColumn("units", F.lit(1)).mapInArrow(whole, CENSUS)
    masks = units.filter(f"units > {whole_units}").mapInArrow(parts, MASKS)
    words = masks.groupBy("graph_id", "k", "code", "place", "word").agg(F.sum("cnt").alias("cnt"), F.bit_or("mask").alias("mask"))
    places = words.groupBy("graph_id", "k", "code", "place").agg(F.sum("cnt").alias("cnt"), F.sum(F.bit_count("mask")).alias("image"))
    return once.unionByName(places.groupBy("graph_id", "k", "code").agg(F.sum("cnt").alias("freq"), F.min("image").alias("mni")))


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [[]] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64()))], ["graph_id", "k", "code", "freq", "mni"])


def image_sets(matches: DataFrame) -> DataFrame:
    """graph_id, place, image: distinct nodes that a pattern's places take over all mappings."""
    return matches.select("graph_id", F.posexplode("mapping").alias("place", "node")).groupBy("graph_id", "place").agg(F.count_distinct("node").alias("image"))


def mni(matches: DataFrame) -> DataFrame:
    return image_sets(matches).groupBy("graph_id").agg(F.min("image").alias("mni"))


def mine(graphs: DataFrame, k_max: int, least: int, induced: bool = True, guard: int = GUARD) -> DataFrame:
    """Classes with support of at least `least`, level by level: only occurrences of classes that survive grow.

    With induced=False a class's images are those of any place that has at least its edges.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for g in rows_of(batches):
            if induced:
                near, labels = V.adjacency(g["nbrs"]), np.array(g["label_ids"], np.int64)
                for level, kept in grow(near, labels, k_max, least, guard):
                    rows += level.rows(g["graph_id"], kept)
            else:
                rows += [(g["graph_id"], *r) for r in grow_plain(g["label_ids"], g["nbrs"], k_max, least, guard)]
            if len(rows) >= HELD:
                yield _rows(rows)
                rows = []
        yield _rows(rows)

    return graphs.select("graph_id", "label_ids", "nbrs").mapInArrow(kernel, CENSUS)


def grow(near: np.ndarray, labels: np.ndarray, k_max: int, least: int, guard: int = GUARD) -> Iterator[tuple[Level, np.ndarray]]:
    """Level-wise mining of one graph: each level and its surviving classes."""
    members = np.arange(len(labels))[:, None]
    while len(members):
        if len(members) > guard:
            raise V.SearchSpaceTooLarge(f"over {guard} occurrences in one level; raise the guard or the threshold")
        level = Level(members, labels, near)
        ok = level.support >= least
        yield level, np.flatnonzero(ok)
        if members.shape[1] == k_max:
            return
        members = _children(members[ok[level.of]], near)


def _children(members: np.ndarray, near: np.ndarray) -> np.ndarray:
    """Sets that hold one neighbour more, each once."""
    found = [np.zeros((0, members.shape[1] + 1), np.int64)]
    for a in range(0, len(members), 50_000):
        part = members[a : a + 50_000]
        reach = near[part].any(1)
        np.put_along_axis(reach, part, False, 1)
        row, node = np.nonzero(reach)
        found.append(_once(np.sort(np.concatenate([part[row], node[:, None]], 1), 1)))
    return _once(np.concatenate(found))


def _once(rows: np.ndarray) -> np.ndarray:
    order = np.lexsort(rows.T[::-1])
    rows = rows[order]
    new = np.ones(len(rows), bool)
    new[1:] = (rows[1:] != rows[:-1]).any(1)
    return rows[new]


def grow_plain(labels: list[int], nbrs: list[list[int]], k_max: int, least: int, guard: int = GUARD) -> list[tuple[int, str, int, int]]:
    """Level-wise mining of one graph where an occurrence may leave out edges of the graph.

    An occurrence is a set of nodes with chosen edges that connect it; it grows by a node with at least one of
    its edges into the set. One that is left after taking away some node is connected too, so nothing is missed.
    """
    from itertools import combinations

    from .canonical import canonical_of

    near = [set(r) for r in nbrs]
    level = {((i,), frozenset()) for i in range(len(labels))}
    out = []
    for k in range(1, k_max + 1):
        if len(level) > guard:
            raise V.SearchSpaceTooLarge(f"over {guard} occurrences in one level; raise the guard or the threshold")
        classes: dict[str, tuple[set, dict, list]] = {}
        for nodes, edges in level:
            bits = 0
            for a, b in combinations(nodes, 2):
                bits = bits << 1 | ((a, b) in edges)
            code, _, order, orbit = canonical_of(tuple(labels[x] for x in nodes), bits)
            sets, images, held = classes.setdefault(code, (set(), {}, []))
            sets.add(nodes)
            held.append((nodes, edges))
            place = {x: i for i, x in enumerate(order)}
            for x, node in enumerate(nodes):
                images.setdefault(min(place[y] for y in range(k) if orbit[y] == orbit[x]), set()).add(node)
        level = set()
        for code, (sets, images, held) in classes.items():
            support = min(map(len, images.values()))
            if support < least:
                continue
            out.append((k, code, len(sets), support))
            for nodes, edges in held if k < k_max else ():
                for w in set().union(*(near[x] for x in nodes)).difference(nodes):
                    links = [(min(w, x), max(w, x)) for x in nodes if w in near[x]]
                    for count in range(1, len(links) + 1):
                        level.update((tuple(sorted((*nodes, w))), edges.union(pick)) for pick in combinations(links, count))
    return out


def upper_bound(graphs: DataFrame) -> DataFrame:
    """graph_id, bound: no class has more support than its scarcest label has nodes; the most common label bounds all."""
    counts = graphs.select("graph_id", F.explode("label_ids").alias("l")).groupBy("graph_id", "l").count()
    return counts.groupBy("graph_id").agg(F.max("count").alias("bound"))


def descent(graphs: DataFrame, sizes: list[int], shrink: float = 0.5, guard: int = GUARD) -> DataFrame:
    """Mining again and again with a lower threshold until every size has an answer.

    Each graph starts at its label bound and has its own threshold; rows are those of the last run, so they
    hold the classes of most support of every size.
    """
    wanted = set(sizes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for g in batch.to_pylist():
                near, labels = V.adjacency(g["nbrs"]), np.array(g["label_ids"], np.int64)
                least, missing = int(np.bincount(labels).max(initial=0)), set(wanted)
                while missing and least >= 1:
                    for level, kept in grow(near, labels, max(missing), least, guard):
                        if level.size in missing and len(kept):
                            top = level.support[kept].max()
                            rows += level.rows(g["graph_id"], kept[level.support[kept] == top])
                            missing = missing - {level.size}
                    least = min(least - 1, max(1, int(least * shrink)))
            yield _rows(rows)

    return dealt(graphs.select("graph_id", "label_ids", "nbrs"), "graph_id").mapInArrow(kernel, CENSUS)


def best_support(graphs: DataFrame, sizes: list[int], guard: int = GUARD) -> DataFrame:
    """baseline(mni_census()), where a graph of few units gives its best classes alone out of its task."""
    wanted = set(sizes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {k: [] for k in wanted}
        rows = dict.fromkeys(wanted, 0)
        for row in rows_of(batches):
            for level in _whole_levels(row, wanted, guard):
                k, support = level.size, level.support
                top = np.flatnonzero(support == support.max())
                top = top[level.freq[top] == level.freq[top].max()]
                held[k].append((row["graph_id"], int(level.freq[top[0]]), int(support[top[0]]), level.raw(top)))
                rows[k] += len(top)
                if rows[k] >= HELD:
                    yield least(k, held[k])
                    held[k], rows[k] = [], 0
        for k, parts in held.items():
            if parts:
                yield least(k, parts)

    def least(k: int, parts: list[tuple]) -> pa.RecordBatch:
        codes, _ = shared.least_codes([p[3] for p in parts])
        return _rows([(graph, k, code, freq, mni) for (graph, freq, mni, _), code in zip(parts, codes)])

    units = units_of(max(wanted))
    whole = work_units(graphs.filter(units <= WHOLE), max(wanted)).filter("unit = 0").withColumn("units", F.lit(1)).mapInArrow(kernel, CENSUS)
    return whole.unionByName(baseline(mni_census(graphs.filter(units > WHOLE), sizes, guard)))


def max_mni(census: DataFrame) -> DataFrame:
    """Classes of highest support of each graph and size, equals included."""
    w = Window.partitionBy("graph_id", "k").orderBy(F.desc("mni"))
    return census.withColumn("_r", F.rank().over(w)).filter("_r = 1").drop("_r")


def baseline(census: DataFrame) -> DataFrame:
    """The most frequent among the classes of highest support."""
    w = Window.partitionBy("graph_id", "k").orderBy(F.desc("mni"), F.desc("freq"), "code")
    return census.withColumn("_r", F.row_number().over(w)).filter("_r = 1").drop("_r")


def disagreement(census: DataFrame) -> DataFrame:
    """k, graphs, worse: in how many graphs the class of highest support is not a most frequent one."""
    held = saved(census)
    best = held.groupBy("graph_id", "k").agg(F.max("freq").alias("best"))
    joined = baseline(held).join(shuffled(best), ["graph_id", "k"])
    return joined.groupBy("k").agg(F.count(F.lit(1)).alias("graphs"), F.sum((F.col("freq") < F.col("best")).cast("long")).alias("worse"))
