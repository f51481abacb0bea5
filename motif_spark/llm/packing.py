"""Packing of token pieces into sequences by bin completion.

Only lengths matter to a packing, and there are at most `capacity` of them: the plan is made from the
histogram, so the driver holds no more than that, whatever the corpus. The better of best fit and of
least-waste fillings is the incumbent. Where it needs more sequences than the lower bound, branch and bound
goes over undominated fillings around the largest length left, pruned by the waste that is still allowed,
and back, within a budget of nodes. Pieces then find their places by their rank among pieces of equal length.

Defined cases: a null or empty text has only the end id; repeated rows are packed each on its own, spread like
any others; an empty table gives an empty result; a very long text is cut into pieces of `capacity` ids; among
pieces of one length any order is as good, and it is that of a hash of their place in the saved table; extra
columns are left out, so their names do not matter.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpoint, release
from .tokens import coder

CAPACITY = 2048
#: Pieces of text whose ids a worker holds, and those it keeps between tasks.
HELD_PIECES, KEPT_PIECES = 250_000, 60_000
END = 0
#: Nodes that the search for one filling may visit, and items besides the largest.
NODES, DEPTH = 20_000, 12
#: Nodes that the search over whole packings may visit.
BUDGET = 200_000
#: Pieces of one length that are ranked by one task.
RANK_ROWS = 512
PIECE = ["doc_id", "piece", "start", "length", "ids_crc32"]


def best_fit_fillings(counts: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """Best-fit decreasing by length classes: each bin takes the longest that fits, again and again."""
    left, out = dict(counts), []
    lengths = sorted(left)
    while lengths:
        filling, used, room, k = [], {}, capacity, len(lengths) - 1
        while (k := min(k, bisect_right(lengths, room) - 1)) >= 0:
            x = lengths[k]
            n = min(left[x], room // x)
            used[x] = n
            filling += [x] * n
            room -= n * x
            k -= 1
        times = min(left[x] // n for x, n in used.items())
        for x, n in used.items():
            left[x] -= times * n
        lengths = [x for x in lengths if left[x]]
        out.append((filling, times))
    return out


def best_fit(counts: dict[int, int], capacity: int) -> int:
    """Bins of best-fit decreasing."""
    return sum(times for _, times in best_fit_fillings(counts, capacity))


def lower_bound(counts: dict[int, int], capacity: int) -> int:
    """Bins that no packing goes below: for each k, lengths above capacity - k stand alone, those above half
    the capacity take a bin each, and lengths from k to half fill what these leave."""
    n = np.zeros(capacity + 1, np.int64)
    for x, m in counts.items():
        n[x] = m
    number, size = np.cumsum(n), np.cumsum(n * np.arange(capacity + 1))
    half = capacity // 2
    k = np.arange(1, half + 1)
    large = number[-1] - number[half]
    halves, half_size = number[capacity - k] - number[half], size[capacity - k] - size[half]
    over = size[half] - size[k - 1] - (halves * capacity - half_size)
    return int(max([-(-size[-1] // capacity), *(large + np.maximum(0, -(-over // capacity)))]))


class _Lengths:
    """Lengths left, with the longest that fits."""

    def __init__(self, counts: dict[int, int], capacity: int):
        self.left = [0] * (capacity + 1)
        for x, n in counts.items():
            self.left[x] = n

    def fitting(self, most: int, used: dict[int, int]) -> Iterator[int]:
        for x in range(most, 0, -1):
            if self.left[x] > used.get(x, 0):
                yield x


def complete(lengths: _Lengths, first: int, capacity: int) -> list[int]:
    """A filling around `first`: least waste, then fewest and longest items.

    A filling with an item that could be swapped for a longer one that still fits is dominated, so items go
    in from the longest, and a branch ends where its waste cannot beat the incumbent's.
    """
    used = {first: 1}
    incumbent, room = [first], capacity - first
    for x in _greedy(lengths, room, used):
        incumbent.append(x)
    best, waste = incumbent, capacity - sum(incumbent)
    if not waste:
        return best
    for depth in range(1, DEPTH + 1):
        nodes = [NODES]
        found = _search(lengths, room, room, depth, dict(used), waste, nodes)
        if found and found[0] < waste:
            waste, best = found[0], [first, *found[1]]
            if waste == 0:
                break
        if nodes[0] <= 0 and depth > 3:
            break
    return best


def _greedy(lengths: _Lengths, room: int, used: dict[int, int]) -> list[int]:
    out, used = [], dict(used)
    while room > 0:
        x = next(lengths.fitting(room, used), 0)
        if not x:
            break
        used[x] = used.get(x, 0) + 1
        out.append(x)
        room -= x
    return out


def _search(lengths: _Lengths, room: int, most: int, depth: int, used: dict[int, int], bound: int, nodes: list[int]):
    """Least waste of at most `depth` items no longer than `most`; None if none beats the bound."""
    best = None
    if depth == 1:
        x = next(lengths.fitting(min(room, most), used), 0)
        nodes[0] -= 1
        return (room - x, [x]) if x and room - x < bound else None
    for x in lengths.fitting(min(room, most), used):
        if nodes[0] <= 0 or room - x * depth >= bound:
            break
        nodes[0] -= 1
        if room == x:
            return 0, [x]
        used[x] = used.get(x, 0) + 1
        got = _search(lengths, room - x, x, depth - 1, used, bound, nodes)
        used[x] -= 1
        if got and got[0] < bound:
            bound, best = got[0], (got[0], [x, *got[1]])
            if bound == 0:
                break
    return best


def completions(counts: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """The least-waste filling around each largest length, as often as it lasts, without a way back."""
    lengths, out = _Lengths(counts, capacity), []
    for first in range(capacity, 0, -1):
        while lengths.left[first]:
            filling = complete(lengths, first, capacity)
            times = _times(lengths.left, filling)
            _take(lengths.left, filling, times)
            out.append((filling, times))
    return out


def _times(left: list[int], filling: list[int]) -> int:
    return min(left[x] // n for x, n in Counter(filling).items())


def _take(left: list[int], filling: list[int], times: int) -> None:
    for x in filling:
        left[x] -= times


def _undominated(left: list[int], first: int, capacity: int, allowed: int, nodes: list[int]) -> Iterator[list[int]]:
    """Fillings around `first` that waste at most `allowed`, from the longest items on, each once.

    No length left over fits into the waste, or in the place of a shorter item.
    """
    lengths = [x for x in range(min(first, capacity - first), 0, -1) if left[x] - (x == first) > 0]
    free = {x: left[x] - (x == first) for x in lengths}
    # Bytes that lengths from each place on can fill at most: ends branches that must waste too much.
    rest = [0] * (len(lengths) + 1)
    for k in range(len(lengths) - 1, -1, -1):
        rest[k] = rest[k + 1] + lengths[k] * free[lengths[k]]

    def dominated(filling: list[int], room: int) -> bool:
        used = Counter(filling[1:])
        spare = [x for x in lengths if free[x] > used[x]]
        if any(x <= room for x in spare[-1:]):
            return True
        return any(0 < y - x <= room for x in used for y in spare)

    stack = [(0, [first], capacity - first)]
    while stack and nodes[0] > 0:
        nodes[0] -= 1
        k, filling, room = stack.pop()
        while k < len(lengths) and lengths[k] > room:
            k += 1
        if room - rest[k] > allowed:
            continue
        if k == len(lengths) or room == 0:
            if room <= allowed and not dominated(filling, room):
                yield filling
            continue
        x = lengths[k]
        for n in range(min(free[x], room // x) + 1):  # the most of x is looked at first
            stack.append((k + 1, filling + [x] * n, room - n * x))


def _fewer(counts: dict[int, int], capacity: int, bins: int, nodes: list[int]) -> list[tuple[list[int], int]] | None:
    """A packing into at most `bins`, by branching over fillings and how often each is used; None if none is found.

    What fillings may still waste is what `bins` hold beyond the lengths; a branch ends where it is spent.
    Each filling is tried as often as it lasts, then by halves down to once, which keeps the search whole.
    """
    left = [0] * (capacity + 1)
    for x, n in counts.items():
        left[x] = n
    allowed = bins * capacity - sum(x * n for x, n in counts.items())
    if allowed < 0:
        return None

    def options(first: int, allowed: int) -> Iterator[tuple[list[int], int]]:
        for filling in _undominated(left, first, capacity, allowed, nodes):
            waste, times = capacity - sum(filling), _times(left, filling)
            if waste:
                times = min(times, allowed // waste)
            while times:
                yield filling, times
                times //= 2

    largest = lambda x: next((y for y in range(x, 0, -1) if left[y]), 0)
    path: list[tuple[list[int], int]] = []
    if not (first := largest(capacity)):
        return []
    turns = [(first, allowed, options(first, allowed))]
    while turns:
        first, allowed, more = turns[-1]
        if len(path) == len(turns):
            filling, times = path.pop()
            _take(left, filling, -times)
        step = next(more, None)
        if step is None:
            turns.pop()
            continue
        filling, times = step
        _take(left, filling, times)
        path.append(step)
        if not (below := largest(first)):
            return path
        allowed -= times * (capacity - sum(filling))
        turns.append((below, allowed, options(below, allowed)))
    return None


def plan(counts: dict[int, int], capacity: int = CAPACITY, budget: int = BUDGET) -> list[tuple[list[int], int]]:
    """Fillings and how often each is used, for all lengths.

    The better of completions() and best fit is the incumbent; branch and bound looks for fewer sequences
    until the lower bound is met, no packing is left, or `budget` nodes are spent.
    """
    bins = lambda p: sum(n for _, n in p)
    best = min(completions(counts, capacity), best_fit_fillings(counts, capacity), key=bins)
    least, nodes = lower_bound(counts, capacity), [budget]
    while bins(best) > least and nodes[0] > 0:
        found = _fewer(counts, capacity, bins(best) - 1, nodes)
        if found is None:
            break
        best = found
    return best


def places(fillings: list[tuple[list[int], int]]) -> dict[str, np.ndarray]:
    """Ranges of ranks of each length with the first sequence and the offset they go to, sorted."""
    seen: dict[int, int] = {}
    rows, sequence = [], 0
    for filling, times in fillings:
        offset = 0
        for x in filling:
            rank = seen.get(x, 0)
            rows.append((x, rank, sequence, offset))
            seen[x] = rank + times
            offset += x
        sequence += times
    rows.sort()
    table = np.array(rows, np.int64).reshape(-1, 4)
    return {"key": table[:, 0] << 44 | table[:, 1], "rank": table[:, 1], "sequence": table[:, 2], "offset": table[:, 3]}


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 for every piece of every row; no shuffle."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = coder(tokenizer, HELD_PIECES), np.array([end_id], "<u4")
        for batch in batches:
            rows, done = encode(batch.column(1)), 0
            while some := [*islice(rows, 4096)]:
                at = done
                row, piece, start, length, crc = [], [], [], [], []
                for x in some:
                    x = np.concatenate([x, end])
                    for p, a in enumerate(range(0, len(x), capacity)):
                        part = x[a : a + capacity]
                        row.append(at), piece.append(p), start.append(a), length.append(len(part)), crc.append(zlib.crc32(part))
                    at += 1
                cols = [batch.column(0).take(pa.array(row, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, ["doc_id", "piece", "start", "length", "ids_crc32"])
                done = at
        encode.shrink(KEPT_PIECES)
        release()

    kind = dict(docs.dtypes)[id_col]
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(kernel, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint")


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset for every piece."""
    cut = checkpoint(pieces(docs, tokenizer, capacity, end_id))
    # Rows keep their numbers, as the saved table's partitions stay; so repeated rows are spread, too.
    cut = cut.withColumn("_u", F.monotonically_increasing_id())
    # A full piece is a sequence of its own, numbered below zero: most pieces of long texts need no rank.
    alone = cut.filter(F.col("length") == capacity).select(*PIECE, (-1 - F.col("_u")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    cut = cut.filter(F.col("length") < capacity)
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most `capacity` rows
    slots = places(plan(counts, capacity))
    groups = np.ones(capacity + 1, np.int64)
    for x, n in counts.items():
        groups[x] = -(-n // RANK_ROWS)
    n_groups = F.get(F.array(*[F.lit(int(g)) for g in groups]), F.col("length").cast("int"))
    dealt = cut.withColumn("_g", F.pmod(F.xxhash64("_u"), n_groups))
    sizes = dealt.groupBy("length", "_g").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("length").orderBy("_g").rowsBetween(Window.unboundedPreceding, -1))
    sizes = sizes.select("length", "_g", F.coalesce(before, F.lit(0)).alias("_before"))
    ranked = dealt.withColumn("_r", F.row_number().over(Window.partitionBy("length", "_g").orderBy("doc_id", "piece", "_u")))
    ranked = ranked.join(sizes, ["length", "_g"]).withColumn("_rank", F.col("_before") + F.col("_r") - 1)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(k).to_numpy(zero_copy_only=False) for k in (3, 5))
            at = np.searchsorted(slots["key"], length << 44 | rank, "right") - 1
            cols = [*batch.columns[:5], pa.array(slots["sequence"][at] + rank - slots["rank"][at]), pa.array(slots["offset"][at])]
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    kind = dict(cut.dtypes)["doc_id"]
    placed = ranked.select(*PIECE, "_rank").mapInArrow(kernel, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint")
    return placed.unionByName(alone)
