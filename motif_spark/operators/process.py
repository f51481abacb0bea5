"""The decision process: states, tasks, valid actions, rewards, and random rollouts through it."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import vector as V
from .canonical import canonical_of
from .census import masks, raw_key
from .graphs import dealt

ROLLOUT = "graph_id bigint, k int, seed int, sample int, members array<int>, code string"


def reset(graphs: DataFrame, sizes: list[int]) -> DataFrame:
    """A row for each graph and size with nothing selected."""
    return graphs.withColumn("k", F.explode(F.array(*[F.lit(k) for k in sizes]))).withColumns({"selected": F.array().cast("array<int>"), "remaining": F.col("k")})


def task() -> Column:
    """What is left to pick, and the size."""
    return F.struct(F.col("remaining").alias("remaining"), F.col("k").alias("k"))


def valid_actions() -> Column:
    """All nodes at first, then unselected neighbours of what is selected, sorted."""
    near = F.flatten(F.transform("selected", lambda x: F.element_at("nbrs", x + 1)))
    return F.when(F.size("selected") == 0, F.sequence(F.lit(0), F.col("n") - 1)).otherwise(F.array_sort(F.array_except(F.array_distinct(near), "selected")))


def step(states: DataFrame, action: Column) -> DataFrame:
    return states.withColumns({"selected": F.array_append("selected", action), "remaining": F.col("remaining") - 1})


def done() -> Column:
    return F.col("remaining") == 0


def reward(kind: str = "best") -> Column:
    """Reward of a row with freq, best, n, m, k and done: zero before the end.

    raw: the frequency; best: over the best frequency; density: over size, density and k together.
    """
    freq = F.col("freq").cast("double")
    density = 2 * F.col("m") / (F.col("n") * (F.col("n") - 1))
    value = {"raw": freq, "best": freq / F.col("best"), "density": freq / (F.col("n") * density * F.col("k"))}[kind]
    return F.when(F.col("done"), value).otherwise(0.0)


def chance(*key: Column | str) -> Column:
    """A number in [0, 1) from a hash of the key, the same at any partitioning; equals uniform()."""
    joined = F.concat_ws(":", *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in key])
    return F.conv(F.substring(F.md5(joined.cast("binary")), 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))


def sample_action(rows: DataFrame, *key: str) -> DataFrame:
    """Rows graph_id, action, key columns: one node of each graph drawn by the probabilities of graph_id, node, prob."""
    w = Window.partitionBy("graph_id", *key).orderBy("node").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy("graph_id", *key)
    drawn = chance("graph_id", *key) * F.sum("prob").over(whole)
    df = rows.filter("prob > 0").withColumns({"_upto": F.sum("prob").over(w), "_u": drawn, "_last": F.max("node").over(whole)})
    hit = df.filter((F.col("_upto") > F.col("_u")) | (F.col("node") == F.col("_last")))
    return hit.groupBy("graph_id", *key).agg(F.min("node").alias("action"))


def greedy_action(rows: DataFrame, *key: str) -> DataFrame:
    """Rows graph_id, action, key columns: the most probable node, the smallest among equals; none where none is valid."""
    best = rows.filter("prob > 0").groupBy("graph_id", *key).agg(F.min(F.struct(-F.col("prob"), F.col("node").alias("node"))).alias("x"))
    return best.select("graph_id", *key, F.col("x.node").alias("action"))


def uniform(*key: int) -> float:
    """A number in [0, 1) from a hash of the key, the same at any parallelism."""
    return int(md5(":".join(map(str, key)).encode(), usedforsecurity=False).hexdigest()[:13], 16) / (1 << 52)


def walk(near: list[int], k: int, key: tuple[int, ...]) -> tuple[int, ...] | None:
    """k nodes by uniform valid actions; None where the component is too small."""
    chosen, picked, reach = [], 0, (1 << len(near)) - 1
    for t in range(k):
        options = reach & ~picked
        count = options.bit_count()
        if not count:
            return None
        for _ in range(int(uniform(*key, t) * count)):
            options &= options - 1
        x = (options & -options).bit_length() - 1
        chosen.append(x)
        picked |= 1 << x
        reach = near[x] if t == 0 else reach | near[x]
    return tuple(chosen)


def chances(keys: list[bytes], t: int) -> np.ndarray:
    """uniform() of each key and t."""
    end = b":%d" % t
    whole = b"".join([md5(key + end, usedforsecurity=False).digest()[:8] for key in keys])
    return (np.frombuffer(whole, ">u8") >> np.uint64(12)).astype(float) / (1 << 52)


def walks(near: np.ndarray, k: int, key: tuple[int, ...], n_samples: int) -> tuple[np.ndarray, np.ndarray]:
    """walk() of samples 0 to n_samples - 1 at once: numbers of those that came to an end, and their nodes."""
    front = ":".join(map(str, key)).encode()
    return _walked(near, k, [b"%b:%d" % (front, i) for i in range(n_samples)])


def _walked(near: np.ndarray, k: int, keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """A walk for each key: numbers of those that came to an end, and their nodes."""
    n_samples, n = len(keys), len(near)
    kept = np.arange(n_samples)
    chosen = np.zeros((n_samples, 0), np.int64)
    picked, reach = np.zeros((n_samples, n), bool), np.ones((n_samples, n), bool)
    for t in range(k):
        order = np.cumsum(reach & ~picked, 1, dtype=np.int32)
        count = order[:, -1] if n else np.zeros(len(kept), np.int32)
        live = count > 0
        if not live.all():
            kept, chosen, picked, reach, order, count = (x[live] for x in (kept, chosen, picked, reach, order, count))
            keys = [keys[i] for i in np.flatnonzero(live)]
        if not len(kept):
            return kept, np.zeros((0, k), np.int64)
        want = (chances(keys, t) * count).astype(np.int32)
        x = (order > want[:, None]).argmax(1)
        chosen = np.concatenate([chosen, x[:, None]], 1)
        picked[np.arange(len(kept)), x] = True
        reach = near[x] if t == 0 else reach | near[x]
    return kept, chosen


#: Larger sizes, and graphs whose square of nodes is larger, are walked and coded set by set; sets that are coded together.
LARGEST, WALK_CELLS, CODED_ROWS = 11, 4_000_000, 20_000


def _coded(parts: list[tuple]) -> pa.RecordBatch:
    """Rows of (graph, k, seed, samples, members, labels, bits) of one size, each distinct (labels, bits) coded once."""
    sizes = [len(p[3]) for p in parts]
    labels, bits, members, sample = (np.concatenate([p[i] for p in parts]) for i in (5, 6, 4, 3))
    first, which = V.alike(labels, bits)
    kinds = V.Classes(labels[first], bits[first])
    texts = pa.array(kinds.texts(np.arange(len(first))), pa.string())
    held = [np.repeat([p[i] for p in parts], sizes) for i in range(3)]
    nodes = pa.ListArray.from_arrays(pa.array(np.arange(len(members) + 1) * members.shape[1], pa.int32()), pa.array(members.ravel(), pa.int32()))
    cols = [pa.array(held[0], pa.int64()), pa.array(held[1], pa.int32()), pa.array(held[2], pa.int32()), pa.array(sample, pa.int32()), nodes, texts.take(pa.array(which))]
    return pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "seed", "sample", "members", "code"])


def random_rollouts(graphs: DataFrame, sizes: list[int], n_samples: int = 100, seeds: int = 5) -> DataFrame:
    """graph_id, k, seed, sample, members (in order of picking), code; dead ends give no row."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {}
        rows: dict[int, int] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                for g in batch.slice(at, 256).to_pylist():
                    if g["k"] > LARGEST or len(g["nbrs"]) ** 2 > WALK_CELLS:
                        yield one_by_one(g)
                        continue
                    k, (sample, members) = g["k"], walks(V.adjacency(g["nbrs"]), g["k"], (g["graph_id"], g["k"], g["seed"]), n_samples)
                    if not len(sample):
                        continue
                    _, labels, bits = V.keys(members, np.array(g["label_ids"], np.int64), V.adjacency(g["nbrs"]))
                    held.setdefault(k, []).append((g["graph_id"], k, g["seed"], sample, members, labels, bits))
                    rows[k] = rows.get(k, 0) + len(sample)
                    if rows[k] >= CODED_ROWS:
                        yield _coded(held.pop(k))
                        rows[k] = 0
        for parts in held.values():
            yield _coded(parts)

    def one_by_one(g: dict) -> pa.RecordBatch:
        rows, near = [], masks(g["nbrs"])
        for i in range(n_samples):
            s = walk(near, g["k"], (g["graph_id"], g["k"], g["seed"], i))
            if s is not None:
                rows.append((g["graph_id"], g["k"], g["seed"], i, list(s), canonical_of(*raw_key(s, g["label_ids"], near))[0]))
        cols = list(zip(*rows)) if rows else [[]] * 6
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int32()), pa.string())
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["graph_id", "k", "seed", "sample", "members", "code"])

    each = lambda xs: F.explode(F.array(*[F.lit(x) for x in xs]))
    work = graphs.select("graph_id", "label_ids", "nbrs").withColumn("k", each(sizes)).withColumn("seed", each(range(seeds)))
    return dealt(work, "graph_id", "k", "seed").mapInArrow(kernel, ROLLOUT)


def random_baseline(graphs: DataFrame, rollouts: DataFrame, census: DataFrame | None = None) -> DataFrame:
    """graph_id, k, seed, code, freq: the most frequent sampled class. Each class is counted once for a graph."""
    from .graphs import saved, shuffled
    from .match import frequencies, frequency_lookup

    drawn = saved(rollouts.select("graph_id", "k", "seed", "code").distinct())
    classes = drawn.select("graph_id", "k", "code").distinct()
    counted = frequency_lookup(classes, census) if census is not None else frequencies(graphs, classes)
    seen = drawn.join(shuffled(counted), ["graph_id", "k", "code"])
    w = Window.partitionBy("graph_id", "k", "seed").orderBy(F.desc("freq"), "code")
    return seen.withColumn("_r", F.row_number().over(w)).filter("_r = 1").select("graph_id", "k", "seed", "code", "freq")


def random_best(graphs: DataFrame, sizes: list[int], n_samples: int = 100, seeds: int = 5) -> DataFrame:
    """random_baseline(random_rollouts()), where a graph of one unit of work draws, counts and picks in its task.

    All seeds of a graph and size are walked at once. Where its structure is shared, the drawn sets' classes are read
    off; else one walk over its connected sets counts the drawn classes.
    """
    from . import shared
    from .census import GUARD, _by_size, units_of, work_units
    from .graphs import rows_of, saved

    def drawn(g: dict, near: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """size, seeds and nodes of the walks that came to an end."""
        for k in sizes:
            number, members = _walked(near, k, [b"%d:%d:%d:%d" % (g["graph_id"], k, s, i) for s in range(seeds) for i in range(n_samples)])
            if len(number):
                yield k, number // n_samples, members

    def classes(g: dict, near: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray, tuple[np.ndarray, np.ndarray]]]:
        """size, seeds, frequencies, and labels and bits of the drawn classes."""
        held = shared.levels(g["label_ids"], g["nbrs"], set(sizes))
        own = np.array(g["label_ids"], np.int64)
        walked = list(drawn(g, near))
        if held is not None:
            for k, seed, members in walked:
                both = np.unique(seed * len(held[k].first) + held[k].class_of(members))
                seed, at = np.divmod(both, len(held[k].first))
                yield k, seed, held[k].freq[at], held[k].raw(at)
            return
        kinds, first, which, counts = {}, {}, {}, {}
        for k, _, members in walked:
            _, labels, bits = V.keys(members, own, near)
            kinds[k] = V.Classes(labels, bits)
            first[k], which[k] = V.alike(kinds[k].labels, kinds[k].form)
            counts[k] = {(*x, b): 0 for x, b in zip(kinds[k].labels[first[k]].tolist(), kinds[k].form[first[k]].tolist())}
        for k, labels, bits, cnt, _ in _by_size(g | {"unit": 0, "units": 1}, set(counts), GUARD) if counts else ():
            some = V.Classes(labels, bits)
            for x, b, n in zip(some.labels.tolist(), some.form.tolist(), cnt.tolist()):
                if (*x, b) in counts[k]:
                    counts[k][*x, b] += n
        for k, seed, _ in walked:
            freq = np.array(list(counts[k].values()))
            yield k, seed, freq[which[k]], (kinds[k].labels, kinds[k].form)

    def least(k: int, parts: list[tuple]) -> pa.RecordBatch:
        graph, seed, freq, raw = zip(*parts)
        cols = [pa.array(graph, pa.int64()), pa.array([k] * len(parts), pa.int32()), pa.array(seed, pa.int32()), pa.array(shared.least_codes(raw)[0], pa.string()), pa.array(freq, pa.int64())]
        return pa.RecordBatch.from_arrays(cols, ["graph_id", "k", "seed", "code", "freq"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple]] = {k: [] for k in sizes}
        rows = dict.fromkeys(sizes, 0)
        for g in rows_of(batches):
            for k, seed, freq, (labels, bits) in classes(g, V.adjacency(g["nbrs"])):
                for s in np.unique(seed).tolist():
                    own = np.flatnonzero(seed == s)
                    top = own[freq[own] == freq[own].max()]
                    held[k].append((g["graph_id"], s, int(freq[top[0]]), (labels[top], bits[top])))
                    rows[k] += len(top)
                if rows[k] >= CODED_ROWS:
                    yield least(k, held[k])
                    held[k], rows[k] = [], 0
        for k, parts in held.items():
            if parts:
                yield least(k, parts)

    small = (units_of(max(sizes)) <= 1) & (F.col("n").cast("long") * F.col("n") <= WALK_CELLS) & F.lit(max(sizes) <= LARGEST)
    rest = saved(graphs.filter(~small))
    once = work_units(graphs.filter(small), max(sizes)).mapInArrow(kernel, "graph_id bigint, k int, seed int, code string, freq bigint")
    return once.unionByName(random_baseline(rest, random_rollouts(rest, sizes, n_samples, seeds)))


def sample_enumeration(graphs: DataFrame, k: int, keep: list[float], seed: int = 1) -> DataFrame:
    """graph_id, k, code, freq: unbiased estimates from an enumeration whose branches live on by chance.

    keep[j] is the chance that a set of j + 1 nodes is grown further or, at k, counted.
    """
    scale = 1.0
    for p in keep[:k]:
        scale /= p

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            counts: dict = {}
            for g in batch.to_pylist():
                near = masks(g["nbrs"])
                stack = [((r,), near[r] & ~((1 << (r + 1)) - 1), near[r] | 1 << r) for r in range(g["unit"], len(near), g["units"])]
                while stack:
                    members, frontier, seen = stack.pop()
                    above = ~((1 << (members[0] + 1)) - 1)
                    if uniform(seed, g["graph_id"], *members) >= keep[len(members) - 1]:
                        continue
                    if len(members) == k:
                        key = (g["graph_id"], canonical_of(*raw_key(members, g["label_ids"], near))[0])
                        counts[key] = counts.get(key, 0.0) + scale
                        continue
                    while frontier:
                        low = frontier & -frontier
                        frontier ^= low
                        w = low.bit_length() - 1
                        stack.append(((*members, w), frontier | (near[w] & above & ~seen), seen | near[w]))
            keys = list(counts)
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in keys], pa.int64()), pa.array([c for _, c in keys], pa.string()), pa.array([counts[x] for x in keys], pa.float64())], ["graph_id", "code", "freq"])

    from .census import work_units

    return work_units(graphs, k).mapInArrow(kernel, "graph_id bigint, code string, freq double").groupBy("graph_id", "code").agg(F.sum("freq").alias("freq")).withColumn("k", F.lit(k))


def transitions(rollouts: DataFrame, census: DataFrame, graphs: DataFrame, kind: str = "best") -> DataFrame:
    """The replay table: a row for each step of each rollout with what was selected before, the action, reward and end.

    Frequencies are looked up in the census by a join; the reward is paid at the last step.
    """
    from .graphs import shuffled

    best = census.groupBy("graph_id", "k").agg(F.max("freq").alias("best"))
    paid = rollouts.join(shuffled(census.select("graph_id", "k", "code", "freq")), ["graph_id", "k", "code"]).join(shuffled(best), ["graph_id", "k"])
    rows = paid.join(shuffled(graphs.select("graph_id", "n", "m")), "graph_id").select("*", F.posexplode("members").alias("step", "action"))
    rows = rows.withColumns({"selected": F.slice("members", F.lit(1), F.col("step")), "done": F.col("step") == F.col("k") - 1})
    keys = [c for c in ("seed", "sample") if c in rollouts.columns]
    return rows.select("graph_id", "k", *keys, "step", "selected", "action", reward(kind).alias("reward"), "done")
