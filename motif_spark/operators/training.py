"""Training in Spark: tasks roll out episodes on their own graphs and learn from them, and their weights are averaged.

A lesson is a graph with the frequencies of all its classes (by a 64-bit hash of the code), so a reward is a
look-up in the row itself. Each round is one job over the saved lessons: every partition starts from the same
weights, samples groups of episodes for a graph and size, follows the gradient of the policy with each group's
mean reward as its baseline, and gives back its weights and moments as one row. Those rows are averaged by a
tree of tasks; the driver holds one set of weights, whatever the number of graphs. A lost task is run again from
the same seeds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import autograd as ag
from . import network as net
from .census import code_of
from .graphs import saved
from .learning import Adam, Policy, terminal_reward, walks

#: Rows of weights that one task averages.
FAN = 32
STATE = "part int, weight double, samples bigint, reward double, vector binary"
RATIOS = "k int, ratio double, graphs bigint"


@dataclass(frozen=True)
class Rounds:
    """All choices. In a step a task samples `groups` pairs of graph and size with `per` episodes each.

    With decay the rate falls to nothing over the rounds. reward: best, raw or density. most_graphs: graphs that a task holds, the first by a hash of the id.
    """

    sizes: tuple[int, ...] = (5, 6, 7, 8, 9)
    rounds: int = 30
    steps: int = 8
    groups: int = 16
    per: int = 16
    rate: float = 5e-4
    decay: bool = True
    entropy: float = 0.01
    batch: int = 256
    reward: str = "best"
    check_every: int = 5
    seed: int = 1
    most_graphs: int = 4_000


def lessons(graphs: DataFrame, census: DataFrame, parts: int) -> DataFrame:
    """Saved rows graph_id, label_ids, nbrs, classes (hash, k, freq; by hash), dealt evenly to `parts` partitions."""
    item = F.struct(F.xxhash64("code").alias("h"), F.col("k").alias("k"), F.col("freq").alias("freq"))
    by_graph = census.groupBy("graph_id").agg(F.sort_array(F.collect_list(item)).alias("classes"))
    rows = graphs.select("graph_id", "label_ids", "nbrs").join(by_graph, "graph_id")
    return saved(rows.repartition(parts, F.xxhash64("graph_id", F.lit(7))).sortWithinPartitions(F.xxhash64("graph_id"), "graph_id"))


class School:
    """The lessons of a task."""

    def __init__(self, batches: Iterator[pa.RecordBatch], most: int):
        self.graphs, self.hashes, self.freqs, self.best = [], [], [], []
        for batch in batches:
            classes = batch.column("classes")
            ends = classes.offsets.to_numpy()
            h, k, freq = (x.to_numpy(zero_copy_only=False) for x in classes.values.flatten())
            for i, row in enumerate(batch.select(["label_ids", "nbrs"]).to_pylist()):
                if len(self.graphs) >= most:
                    continue
                part = slice(ends[i], ends[i + 1])
                self.graphs.append((row["label_ids"], row["nbrs"]))
                self.hashes.append(h[part].copy())
                self.freqs.append(freq[part].copy())
                self.best.append({int(x): int(freq[part][k[part] == x].max()) for x in np.unique(k[part])})
        self.pool = net.Pool(self.graphs)

    def frequency(self, row: int, nodes: list[int]) -> int:
        import xxhash

        h = xxhash.xxh64_intdigest(code_of(nodes, *self.graphs[row]), 42)
        h = h - (1 << 64) if h >> 63 else h
        at = int(np.searchsorted(self.hashes[row], h))
        return int(self.freqs[row][at]) if at < len(self.hashes[row]) and self.hashes[row][at] == h else 0

    def rewards(self, kind: str, rows: np.ndarray, sizes: np.ndarray, picked: np.ndarray) -> np.ndarray:
        """Terminal reward of each line of picks; a line that ended early has none."""
        out = np.zeros(len(rows))
        for i, (row, k) in enumerate(zip(rows.tolist(), sizes.tolist())):
            nodes = picked[i, :k].tolist()
            if min(nodes) >= 0:
                labels, nbrs = self.graphs[row]
                out[i] = terminal_reward(kind, self.frequency(row, nodes), self.best[row][k], len(labels), sum(map(len, nbrs)) // 2, k)
        return out


def group_step(school: School, actor: dict, adam: Adam, config: net.Config, how: Rounds, rng: np.random.Generator) -> tuple[int, float]:
    """Episodes in groups, then the policy gradient with each group's mean as baseline. Gives samples and mean reward."""
    sizes = np.array(how.sizes)
    chosen, wanted = rng.integers(len(school.graphs), size=how.groups), rng.choice(sizes, how.groups)
    if config.task == "separate":
        wanted[:] = rng.choice(sizes)
    rows, k = np.repeat(chosen, how.per), np.repeat(wanted, how.per)
    picked = walks(actor, config, school.pool, rows, k, rng)
    reward = school.rewards(how.reward, rows, k, picked)
    grouped = reward.reshape(how.groups, how.per)
    spread = grouped.std(1, keepdims=True)
    gain = ((grouped - grouped.mean(1, keepdims=True)) / (spread + 0.02 * np.abs(grouped).max(1, keepdims=True) + 1e-9)).ravel()
    line, t = np.nonzero(picked >= 0)
    order = rng.permutation(len(line))
    line, t = line[order], t[order]
    for a in range(0, len(line), how.batch):
        i, s = line[a : a + how.batch], t[a : a + how.batch]
        selected = np.zeros((len(i), int(school.pool.sizes.max())), bool)
        for step in range(int(s.max())):
            before = s > step
            selected[before, picked[i[before], step]] = True
        b = school.pool.batch(rows[i], selected, k[i] - s, k[i])
        held = net.tensors(actor)
        probs = net.actor_probs(held, b, config)
        taken = ag.log(ag.pick(probs, picked[i, s]))
        loss = (ag.total(probs * ag.log(probs)) * how.entropy - ag.total(taken * gain[i])) * (1 / len(i))
        loss.backward()
        adam.step(actor, {name: x.grad if x.grad is not None else np.zeros_like(x.value) for name, x in held.items()})
    return len(rows), float(reward.mean())


def _flat(actor: dict, adam: Adam) -> np.ndarray:
    return np.concatenate([x.ravel() for held in (actor, adam.m, adam.v) for x in held.values()]).astype(np.float32)


def _spread(vector: np.ndarray, like: dict) -> list[dict]:
    out, at = [], 0
    for _ in range(3):
        held = {}
        for name, x in like.items():
            held[name] = vector[at : at + x.size].reshape(x.shape).copy()
            at += x.size
        out.append(held)
    return out


def _averaged(rows: DataFrame, parts: int) -> dict:
    """One row of the weighted mean of all rows' vectors, by a tree of tasks of FAN rows each."""

    def kernel(table: pa.Table) -> pa.Table:
        got = table.to_pylist()
        weight = sum(r["weight"] for r in got)
        vector = sum(np.frombuffer(r["vector"], np.float32).astype(float) * r["weight"] for r in got) / max(weight, 1e-9)
        reward = sum(r["reward"] * r["weight"] for r in got) / max(weight, 1e-9)
        return pa.table({"part": pa.array([got[0]["part"]], pa.int32()), "weight": [weight], "samples": pa.array([sum(r["samples"] for r in got)], pa.int64()), "reward": [reward], "vector": pa.array([vector.astype(np.float32).tobytes()], pa.binary())})

    while parts > FAN:
        parts = -(-parts // FAN)
        rows = rows.withColumn("part", F.floor(F.col("part") / FAN).cast("int")).groupBy("part").applyInArrow(kernel, STATE)
    got = rows.collect()  # at most FAN rows of weights
    weight = sum(r["weight"] for r in got)
    vector = sum(np.frombuffer(r["vector"], np.float32).astype(float) * r["weight"] for r in got) / max(weight, 1e-9)
    return {"vector": vector.astype(np.float32), "samples": sum(r["samples"] for r in got), "reward": sum(r["reward"] * r["weight"] for r in got) / max(weight, 1e-9)}


def mean_ratios(rows: DataFrame, policy: Policy, sizes: tuple[int, ...]) -> DataFrame:
    """k, ratio, graphs: mean ratio of greedy search over lessons."""
    actor, config = policy.actor, policy.config

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            school = School(iter([batch]), batch.num_rows)
            which, wanted = np.repeat(np.arange(batch.num_rows), len(sizes)), np.tile(np.array(sizes, int), batch.num_rows)
            with ag.precision(np.float32):
                ratio = school.rewards("best", which, wanted, walks(actor, config, school.pool, which, wanted))
            total = [float(ratio[wanted == k].sum()) for k in sizes]
            yield pa.RecordBatch.from_arrays([pa.array(sizes, pa.int32()), pa.array(total), pa.array([batch.num_rows] * len(sizes), pa.int64())], ["k", "ratio", "graphs"])

    each = rows.mapInArrow(kernel, RATIOS)
    return each.groupBy("k").agg((F.sum("ratio") / F.sum("graphs")).alias("ratio"), F.sum("graphs").alias("graphs"))


def train_rounds(train: DataFrame, config: net.Config, how: Rounds = Rounds(), watch: dict[str, DataFrame] | None = None, start: Policy | None = None, tell=None, keep=None) -> Policy:
    """One set of weights for all sizes, from lessons. Every `check_every` rounds the mean ratio on each watched table
    goes into the curve (and to tell); the policy kept (and given to keep) is the best on `valid` if that is watched,
    else the last."""
    actor = {name: x.astype(np.float32) for name, x in (start.actor if start else net.init(config, "actor", how.seed)).items()}
    adam, parts = Adam(actor, how.rate), train.rdd.getNumPartitions()
    policy, top = Policy(config, {name: x.copy() for name, x in actor.items()}), -1.0
    policy.samples = start.samples if start else 0
    for turn in range(how.rounds):
        state, turns = _flat(actor, adam), adam.t

        def kernel(batches: Iterator[pa.RecordBatch], state=state, turns=turns, turn=turn) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            part = TaskContext.get().partitionId()
            school = School(batches, how.most_graphs)
            if not school.graphs:
                return
            like = net.init(config, "actor", how.seed)
            own, m, v = _spread(state, like)
            local = Adam(own, how.rate * (1 - turn / how.rounds if how.decay else 1))
            local.m, local.v, local.t = m, v, turns
            rng, samples, rewards = np.random.default_rng([how.seed, turn, part]), 0, []
            with ag.precision(np.float32):
                for _ in range(how.steps):
                    n, mean = group_step(school, own, local, config, how, rng)
                    samples += n
                    rewards.append(mean)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([float(len(school.graphs))]), pa.array([samples], pa.int64()), pa.array([float(np.mean(rewards))]), pa.array([_flat(own, local).tobytes()], pa.binary())], ["part", "weight", "samples", "reward", "vector"])

        got = _averaged(train.mapInArrow(kernel, STATE), parts)
        actor, adam.m, adam.v = _spread(got["vector"], actor)
        adam.t = turns + how.steps * max(1, how.groups * how.per * int(np.mean(how.sizes)) // how.batch)
        policy.samples += got["samples"]
        if (turn + 1) % how.check_every == 0 or turn + 1 == how.rounds:
            now = replace_actor(policy, actor)
            score = None
            for split, rows in (watch or {}).items():
                ratios = {r["k"]: r["ratio"] for r in mean_ratios(rows, now, how.sizes).collect()}
                policy.curve.append({"epoch": turn + 1, "samples": policy.samples, "split": split, "reward": got["reward"], **{f"k{k}": x for k, x in ratios.items()}})
                if split == "valid":
                    score = float(np.mean(list(ratios.values())))
                if tell:
                    tell(policy.curve[-1])
            if score is None or score > top:
                top, policy.actor = score if score is not None else top, {name: x.copy() for name, x in actor.items()}
                if keep:
                    keep(policy)
    return policy


def replace_actor(policy: Policy, actor: dict[str, np.ndarray]) -> Policy:
    return replace(policy, actor=actor)
