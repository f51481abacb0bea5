"""Multi-task training of the policy by discrete soft actor-critic, and greedy search with it."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import autograd as ag
from . import network as net
from .census import code_of

BEST = "graph_id bigint, k int, method string, members array<int>, code string, dead boolean"
GRADIENT = "name string, at int, g double, weight double"


@dataclass(frozen=True)
class Training:
    """All training choices; reward: best, raw or density."""

    sizes: tuple[int, ...] = (5, 6, 7, 8, 9)
    epochs: int = 150
    episodes: int = 32
    updates: int = 4
    batch: int = 128
    capacity: int = 20_000
    discount: float = 0.99
    target_rate: float = 0.01
    rate: float = 1e-3
    alpha: float = 0.05
    entropy: float = 0.5
    reward: str = "best"
    check_every: int = 25
    seed: int = 1
    most_graphs: int = 2_000


@dataclass
class Policy:
    config: net.Config
    actor: dict[str, np.ndarray]
    curve: list[dict] = field(default_factory=list)
    samples: int = 0


class Adam:
    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.rate, self.t = rate, 0
        self.m, self.v = ({k: np.zeros_like(x) for k, x in params.items()} for _ in range(2))

    def step(self, params: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        norm = np.sqrt(sum(float((g**2).sum()) for g in grads.values()))
        for k, g in grads.items():
            g = g * min(1.0, 5.0 / (norm + 1e-9))
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            params[k] -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def critic_loss(critic: dict, batch: net.Batch, config: net.Config, action: np.ndarray, target: np.ndarray, reward: np.ndarray) -> ag.Tensor:
    q, predicted = net.q_values(critic, batch, config, action)
    miss = ag.pick(q, action) - target
    loss = ag.total(miss * miss)
    if predicted is not None:
        off = predicted - reward
        loss = loss + ag.total(off * off)
    return loss * (1 / len(action))


def actor_loss(actor: dict, batch: net.Batch, config: net.Config, q: np.ndarray, alpha: float) -> ag.Tensor:
    probs = net.actor_probs(actor, batch, config)
    return ag.total(probs * (ag.log(probs) * alpha - q * batch.valid)) * (1 / len(batch.k))


def soft_target(actor: dict, twins: list[dict], after: net.Batch, config: net.Config, reward: np.ndarray, done: np.ndarray, discount: float, alpha: float) -> np.ndarray:
    probs = net.actor_probs(net.tensors(actor), after, config).value
    q = np.minimum(*[net.q_values(net.tensors(t), after, config)[0].value for t in twins])
    soft = (probs * (q * after.valid - alpha * np.log(np.maximum(probs, 1e-12)))).sum(1)
    return reward + discount * np.where(done, 0.0, soft)


def gradients(params: dict[str, np.ndarray], loss) -> tuple[dict[str, np.ndarray], float]:
    held = net.tensors(params)
    out = loss(held)
    out.backward()
    return {k: t.grad if t.grad is not None else np.zeros_like(t.value) for k, t in held.items()}, float(out.value)


#: Transitions that are padded to one batch of a gradient.
PADDED = 256


def distributed_gradients(transitions: DataFrame, params: dict[str, np.ndarray], config: net.Config) -> dict[str, np.ndarray]:
    """Critic gradient of a table of transitions: a sum in every task, then one sum by name and place.

    Columns: label_ids, nbrs, selected, left, k, action, target, reward.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, seen = 0.0, 0
        for batch in batches:
            for start in range(0, batch.num_rows, PADDED):
                rows = batch.slice(start, PADDED).to_pylist()
                b = net.pad([(r["label_ids"], r["nbrs"]) for r in rows], [r["selected"] for r in rows], [r["left"] for r in rows], [r["k"] for r in rows])
                col = lambda c, kind=float: np.array([r[c] for r in rows], kind)  # noqa: B023, E731
                got, _ = gradients(params, lambda p: critic_loss(p, b, config, col("action", int), col("target"), col("reward")))  # noqa: B023
                names = [k for k, g in got.items() for _ in range(g.size)]
                at = np.concatenate([np.arange(g.size) for g in got.values()])
                total, seen = total + np.concatenate([g.ravel() for g in got.values()]) * len(rows), seen + len(rows)
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(at, pa.int32()), pa.array(total), pa.array(np.full(len(total), float(seen)))], ["name", "at", "g", "weight"])

    summed = transitions.mapInArrow(kernel, GRADIENT).groupBy("name", "at").agg((F.sum("g") / F.sum("weight")).alias("g"))
    out = {k: np.zeros(x.size) for k, x in params.items()}
    for r in summed.collect():  # as many rows as parameters
        out[r["name"]][r["at"]] = r["g"]
    return {k: g.reshape(params[k].shape) for k, g in out.items()}


def _sample(probs: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    return np.minimum((probs.cumsum(1) < rng.random((len(probs), 1)) * probs.sum(1, keepdims=True)).sum(1), probs.shape[1] - 1)


def walks(actor: dict[str, np.ndarray], config: net.Config, pool: net.Pool, rows: np.ndarray, sizes: np.ndarray, rng: np.random.Generator | None = None) -> np.ndarray:
    """Nodes picked in the pool's graphs at `rows`, a line for each; greedy without a generator, ties to the smallest node.

    Where a component is too small a line ends early with -1.
    """
    held = net.tensors(actor)
    picked = np.full((len(rows), int(sizes.max(initial=0))), -1)
    selected = np.zeros((len(rows), int(pool.sizes[rows].max(initial=0))), bool)
    alive = np.ones(len(rows), bool)
    for t in range(picked.shape[1]):
        live = np.flatnonzero(alive & (sizes > t))
        for part in _parts(live, pool.sizes[rows], sizes, config):
            b = pool.batch(rows[part], selected[part], sizes[part] - t, sizes[part])
            probs = net.actor_probs(held, b, config).value
            some = probs.sum(1) > 0
            choice = _sample(probs, rng) if rng else probs.argmax(1)
            alive[part] = some
            picked[part[some], t] = choice[some]
            selected[part[some], choice[some]] = True
    return picked


def rollout(actor: dict[str, np.ndarray], config: net.Config, graphs: list, sizes: list[int], rng: np.random.Generator | None = None) -> list[list[int]]:
    """walks() over a list of graphs, as lists of nodes."""
    got = walks(actor, config, net.Pool(graphs), np.arange(len(graphs)), np.array(sizes, int), rng)
    return [[x for x in line if x >= 0] for line in got.tolist()]


def _parts(live: np.ndarray, nodes: np.ndarray, sizes: np.ndarray, config: net.Config, cells: int = 1 << 18) -> Iterator[np.ndarray]:
    """Groups of graphs of like size, so that padding stays small and attention fits in memory."""
    apart = sizes[live] if config.task == "separate" else np.zeros(len(live), int)
    live = live[np.lexsort((nodes[live], apart))]
    a = 0
    while a < len(live):
        b = a + 1
        while b < len(live) and (b + 1 - a) * nodes[live[b]] ** 2 <= cells and (config.task != "separate" or sizes[live[b]] == sizes[live[a]]):
            b += 1
        yield live[a:b]
        a = b


def reward_tables(graphs: DataFrame, census: DataFrame, most: int) -> tuple[dict, dict, dict]:
    """Training graphs, frequencies by (graph, k, code) and best by (graph, k); a bounded number of graphs."""
    rows = graphs.orderBy(F.xxhash64("graph_id"), "graph_id").limit(most).collect()
    held = {r["graph_id"]: (list(r["label_ids"]), [list(x) for x in r["nbrs"]]) for r in rows}
    ids = graphs.sparkSession.createDataFrame([(g,) for g in held], "graph_id bigint")
    freq, best = {}, {}
    for r in census.join(ids, "graph_id", "left_semi").select("graph_id", "k", "code", "freq").toLocalIterator():
        freq[r["graph_id"], r["k"], r["code"]] = r["freq"]
        best[r["graph_id"], r["k"]] = max(best.get((r["graph_id"], r["k"]), 0), r["freq"])
    return held, freq, best


def terminal_reward(kind: str, freq: float, best: float, n: int, m: int, k: int) -> float:
    if kind == "raw":
        return float(freq)
    return freq / best if kind == "best" else freq / (n * (2 * m / (n * (n - 1))) * k)


def train(graphs: DataFrame, census: DataFrame, config: net.Config, how: Training = Training(), valid: DataFrame | None = None, valid_census: DataFrame | None = None) -> Policy:
    """One set of parameters for all sizes. The policy kept is the best on the validation graphs, else on the training graphs."""
    held, freq, best = reward_tables(graphs, census, how.most_graphs)
    checks = reward_tables(valid, valid_census, how.most_graphs) if valid is not None else (held, freq, best)
    rng, ids = np.random.default_rng(how.seed), sorted(held)
    pool, at = net.Pool([held[g] for g in ids]), {g: i for i, g in enumerate(ids)}
    widest = int(pool.sizes.max(initial=0))

    def marks(rows: list[list[int]]) -> np.ndarray:
        out = np.zeros((len(rows), widest), bool)
        for i, nodes in enumerate(rows):
            out[i, list(nodes)] = True
        return out

    actor = net.init(config, "actor", how.seed)
    critics = [net.init(config, "critic", how.seed + 1 + i) for i in range(2)]
    targets = [{k: x.copy() for k, x in c.items()} for c in critics]
    steps = [Adam(p, how.rate) for p in (actor, *critics)]
    memory: list[tuple] = []
    heat = {"log": np.array([np.log(how.alpha)])}
    warmth = Adam(heat, how.rate * 10)
    alpha, policy, top = how.alpha, Policy(config, {k: x.copy() for k, x in actor.items()}), -1.0
    for epoch in range(how.epochs):
        chosen = [ids[i] for i in rng.integers(len(ids), size=how.episodes)]
        sizes = [how.sizes[i] for i in rng.integers(len(how.sizes), size=how.episodes)]
        if config.task == "separate":
            sizes = [how.sizes[epoch % len(how.sizes)]] * how.episodes
        for g, k, nodes in zip(chosen, sizes, rollout(actor, config, [held[g] for g in chosen], sizes, rng)):
            if len(nodes) < k:
                continue
            code = code_of(nodes, *held[g])
            n, m = len(held[g][0]), sum(map(len, held[g][1])) // 2
            r = terminal_reward(how.reward, freq[g, k, code], best[g, k], n, m, k)
            policy.samples += 1
            memory += [(g, k, tuple(nodes[:t]), nodes[t], r if t == k - 1 else 0.0, t == k - 1) for t in range(k)]
        memory = memory[-how.capacity :]
        past = [m for m in memory if m[1] == sizes[0]] if config.task == "separate" else memory
        for _ in range(how.updates if len(past) >= how.batch else 0):
            rows = [past[i] for i in rng.integers(len(past), size=how.batch)]
            own, k = np.array([at[r[0]] for r in rows]), np.array([r[1] for r in rows])
            left = k - np.array([len(r[2]) for r in rows])
            now = pool.batch(own, marks([r[2] for r in rows]), left, k)
            after = pool.batch(own, marks([(*r[2], r[3]) for r in rows]), left - 1, k)
            action, reward, done = np.array([r[3] for r in rows]), np.array([r[4] for r in rows]), np.array([r[5] for r in rows])
            goal = soft_target(actor, targets, after, config, reward, done, how.discount, alpha)
            for c, s in zip(critics, steps[1:]):
                s.step(c, gradients(c, lambda p: critic_loss(p, now, config, action, goal, reward))[0])
            q = np.minimum(*[net.q_values(net.tensors(c), now, config)[0].value for c in critics])
            steps[0].step(actor, gradients(actor, lambda p: actor_loss(p, now, config, q, alpha))[0])
            probs = net.actor_probs(net.tensors(actor), now, config).value
            spread = -(probs * np.log(np.maximum(probs, 1e-12))).sum(1)
            wanted = how.entropy * np.log(np.maximum(now.valid.sum(1), 1)) * (1 - epoch / how.epochs)
            # Temperature: one step down the loss alpha * (entropy - wanted entropy), taken on its logarithm.
            warmth.step(heat, {"log": np.array([np.exp(heat["log"][0]) * (spread - wanted).mean()])})
            heat["log"] = np.clip(heat["log"], np.log(1e-4), 0.0)
            alpha = float(np.exp(heat["log"][0]))
            for t, c in zip(targets, critics):
                for k in t:
                    t[k] += how.target_rate * (c[k] - t[k])
        if (epoch + 1) % how.check_every == 0 or epoch + 1 == how.epochs:
            ratio = mean_ratio(actor, config, *checks, how.sizes)
            policy.curve.append({"epoch": epoch + 1, "samples": policy.samples, **{f"k{k}": x for k, x in ratio.items()}})
            score = float(np.mean(list(ratio.values())))
            if score > top:
                top, policy.actor = score, {k: x.copy() for k, x in actor.items()}
    return policy


def mean_ratio(actor: dict, config: net.Config, held: dict, freq: dict, best: dict, sizes: tuple[int, ...]) -> dict[int, float]:
    """Mean ratio of greedy search over graphs, for each size."""
    work = [(g, k) for g in sorted(held) for k in sizes if (g, k) in best]
    found = rollout(actor, config, [held[g] for g, _ in work], [k for _, k in work])
    got: dict[int, list[float]] = {k: [] for k in sizes}
    for (g, k), nodes in zip(work, found):
        got[k].append(freq[g, k, code_of(nodes, *held[g])] / best[g, k] if len(nodes) == k else 0.0)
    return {k: float(np.mean(x)) if x else 0.0 for k, x in got.items()}


def mine_all(graphs: DataFrame, sizes: list[int], policy: Policy, width: int = 1, seed: int = 1) -> DataFrame:
    """Greedy search of every size in every graph: one narrow stage, no counting.

    With width > 1 that many sampled searches are added to the greedy one; rows are then all their sets.
    """
    actor, config = policy.actor, policy.config

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = batch.to_pylist()
            pool = net.Pool([(r["label_ids"], r["nbrs"]) for r in rows])
            which, wanted = np.repeat(np.arange(len(rows)), len(sizes)), np.tile(np.array(sizes, int), len(rows))
            out = []
            for turn in range(width):
                rng = np.random.default_rng([seed, turn]) if turn else None
                with ag.precision(np.float32):
                    lines = walks(actor, config, pool, which, wanted, rng).tolist()
                for i, k, line in zip(which.tolist(), wanted.tolist(), lines):
                    nodes, row = sorted(x for x in line if x >= 0), rows[i]
                    code = code_of(nodes, row["label_ids"], row["nbrs"]) if len(nodes) == k else None
                    out.append((row["graph_id"], k, "learned", nodes, code, len(nodes) < k))
            cols = list(zip(*out)) if out else [[]] * 6
            kinds = (pa.int64(), pa.int32(), pa.string(), pa.list_(pa.int32()), pa.string(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], ["graph_id", "k", "method", "members", "code", "dead"])

    return graphs.select("graph_id", "label_ids", "nbrs").mapInArrow(kernel, BEST)


def save(policy: Policy, spark: SparkSession, path: str, version: int = 1) -> None:
    rows = [(version, k, list(x.shape), x.astype(np.float32).ravel().tolist()) for k, x in policy.actor.items()]
    spark.createDataFrame(rows, "version int, name string, shape array<int>, values array<float>").coalesce(1).write.mode("append").parquet(path)


def load(spark: SparkSession, path: str, config: net.Config, version: int = 1) -> Policy:
    rows = spark.read.parquet(path).filter(F.col("version") == version).collect()
    return Policy(config, {r["name"]: np.array(r["values"], float).reshape(r["shape"]) for r in rows})


def variants(config: net.Config) -> dict[str, net.Config]:
    """The ablation ladder and single changes."""
    return {
        "plain": replace(config, task="none", state="none", skip="none"),
        "task": replace(config, state="none", skip="none"),
        "state": replace(config, task="none", skip="none"),
        "task_state": replace(config, skip="none"),
        "full": config,
        "plain_skip": replace(config, skip="plain"),
        "state_label": replace(config, state="concat"),
        "separate_tasks": replace(config, task="separate"),
        "no_attention": replace(config, attention=False),
        "mean_pooling": replace(config, pooling="mean"),
        "no_dueling": replace(config, dueling=False),
        "no_reward_head": replace(config, reward_head=False),
    }
