"""The task- and state-aware graph network with its heads, over padded batches of graphs.

Each message is a difference of two terms that depend on one endpoint each, so all matrix work is done per
node and only a sum over neighbours is done per edge.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from . import autograd as ag
from .autograd import Tensor

MASKED = -1e8


@dataclass(frozen=True)
class Config:
    """Sizes and variants. skip: gated, plain, none; state: message, concat, none; task: embed, separate, none.

    residual adds a node's own representation to what attention gives it, which the published heads do not.
    """

    labels: int = 5
    width: int = 32
    heads: int = 4
    layers: int = 3
    k_max: int = 9
    skip: str = "gated"
    state: str = "message"
    task: str = "embed"
    attention: bool = True
    pooling: str = "attention"
    dueling: bool = True
    reward_head: bool = True
    residual: bool = False


def init(config: Config, kind: str, seed: int) -> dict[str, np.ndarray]:
    """Parameters of an actor or a critic, named by role."""
    rng, d, n = np.random.default_rng(seed), config.width, config.k_max + 1
    dense = lambda a, b: rng.normal(0, np.sqrt(2 / (a + b)), (a, b))
    p = {"label": dense(config.labels * (2 if config.state == "concat" else 1), d) * 2, "task_left": 1 + 0.3 * rng.normal(size=(n, d)), "task_size": 1 + 0.3 * rng.normal(size=(n, d)), "gate_centre": dense(d, d), "gate_near": dense(d, d), "gate_skip": dense(d, d)}
    for layer in range(config.layers):
        for copy in range(n if config.task == "separate" else 1):
            at = f"l{layer}.{copy}." if config.task == "separate" else f"l{layer}."
            p |= {at + x: dense(d, d) * (0.5 if x in ("centre", "near") else 1) for x in ("own", "centre", "near", "gate_c", "gate_n")}
            p |= {at + x: 1 + 0.1 * rng.normal(size=(2, d)) for x in ("state_c", "state_n")}
    p |= {f"att.{x}": dense(d, d) for x in "qkvo"} | {"head.w1": dense(d, d), "head.b1": np.zeros(d), "head.w2": dense(d, 1)}
    if kind == "critic":
        p |= {"pool.seed": rng.normal(size=(1, d))} | {f"pool.{x}": dense(d, d) for x in "kvo"}
        p |= {"pool.w1": dense(d, d), "pool.b1": np.zeros(d), "value.w1": dense(d, d), "value.b1": np.zeros(d), "value.w2": dense(d, 1), "reward.w1": dense(2 * d, d), "reward.b1": np.zeros(d), "reward.w2": dense(d, 1)}
    return p


@dataclass
class Batch:
    """Padded graphs with state and task: labels, near (adjacency), real nodes, selected, left and k, valid actions."""

    labels: np.ndarray
    near: np.ndarray
    real: np.ndarray
    selected: np.ndarray
    left: np.ndarray
    k: np.ndarray

    @property
    def valid(self) -> np.ndarray:
        reach = np.einsum("bij,bj->bi", self.near, self.selected) > 0
        start = self.selected.sum(1, keepdims=True) == 0
        return (start | reach) & (self.selected == 0) & (self.real > 0)


class Pool:
    """Graphs of which padded batches are made again and again."""

    def __init__(self, graphs: list[tuple[list[int], list[list[int]]]]):
        self.sizes = np.array([len(g[0]) for g in graphs], int)
        self.labels = [np.asarray(g[0], int) for g in graphs]
        self.ends = [(np.repeat(np.arange(len(r)), [len(x) for x in r]), np.array([j for x in r for j in x], int)) for _, r in graphs]

    def batch(self, rows: np.ndarray, selected: np.ndarray, left: np.ndarray, k: np.ndarray) -> Batch:
        """The graphs at `rows`; selected has a line of marks for each, at least as wide as the largest graph."""
        n, b = int(self.sizes[rows].max()), len(rows)
        labels, near = np.zeros((b, n), int), np.zeros((b, n, n), np.float32)
        for i, row in enumerate(rows):
            labels[i, : self.sizes[row]] = self.labels[row]
            u, v = self.ends[row]
            near[i, u, v] = 1
        real = (np.arange(n) < self.sizes[rows][:, None]).astype(np.float32)
        return Batch(labels, near, real, selected[:, :n].astype(np.float32), left, k)


def pad(graphs: list[tuple[list[int], list[list[int]]]], selected: list[list[int]], left: list[int], k: list[int]) -> Batch:
    n = max(len(g[0]) for g in graphs)
    b = len(graphs)
    out = Batch(np.zeros((b, n), int), np.zeros((b, n, n)), np.zeros((b, n)), np.zeros((b, n)), np.array(left), np.array(k))
    for i, (labels, nbrs) in enumerate(graphs):
        out.labels[i, : len(labels)] = labels
        out.real[i, : len(labels)] = 1
        for u, row in enumerate(nbrs):
            out.near[i, u, row] = 1
        out.selected[i, selected[i]] = 1
    return out


def layer_plain(p: dict, at: str, h: Tensor, near: np.ndarray) -> Tensor:
    """Own transform plus summed differences to the neighbours."""
    degree = near.sum(2, keepdims=True)
    return ag.relu(h @ p[at + "own"] + (h @ p[at + "centre"]) * degree - ag.tensor(near) @ (h @ p[at + "near"]))


def embed_task(p: dict, left: np.ndarray, k: np.ndarray) -> Tensor:
    return ag.take(p["task_left"], left) * ag.take(p["task_size"], k)


def layer(p: dict, at: str, h: Tensor, b: Batch, task: Tensor | None, state: bool) -> Tensor:
    """The combined layer; without task no gates, without state no scaling, with neither the plain layer."""
    degree, chosen = b.near.sum(2, keepdims=True), b.selected.astype(int)
    c = h * ag.take(p[at + "state_c"], chosen) if state else h
    n = h * ag.take(p[at + "state_n"], chosen) if state else h
    u, v = c @ p[at + "centre"], n @ p[at + "near"]
    if task is not None:
        wide = lambda w: ag.reshape(ag.relu(task) @ w, len(b.k), 1, -1)
        u = u * ag.sigmoid((c * wide(p["gate_centre"])) @ p[at + "gate_c"])
        v = v * ag.sigmoid((n * wide(p["gate_near"])) @ p[at + "gate_n"])
    return ag.relu(h @ p[at + "own"] + u * degree - ag.tensor(b.near) @ v)


def encode(p: dict, b: Batch, config: Config) -> Tensor:
    """Node representations of every graph of the batch."""
    label = b.labels + config.labels * b.selected.astype(int) if config.state == "concat" else b.labels
    first = ag.relu(ag.take(p["label"], label))
    task = embed_task(p, b.left, b.k) if config.task == "embed" else None
    h = first
    for x in range(config.layers):
        at = f"l{x}." if config.task != "separate" else f"l{x}.{int(b.k[0])}."
        h = layer(p, at, h, b, task, config.state == "message")
    if config.skip == "none":
        return h
    if config.skip == "plain" or task is None:
        return first + h
    gate = ag.sigmoid(h * ag.reshape(ag.relu(task) @ p["gate_skip"], len(b.k), 1, -1))
    return first + h * gate


def _attend(q: Tensor, k: Tensor, v: Tensor, real: np.ndarray, heads: int) -> Tensor:
    b, m, d = q.value.shape
    split = lambda t: ag.swap(ag.reshape(t, b, t.value.shape[1], heads, d // heads), 1, 2)
    scores = split(q) @ ag.swap(split(k), 2, 3) * (1 / np.sqrt(d / heads)) + (1 - real)[:, None, None, :] * MASKED
    return ag.reshape(ag.swap(ag.softmax(scores) @ split(v), 1, 2), b, m, d)


def attention(p: dict, h: Tensor, b: Batch, config: Config) -> Tensor:
    """Every node compared with every other of its graph."""
    if not config.attention:
        return h
    seen = _attend(h @ p["att.q"], h @ p["att.k"], h @ p["att.v"], b.real, config.heads) @ p["att.o"]
    return h + seen if config.residual else seen


def scores(p: dict, h: Tensor, prefix: str = "head") -> Tensor:
    out = ag.relu(h @ p[prefix + ".w1"] + p[prefix + ".b1"]) @ p[prefix + ".w2"]
    return ag.reshape(out, *out.value.shape[:-1])


def masked_softmax(x: Tensor, valid: np.ndarray) -> Tensor:
    """Probabilities over the valid entries; all others get exactly none."""
    return ag.softmax(x * valid + (1 - valid) * MASKED) * valid


def actor_probs(p: dict, b: Batch, config: Config) -> Tensor:
    return masked_softmax(scores(p, attention(p, encode(p, b, config), b, config)), b.valid.astype(float))


def pooled(p: dict, h: Tensor, b: Batch, config: Config) -> Tensor:
    if config.pooling == "mean":
        got = ag.total(h * b.real[:, :, None], 1) * (1 / b.real.sum(1, keepdims=True))
    else:
        seed = ag.reshape(p["pool.seed"], 1, 1, -1) * np.ones((len(b.k), 1, 1))
        got = ag.reshape(_attend(seed, h @ p["pool.k"], h @ p["pool.v"], b.real, config.heads) @ p["pool.o"], len(b.k), -1)
    return ag.relu(got @ p["pool.w1"] + p["pool.b1"])


def dueling(value: Tensor, advantage: Tensor, valid: np.ndarray) -> Tensor:
    """Value plus advantage less its mean over the valid actions."""
    v = valid.astype(float)
    mean = ag.total(advantage * v, 1, True) * (1 / np.maximum(v.sum(1, keepdims=True), 1))
    return ag.reshape(value, -1, 1) + advantage - mean


def q_values(p: dict, b: Batch, config: Config, action: np.ndarray | None = None):
    """Q-values of all nodes, and the predicted reward of the given actions."""
    h = encode(p, b, config)
    seen = attention(p, h, b, config)
    graph = pooled(p, h, b, config)
    q = scores(p, seen)
    if config.dueling:
        q = dueling(scores(p, graph, "value"), q, b.valid)
    predicted = scores(p, ag.concat(graph, ag.pick(seen, action)), "reward") if action is not None and config.reward_head else None
    return q, predicted


def tensors(params: dict[str, np.ndarray]) -> dict[str, Tensor]:
    return {name: Tensor(x, needs=True) for name, x in params.items()}
