"""Queries of the network: the kernel that trains and searches, run on whole suites, beside SQL of every formula.

Weights are those of a fixed seed, two wide, so that a statement can spell them out. All graphs are in one
state: nodes 0 and 1 are selected, three of five are left to pick.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import autograd as ag
from ..operators import network as net
from .class_queries import session
from .graph_queries import SESSION

QUERIES, SQL = {}, {}
SELECTED, LEFT, SIZE, ACTION = [0, 1], 3, 5, 2
BASE = net.Config(labels=5, width=2, heads=1, layers=2, k_max=5)


def run(spark: SparkSession, sf_dir: str, config: net.Config, kind: str, value: Callable[[dict, net.Batch], np.ndarray], by_node: bool = True) -> DataFrame:
    """graph_id, node and the columns of value(parameters, batch), for every graph of the session suite."""
    params = net.init(config, kind, 3)
    names = ["value"]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                b = net.pad([(row["label_ids"], row["nbrs"])], [SELECTED], [LEFT], [SIZE])
                got = np.asarray(value(net.tensors(params), b))[0]
                got = got.reshape(len(got), -1) if by_node else got.reshape(1, -1)
                n = len(got)
                cols = [pa.array(np.full(n, row["graph_id"])), pa.array(np.arange(n), pa.int32()), pa.array(list(got), pa.list_(pa.float64()))]
                yield pa.RecordBatch.from_arrays(cols, ["graph_id", "node", *names])

    return session(spark, sf_dir).mapInArrow(kernel, "graph_id bigint, node int, value array<double>")


def _columns(df: DataFrame, *names: str, node: bool = True) -> DataFrame:
    return df.select("graph_id", *(["node"] if node else []), *[(F.round(F.col("value")[j], 6) + 0.0).alias(x) for j, x in enumerate(names)])


def _keep(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str) -> None:
    QUERIES[name], SQL[name] = f, sql


# --- the SQL side ---------------------------------------------------------------------------------------------


def _num(x: float) -> str:
    return f"({float(x)!r}::DOUBLE)"


def _mul(names: list[str], w: np.ndarray, j: int) -> str:
    return "(" + " + ".join(f"{x} * {_num(w[i][j])}" for i, x in enumerate(names)) + ")"


def _pick(table: np.ndarray, index: str, j: int) -> str:
    return f"CASE {index} " + " ".join(f"WHEN {i} THEN {_num(r[j])}" for i, r in enumerate(table)) + " END"


def _sigmoid(x: str) -> str:
    return f"(1 / (1 + exp(-({x}))))"


def encoder_sql(config: net.Config, kind: str) -> str:
    """CTEs up to h: graph_id, node, sel, h0, h1, the encoder's result."""
    p, d = net.init(config, kind, 3), config.width
    spots = range(d)
    task = np.maximum(p["task_left"][LEFT] * p["task_size"][SIZE], 0)
    index = f"(label_id + {config.labels} * sel)" if config.state == "concat" else "label_id"
    out = [SESSION, f"st AS (SELECT graph_id, node, label_id, CASE WHEN node IN ({', '.join(map(str, SELECTED))}) THEN 1 ELSE 0 END AS sel FROM s)"]
    out.append("e0 AS (SELECT graph_id, node, sel, " + ", ".join(f"greatest({_pick(p['label'], index, j)}, 0) AS h{j}" for j in spots) + " FROM st)")
    for x in range(config.layers):
        at = f"l{x}.{SIZE}." if config.task == "separate" else f"l{x}."
        side = lambda who: [f"h{j} * {_pick(p[f'{at}state_{who}'], 'sel', j)}" if config.state == "message" else f"h{j}" for j in spots]  # noqa: E731, B023
        gate = lambda who, wide, names: [_sigmoid(_mul([f"{n} * {_num((task @ p[wide])[i])}" for i, n in enumerate(names)], p[f"{at}gate_{who}"], j)) for j in spots] if config.task == "embed" else ["1"] * d  # noqa: E731, B023
        c, n = [f"c{j}" for j in spots], [f"n{j}" for j in spots]
        out.append(f"a{x} AS (SELECT *, " + ", ".join(f"{v} AS c{j}" for j, v in enumerate(side("c"))) + ", " + ", ".join(f"{v} AS n{j}" for j, v in enumerate(side("n"))) + f" FROM e{x})")
        u = [f"{_mul(c, p[at + 'centre'], j)} * {g} AS u{j}" for j, g in enumerate(gate("c", "gate_centre", c))]
        v = [f"{_mul(n, p[at + 'near'], j)} * {g} AS v{j}" for j, g in enumerate(gate("n", "gate_near", n))]
        out.append(f"m{x} AS (SELECT *, {', '.join(u + v)} FROM a{x})")
        out.append(f"r{x} AS (SELECT b.graph_id, b.a AS node, count(*) AS deg, {', '.join(f'sum(v{j}) AS s{j}' for j in spots)} FROM b JOIN m{x} y ON y.graph_id = b.graph_id AND y.node = b.o GROUP BY 1, 2)")
        own = [f"greatest({_mul([f'h{i}' for i in spots], p[at + 'own'], j)} + u{j} * deg - s{j}, 0) AS h{j}" for j in spots]
        out.append(f"e{x + 1} AS (SELECT y.graph_id, y.node, y.sel, {', '.join(own)} FROM m{x} y JOIN r{x} t ON t.graph_id = y.graph_id AND t.node = y.node)")
    last = f"e{config.layers}"
    if config.skip == "none":
        out.append(f"h AS (SELECT * FROM {last})")
    else:
        gated = config.skip == "gated" and config.task == "embed"
        g = [" * " + _sigmoid(f"z.h{j} * {_num((task @ p['gate_skip'])[j])}") if gated else "" for j in spots]
        out.append(f"h AS (SELECT z.graph_id, z.node, z.sel, {', '.join(f'f.h{j} + z.h{j}{g[j]} AS h{j}' for j in spots)} FROM e0 f JOIN {last} z ON z.graph_id = f.graph_id AND z.node = f.node)")
    return ", ".join(out)


def heads_sql(config: net.Config, kind: str) -> str:
    """encoder_sql() with seen (after attention), valid and score; for a critic also pool, value, q and predicted."""
    p, d, heads = net.init(config, kind, 3), config.width, config.heads
    spots, wide = range(d), d // config.heads
    hs = [f"h{i}" for i in spots]
    out = [encoder_sql(config, kind)]
    parts = lambda h: range(h * wide, (h + 1) * wide)
    if config.attention:
        out.append("qkv AS (SELECT *, " + ", ".join(f"{_mul(hs, p['att.' + w], j)} AS {w}{j}" for w in "qkv" for j in spots) + " FROM h)")
        out.append("pair AS (SELECT x.graph_id, x.node, x.sel, " + ", ".join(f"x.h{j} AS h{j}, y.v{j} AS v{j}" for j in spots) + ", " + ", ".join("exp((" + " + ".join(f"x.q{j} * y.k{j}" for j in parts(h)) + f") / {_num(np.sqrt(wide))}) AS w{h}" for h in range(heads)) + " FROM qkv x JOIN qkv y ON y.graph_id = x.graph_id)")
        out.append("att AS (SELECT graph_id, node, sel, " + ", ".join(f"any_value(h{j}) AS h{j}, sum(w{j // wide} * v{j}) / sum(w{j // wide}) AS o{j}" for j in spots) + " FROM pair GROUP BY 1, 2, 3)")
        own = "h{j} + " if config.residual else ""
        out.append("seen AS (SELECT graph_id, node, sel, " + ", ".join(f"{own.format(j=j)}{_mul([f'o{i}' for i in spots], p['att.o'], j)} AS h{j}" for j in spots) + " FROM att)")
    else:
        out.append("seen AS (SELECT * FROM h)")

    def layer(names: list[str], at: str) -> str:
        hidden = [f"greatest({_mul(names, p[at + '.w1'], j)} + {_num(p[at + '.b1'][j])}, 0)" for j in spots]
        return _mul(hidden, p[at + ".w2"], 0)

    near = f"SELECT DISTINCT graph_id, o FROM b WHERE a IN ({', '.join(map(str, SELECTED))}) AND o NOT IN ({', '.join(map(str, SELECTED))})"
    out.append(f"score AS (SELECT x.graph_id, x.node, {layer(hs, 'head')} AS score, v.o IS NOT NULL AS valid FROM seen x LEFT JOIN ({near}) v ON v.graph_id = x.graph_id AND v.o = x.node)")
    if kind == "critic":
        if config.pooling == "mean":
            out.append("pooled AS (SELECT graph_id, " + ", ".join(f"avg(h{j}) AS g{j}" for j in spots) + " FROM h GROUP BY 1)")
        else:
            weight = ["exp((" + " + ".join(f"{_num(p['pool.seed'][0][j])} * {_mul(hs, p['pool.k'], j)}" for j in parts(h)) + f") / {_num(np.sqrt(wide))}) AS w{h}" for h in range(heads)]
            out.append("pw AS (SELECT graph_id, " + ", ".join(weight) + ", " + ", ".join(f"{_mul(hs, p['pool.v'], j)} AS v{j}" for j in spots) + " FROM h)")
            out.append("pv AS (SELECT graph_id, " + ", ".join(f"sum(w{j // wide} * v{j}) / sum(w{j // wide}) AS o{j}" for j in spots) + " FROM pw GROUP BY 1)")
            out.append("pooled AS (SELECT graph_id, " + ", ".join(f"{_mul([f'o{i}' for i in spots], p['pool.o'], j)} AS g{j}" for j in spots) + " FROM pv)")
        out.append("graph AS (SELECT graph_id, " + ", ".join(f"greatest({_mul([f'g{i}' for i in spots], p['pool.w1'], j)} + {_num(p['pool.b1'][j])}, 0) AS g{j}" for j in spots) + " FROM pooled)")
        q = "value + score - avg(CASE WHEN valid THEN score END) OVER (PARTITION BY x.graph_id)" if config.dueling else "score"
        out.append(f"q AS (SELECT x.graph_id, x.node, {q} AS q FROM score x JOIN (SELECT graph_id, {layer([f'g{j}' for j in spots], 'value')} AS value FROM graph) v ON v.graph_id = x.graph_id)")
        both = [f"g.g{j}" for j in spots] + [f"x.h{j}" for j in spots]
        out.append(f"predicted AS (SELECT x.graph_id, {layer(both, 'reward')} AS reward FROM seen x JOIN graph g ON g.graph_id = x.graph_id WHERE x.node = {ACTION})")
    return ", ".join(out)


# --- queries --------------------------------------------------------------------------------------------------


def _encoder(name: str, **change) -> None:
    config = net.Config(**{f: getattr(BASE, f) for f in BASE.__dataclass_fields__} | change)
    sql = f"WITH {encoder_sql(config, 'actor')} SELECT graph_id, node, round(h0, 6) + 0.0 AS h0, round(h1, 6) + 0.0 AS h1 FROM h"
    _keep(name, lambda s, d: _columns(run(s, d, config, "actor", lambda p, b: net.encode(p, b, config).value), "h0", "h1"), sql)


_encoder("m_encoder")
_encoder("m_encoder_plain", task="none", state="none", skip="none")
_encoder("m_encoder_task", state="none", skip="none")
_encoder("m_encoder_state", task="none", skip="none")
_encoder("m_encoder_state_label", state="concat")
_encoder("m_encoder_plain_skip", skip="plain")
_encoder("m_encoder_no_skip", skip="none")
_encoder("m_encoder_separate", task="separate")
_encoder("m_encoder_three_layers", layers=3)


def m_task_embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The embedding of a task for every event: a product of one for what is left and one for the size."""
    p = net.init(BASE, "actor", 3)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            left, k = (batch.column(i).to_numpy(zero_copy_only=False) for i in (1, 2))
            got = np.asarray(net.embed_task(net.tensors(p), left, k).value)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(got[:, 0]), pa.array(got[:, 1])], [*batch.schema.names, "t0", "t1"])

    k = F.col("event_id") % SIZE + 1
    tasks = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", (F.col("user_id") % k + 1).cast("int").alias("remaining"), k.cast("int").alias("k"))
    found = tasks.mapInArrow(kernel, "event_id bigint, remaining int, k int, t0 double, t1 double")
    return found.select("event_id", "remaining", "k", *[(F.round(c, 6) + 0.0).alias(c) for c in ("t0", "t1")])


def _embed_sql() -> str:
    p = net.init(BASE, "actor", 3)
    parts = [f"round({_pick(p['task_left'], 'remaining', j)} * {_pick(p['task_size'], 'k', j)}, 6) AS t{j}" for j in range(2)]
    tasks = f"SELECT event_id, user_id % k + 1 AS remaining, k FROM (SELECT *, event_id % {SIZE} + 1 AS k FROM events)"
    return f"SELECT event_id, CAST(remaining AS INT) AS remaining, CAST(k AS INT) AS k, {', '.join(parts)} FROM ({tasks})"


_keep("m_task_embed", m_task_embed, _embed_sql())


def _actor(name: str, **change) -> None:
    config = net.Config(**{f: getattr(BASE, f) for f in BASE.__dataclass_fields__} | change)
    prob = "CASE WHEN valid THEN exp(score - m) / sum(CASE WHEN valid THEN exp(score - m) END) OVER (PARTITION BY graph_id) ELSE 0 END"
    sql = f"WITH {heads_sql(config, 'actor')} SELECT graph_id, node, round({prob}, 6) + 0.0 AS prob FROM (SELECT *, max(CASE WHEN valid THEN score END) OVER (PARTITION BY graph_id) AS m FROM score)"
    _keep(name, lambda s, d: _columns(run(s, d, config, "actor", lambda p, b: net.actor_probs(p, b, config).value), "prob"), sql)


_actor("h_actor")
_actor("h_actor_two_heads", heads=2)
_actor("h_actor_residual", residual=True)
_actor("h_actor_no_attention", attention=False)


def _critic(name: str, **change) -> None:
    config = net.Config(**{f: getattr(BASE, f) for f in BASE.__dataclass_fields__} | change)
    sql = f"WITH {heads_sql(config, 'critic')} SELECT graph_id, node, round(q, 6) + 0.0 AS q FROM q"
    _keep(name, lambda s, d: _columns(run(s, d, config, "critic", lambda p, b: net.q_values(p, b, config)[0].value), "q"), sql)


_critic("h_critic")
_critic("h_critic_two_heads", heads=2)
_critic("h_critic_mean_pooling", pooling="mean")
_critic("h_critic_no_dueling", dueling=False)


def h_pooling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole graph by attention of a learned query."""
    return _columns(run(spark, sf_dir, BASE, "critic", lambda p, b: net.pooled(p, net.encode(p, b, BASE), b, BASE).value, False), "g0", "g1", node=False)


_keep("h_pooling", h_pooling, f"WITH {heads_sql(BASE, 'critic')} SELECT graph_id, round(g0, 6) + 0.0 AS g0, round(g1, 6) + 0.0 AS g1 FROM graph")


def h_reward(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reward that the critic expects of picking one node."""
    return _columns(run(spark, sf_dir, BASE, "critic", lambda p, b: ag.reshape(net.q_values(p, b, BASE, np.array([ACTION]))[1], 1, 1).value, False), "reward", node=False)


_keep("h_reward", h_reward, f"WITH {heads_sql(BASE, 'critic')} SELECT graph_id, round(reward, 6) + 0.0 AS reward FROM predicted")
