"""Message layers as DataFrame operations, for graphs too large for one row, and their heads."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def dense(h: Column, w: list[list[float]]) -> Column:
    """A row vector times a matrix."""
    cols = len(w[0])
    return F.array(*[sum((F.element_at(h, i + 1) * float(row[j]) for i, row in enumerate(w)), F.lit(0.0)) for j in range(cols)])


def relu(h: Column) -> Column:
    return F.transform(h, lambda x: F.greatest(x, F.lit(0.0)))


def sigmoid(h: Column) -> Column:
    return F.transform(h, lambda x: 1 / (1 + F.exp(-x)))


def times(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("graph_id", F.col("u").alias("node"), F.col("v").alias("to")).unionByName(edges.select("graph_id", F.col("v").alias("node"), F.col("u").alias("to")))


def message_layer(nodes: DataFrame, edges: DataFrame, weights: dict, task: list[float] | None = None) -> DataFrame:
    """graph_id, node, h after one layer. nodes: graph_id, node, h (array), selected (0 or 1).

    All matrix work is done on nodes; each edge carries one vector into a sum by place, which combines before
    the shuffle. weights: own, centre, near, and optionally state_c, state_n (two rows each), gate_c, gate_n,
    wide_c, wide_n for the task's gates.
    """
    d = len(weights["own"][0])
    state = lambda rows: F.when(F.col("selected") == 1, F.array(*[F.lit(float(x)) for x in rows[1]])).otherwise(F.array(*[F.lit(float(x)) for x in rows[0]]))
    c = times(F.col("h"), state(weights["state_c"])) if "state_c" in weights else F.col("h")
    n = times(F.col("h"), state(weights["state_n"])) if "state_n" in weights else F.col("h")
    df = nodes.withColumns({"_c": c, "_n": n})
    u, v = dense(F.col("_c"), weights["centre"]), dense(F.col("_n"), weights["near"])
    if task is not None:
        lit = lambda w: F.array(*[F.lit(float(sum(max(t, 0.0) * w[i][j] for i, t in enumerate(task)))) for j in range(d)])
        u = times(u, sigmoid(dense(times(F.col("_c"), lit(weights["wide_c"])), weights["gate_c"])))
        v = times(v, sigmoid(dense(times(F.col("_n"), lit(weights["wide_n"])), weights["gate_n"])))
    df = df.withColumns({"_own": dense(F.col("h"), weights["own"]), "_u": u, "_v": v})
    sent = df.select("graph_id", F.col("node").alias("to"), *[F.col("_v")[j].alias(f"v{j}") for j in range(d)])
    got = both_ways(edges).join(sent, ["graph_id", "to"]).groupBy("graph_id", "node").agg(F.count(F.lit(1)).alias("_deg"), *[F.sum(f"v{j}").alias(f"s{j}") for j in range(d)])
    whole = df.join(got, ["graph_id", "node"], "left")
    value = [F.element_at("_own", j + 1) + F.coalesce(F.col("_deg") * F.element_at("_u", j + 1) - F.col(f"s{j}"), F.lit(0.0)) for j in range(d)]
    return whole.select("graph_id", "node", F.array(*[F.greatest(x, F.lit(0.0)) for x in value]).alias("h"), "selected")


def gated_skip(first: Column, last: Column, gate: list[float]) -> Column:
    """First representation plus the last scaled by a task gate."""
    return F.zip_with(first, times(last, sigmoid(times(last, F.array(*[F.lit(float(x)) for x in gate])))), lambda a, b: a + b)


def masked_softmax(rows: DataFrame) -> DataFrame:
    """Adds prob to graph_id, node, score, valid: none outside the valid nodes; a graph's largest score is taken off."""
    w = Window.partitionBy("graph_id")
    held = F.when(F.col("valid"), F.col("score"))
    df = rows.withColumn("_e", F.when(F.col("valid"), F.exp(F.col("score") - F.max(held).over(w))).otherwise(0.0))
    return df.withColumn("prob", F.col("_e") / F.sum("_e").over(w)).drop("_e")


def dueling(rows: DataFrame) -> DataFrame:
    """Adds q to graph_id, node, value, advantage, valid."""
    mean = F.avg(F.when(F.col("valid"), F.col("advantage"))).over(Window.partitionBy("graph_id"))
    return rows.withColumn("q", F.when(F.col("valid"), F.col("value") + F.col("advantage") - mean))


def greedy_large(nodes: DataFrame, edges: DataFrame, k: int, score) -> list[int]:
    """Greedy search in one large graph: at each step score(nodes) gives a score column, the best valid node is taken.

    Only the picked nodes are on the driver; equal scores go to the smallest node.
    """
    from .graphs import saved

    picked: list[int] = []
    held = saved(nodes)
    ends = saved(both_ways(edges))
    for _ in range(k):
        state = held.withColumn("selected", F.col("node").isin(picked).cast("int") if picked else F.lit(0))
        valid = state.filter("selected = 0")
        if picked:
            valid = valid.join(ends.filter(F.col("to").isin(picked)).select("node").distinct(), "node", "left_semi")
        top = valid.withColumn("_s", score(state)).orderBy(F.desc("_s"), "node").select("node").first()
        if top is None:
            break
        picked.append(top["node"])
    return picked
