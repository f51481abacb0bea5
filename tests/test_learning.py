"""The decision process, the sampler, the network and its training."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from motif_spark.operators import autograd as ag
from motif_spark.operators import census as C
from motif_spark.operators import graphs as G
from motif_spark.operators import layers
from motif_spark.operators import learning as L
from motif_spark.operators import measures as A
from motif_spark.operators import network as net
from motif_spark.operators import process as P
from motif_spark.sources import suites as S

CONFIG = net.Config(labels=3, width=8, heads=2, layers=2)
GRAPHS = [([0, 1, 2, 1, 0], [[1, 2], [0, 3], [0, 4], [1], [2]]), ([0, 1, 1], [[1], [0, 2], [1]])]


@pytest.fixture(scope="module")
def folded(spark, small):
    return S.packed(spark, small, "session3", False).cache()


@pytest.fixture(scope="module")
def census(folded):
    return C.exact_census(folded, [3, 5]).cache()


def test_states_and_rewards(folded, spark):
    s = P.reset(folded, [3])
    assert s.select(F.size(P.valid_actions()).alias("a"), "n").filter("a != n").count() == 0
    s = P.step(s, F.lit(5))
    assert {tuple(r.a) for r in s.select(P.valid_actions().alias("a")).collect()} == {(3, 4, 6, 7)}
    assert s.select(P.task().alias("t")).first().t.remaining == 2 and s.filter(P.done()).count() == 0
    row = spark.createDataFrame([(4, 8, 10, 20, 3, True), (4, 8, 10, 20, 3, False)], "freq long, best long, n int, m int, k int, done boolean")
    got = {kind: [r.r for r in row.select(P.reward(kind).alias("r")).collect()] for kind in ("raw", "best", "density")}
    assert got["raw"] == [4.0, 0.0] and got["best"] == [0.5, 0.0]
    assert got["density"][0] == pytest.approx(4 / (3 * 2 * 20 / 9))
    assert L.terminal_reward("density", 4, 8, 10, 20, 3) == pytest.approx(got["density"][0])


def test_rollouts(folded, census):
    rolled = P.random_rollouts(folded, [3, 5], n_samples=20, seeds=2).cache()
    near = {r.graph_id: r.nbrs for r in folded.collect()}
    for r in rolled.collect():
        assert len(set(r.members)) == r.k
        assert all(any(x in near[r.graph_id][y] for y in r.members[:i]) for i, x in enumerate(r.members) if i)
    again = P.random_rollouts(folded.repartition(5), [3, 5], n_samples=20, seeds=2)
    assert rolled.exceptAll(again).count() == 0
    found = P.random_baseline(folded, rolled, census)
    ratios = A.approx_ratio(found, census)
    assert ratios.filter("ratio <= 0 or ratio > 1").count() == 0
    means = {r.k: r.ratio for r in A.average_over_seeds(ratios).collect()}
    assert means[3] > means[5]
    small = folded.orderBy("graph_id").limit(2)
    matched = P.random_baseline(small, rolled.join(small.select("graph_id"), "graph_id", "left_semi"))
    assert matched.join(found, ["graph_id", "k", "seed", "code"]).filter(matched.freq != found.freq).count() == 0
    assert A.avg_ratio(A.approx_ratio(C.most_frequent(census), census)).filter("ratio != 1 or hit_rate != 1").count() == 0


def test_sampled_enumeration(folded):
    full = P.sample_enumeration(folded, 3, [1.0, 1.0, 1.0]).agg(F.sum("freq")).first()[0]
    part = P.sample_enumeration(folded, 3, [1.0, 0.8, 0.8]).agg(F.sum("freq")).first()[0]
    assert full == 3640 and abs(part - 3640) < 400


def test_gradients_against_differences():
    batch = net.pad(GRAPHS, [[0], [1]], [3, 2], [4, 3])
    critic, actor = net.init(CONFIG, "critic", 1), net.init(CONFIG, "actor", 2)
    losses = [(critic, lambda p: L.critic_loss(p, batch, CONFIG, np.array([1, 0]), np.array([0.3, 0.4]), np.array([0.0, 1.0]))), (actor, lambda p: L.actor_loss(p, batch, CONFIG, np.ones((2, 5)) * np.arange(5), 0.1))]
    rng = np.random.default_rng(0)
    for params, loss in losses:
        got, _ = L.gradients(params, loss)
        for name, x in params.items():
            at = tuple(rng.integers(s) for s in x.shape)
            held, e = x[at], 1e-5
            x[at] = held + e
            up = L.gradients(params, loss)[1]
            x[at] = held - e
            down = L.gradients(params, loss)[1]
            x[at] = held
            assert (up - down) / (2 * e) == pytest.approx(got[name][at], abs=1e-6, rel=1e-5), name


def test_renumbering_moves_the_answers():
    p = [3, 0, 4, 1, 2]
    labels, nbrs = GRAPHS[0]
    moved = ([labels[i] for i in p], [sorted(p.index(j) for j in nbrs[i]) for i in p])
    actor = net.tensors(net.init(CONFIG, "actor", 3))
    a = net.actor_probs(actor, net.pad([GRAPHS[0]], [[0]], [3], [4]), CONFIG).value[0]
    b = net.actor_probs(actor, net.pad([moved], [[p.index(0)]], [3], [4]), CONFIG).value[0]
    assert np.allclose(a[p], b) and a.sum() == pytest.approx(1)
    assert set(np.flatnonzero(a)) == {1, 2}


def test_padding_changes_nothing():
    critic = net.tensors(net.init(CONFIG, "critic", 3))
    both = net.q_values(critic, net.pad(GRAPHS, [[0], [1]], [3, 2], [4, 3]), CONFIG, np.array([1, 0]))
    one = net.q_values(critic, net.pad(GRAPHS[1:], [[1]], [2], [3]), CONFIG, np.array([0]))
    assert np.allclose(both[0].value[1, :3], one[0].value[0]) and np.allclose(both[1].value[1], one[1].value[0])


def test_advantages_are_centred():
    batch = net.pad(GRAPHS, [[0], [1]], [3, 2], [4, 3])
    q = net.dueling(ag.tensor(np.array([1.0, 2.0])), ag.tensor(np.arange(10.0).reshape(2, 5)), batch.valid).value
    assert [q[i][batch.valid[i]].mean() for i in (0, 1)] == pytest.approx([1.0, 2.0])


def test_layer_equals_the_sum_over_edges(spark):
    """The per-node form, the per-edge form and the DataFrame form agree."""
    rng = np.random.default_rng(5)
    labels, nbrs = GRAPHS[0]
    h = rng.random((5, 2))
    w = {x: rng.normal(size=(2, 2)) for x in ("own", "centre", "near", "gate_c", "gate_n", "wide_c", "wide_n")} | {x: rng.random((2, 2)) + 0.5 for x in ("state_c", "state_n")}
    task, chosen = np.array([0.4, -0.2]), np.array([1, 0, 0, 0, 0])
    sig = lambda x: 1 / (1 + np.exp(-x))
    wide = {x: np.maximum(task, 0) @ w[x] for x in ("wide_c", "wide_n")}
    want = np.zeros_like(h)
    for i in range(5):
        c = h[i] * w["state_c"][chosen[i]]
        total = h[i] @ w["own"]
        for j in nbrs[i]:
            n = h[j] * w["state_n"][chosen[j]]
            total += (c @ w["centre"]) * sig((c * wide["wide_c"]) @ w["gate_c"]) - (n @ w["near"]) * sig((n * wide["wide_n"]) @ w["gate_n"])
        want[i] = np.maximum(total, 0)
    batch = net.pad([GRAPHS[0]], [[0]], [2], [3])
    names = {"l0.own": "own", "l0.centre": "centre", "l0.near": "near", "l0.gate_c": "gate_c", "l0.gate_n": "gate_n", "l0.state_c": "state_c", "l0.state_n": "state_n", "gate_centre": "wide_c", "gate_near": "wide_n"}
    params = net.tensors({a: w[b] for a, b in names.items()})
    got = net.layer(params, "l0.", ag.tensor(h[None]), batch, ag.tensor(task[None]), True).value[0]
    assert np.allclose(got, want)
    nodes = spark.createDataFrame([(0, i, h[i].tolist(), int(chosen[i])) for i in range(5)], "graph_id long, node int, h array<double>, selected int")
    edges = spark.createDataFrame([(0, i, j) for i in range(5) for j in nbrs[i] if i < j], "graph_id long, u int, v int")
    frame = layers.message_layer(nodes, edges, {k: x.tolist() for k, x in w.items()}, task.tolist()).orderBy("node").collect()
    assert np.allclose([r.h for r in frame], want)
    plain = net.layer(params, "l0.", ag.tensor(h[None]), batch, None, False).value
    assert np.allclose(plain, net.layer_plain(params, "l0.", ag.tensor(h[None]), batch.near).value)


def test_greedy_search(folded, census, spark, tmp_path):
    config = net.Config(labels=3, width=8, heads=2, layers=1)
    policy = L.Policy(config, net.init(config, "actor", 1))
    found = L.mine_all(folded, [3, 5], policy).collect()
    near = {r.graph_id: r.nbrs for r in folded.collect()}
    assert len(found) == 60
    for r in found:
        assert len(set(r.members)) == r.k and any(x in near[r.graph_id][r.members[0]] for x in r.members[1:]) and not r.dead
    folded.write.parquet(str(tmp_path / "graphs"))
    stored = spark.read.parquet(str(tmp_path / "graphs"))
    assert "Exchange" not in L.mine_all(stored, [3], policy)._jdf.queryExecution().executedPlan().toString()
    L.save(policy, spark, str(tmp_path / "policy"))
    again = L.load(spark, str(tmp_path / "policy"), config)
    assert all(np.allclose(x, policy.actor[k], atol=1e-6) for k, x in again.actor.items())
    assert L.mine_all(folded.limit(2), [3], policy, width=3).count() == 6
    nodes, edges = G.unpack_graphs(folded.orderBy("graph_id").limit(1))
    assert layers.greedy_large(nodes, edges, 3, lambda s: F.col("node") * 1.0)[1:] != []


def test_distributed_gradients_equal_local(spark):
    critic = net.init(CONFIG, "critic", 1)
    rows = [(g[0], g[1], s, left, k, a, t, r) for g, s, left, k, a, t, r in zip(GRAPHS, [[0], [1]], [3, 2], [4, 3], [1, 0], [0.3, 0.4], [0.0, 1.0])]
    df = spark.createDataFrame(rows, "label_ids array<int>, nbrs array<array<int>>, selected array<int>, left int, k int, action int, target double, reward double").repartition(2)
    batch = net.pad(GRAPHS, [[0], [1]], [3, 2], [4, 3])
    want, _ = L.gradients(critic, lambda p: L.critic_loss(p, batch, CONFIG, np.array([1, 0]), np.array([0.3, 0.4]), np.array([0.0, 1.0])))
    got = L.distributed_gradients(df, critic, CONFIG)
    assert all(np.allclose(got[k], want[k]) for k in want)


def test_training_runs_and_repeats(folded, census):
    how = L.Training(sizes=(3,), epochs=6, episodes=8, updates=1, batch=16, check_every=3)
    config = net.Config(labels=3, width=8, heads=2, layers=1, k_max=5)
    a, b = (L.train(folded.limit(6), census, config, how) for _ in range(2))
    assert a.curve == b.curve and len(a.curve) == 2 and a.samples == 48
    for name, c in L.variants(config).items():
        got = L.train(folded.limit(4), census, c, L.Training(sizes=(3,), epochs=3, episodes=6, updates=1, batch=12, check_every=3, reward="raw"))
        assert 0 <= got.curve[-1]["k3"] <= 1, name


def test_measures():
    model = A.cost_model(10, 12, 4, 3)
    assert model["search"] == 3 * model["step"] and model["encoder"] == 10 * 16 + 12 * 4
    assert A.slope([1, 2, 3], [2.0, 4.0, 6.0]) == pytest.approx(2) and A.speedup(10, 2) == 5
