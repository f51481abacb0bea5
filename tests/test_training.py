"""Training in Spark: rewards from lessons, averaging, repeatability, and that it learns."""

from __future__ import annotations

import numpy as np
import pytest

from motif_spark.operators import census as C
from motif_spark.operators import learning as L
from motif_spark.operators import network as net
from motif_spark.operators import training as T
from motif_spark.plans.class_queries import session

CONFIG = net.Config(labels=3, width=16, heads=2, layers=2, k_max=4, residual=True)


@pytest.fixture(scope="module")
def folded(spark, small):
    return session(spark, small, True).cache()


@pytest.fixture(scope="module")
def lessons(folded):
    return T.lessons(folded, C.exact_census(folded, [3, 4]), 3)


def test_rewards_are_those_of_the_census(folded, lessons, spark):
    census = {(r.graph_id, r.k, r.code): r.freq for r in C.exact_census(folded, [3, 4]).collect()}
    rows = lessons.collect()
    school = T.School(lessons.toArrow().to_batches(), 1000)
    assert len(school.graphs) == len(rows) == 30
    by_graph = {(tuple(g[0]), str(g[1])): i for i, g in enumerate(school.graphs)}
    for r in rows:
        at = by_graph[tuple(r.label_ids), str(r.nbrs)]
        for nodes in ([0, 1, 2], [3, 4, 6], [0, 2, 4, 5]):
            code = C.code_of(nodes, r.label_ids, r.nbrs)
            assert school.frequency(at, nodes) == census[r.graph_id, len(nodes), code]
            best = max(f for (g, k, _), f in census.items() if g == r.graph_id and k == len(nodes))
            assert school.best[at][len(nodes)] == best
        assert school.frequency(at, [0, 1, 9]) == 0  # not connected, so in no census
    picked = np.array([[0, 1, 2], [0, 1, -1]])
    reward = school.rewards("best", np.array([0, 0]), np.array([3, 3]), picked)
    assert 0 < reward[0] <= 1 and reward[1] == 0


def test_weights_are_averaged_by_a_tree(spark, monkeypatch):
    monkeypatch.setattr(T, "FAN", 3)
    rng = np.random.default_rng(1)
    vectors, weights = rng.normal(size=(23, 5)).astype(np.float32), rng.integers(1, 9, 23).astype(float)
    rows = [(i, float(w), 10 * i, float(i), v.tobytes()) for i, (v, w) in enumerate(zip(vectors, weights))]
    got = T._averaged(spark.createDataFrame(rows, T.STATE).repartition(4), 23)
    assert np.allclose(got["vector"], (vectors * weights[:, None]).sum(0) / weights.sum(), atol=1e-5)
    assert got["samples"] == sum(10 * i for i in range(23)) and got["reward"] == pytest.approx((np.arange(23) * weights).sum() / weights.sum())


def test_training_repeats_and_learns(lessons):
    how = T.Rounds(sizes=(3, 4), rounds=8, steps=6, groups=8, per=8, rate=3e-3, check_every=4)
    a, b = (T.train_rounds(lessons, CONFIG, how, {"valid": lessons}) for _ in range(2))
    assert all(np.allclose(x, b.actor[k], atol=1e-4) for k, x in a.actor.items())
    assert a.samples == 8 * 6 * 64 * 3 and [c["epoch"] for c in a.curve] == [4, 8]
    fresh = L.Policy(CONFIG, net.init(CONFIG, "actor", how.seed))
    mean = lambda p: np.mean([r.ratio for r in T.mean_ratios(lessons, p, (3, 4)).collect()])
    assert mean(a) > mean(fresh) + 0.1


def test_search_of_batches_equals_search_of_one(lessons):
    school = T.School(lessons.toArrow().to_batches(), 1000)
    actor = net.init(CONFIG, "actor", 3)
    rows, sizes = np.arange(30), np.full(30, 4)
    together = L.walks(actor, CONFIG, school.pool, rows, sizes)
    alone = [L.rollout(actor, CONFIG, [school.graphs[i]], [4])[0] for i in range(30)]
    assert together.tolist() == alone
