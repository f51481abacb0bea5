"""Classes read off shared structures, and the operators that hand on the best of a graph alone."""

from __future__ import annotations

import random

import numpy as np
import pytest

from motif_spark.operators import census, match, mni, process, shared
from motif_spark.operators import graphs as G
from motif_spark.operators import vector as V
from motif_spark.plans import class_queries, relational, workload_queries

from .test_large import random_graph


@pytest.fixture
def forget():
    shared._met.clear()
    shared._plans.clear()


@pytest.mark.parametrize("nodes", [1, 2, 5, 8, 12])
def test_levels_of_a_shared_structure(nodes, forget):
    """The second graph of a structure is read off; its rows are those that its own sets give."""
    rng = random.Random(nodes)
    _, nbrs = random_graph(rng, nodes, 3)
    labels = [rng.randrange(3) for _ in range(nodes)]
    row = {"nbrs": nbrs, "label_ids": labels, "unit": 0, "units": 1}
    assert shared.levels(labels[::-1], nbrs, {1, 2, 3, 4, 5}) is None
    got = shared.levels(labels, nbrs, {1, 2, 3, 4, 5})
    for level in mni._levels(row, {1, 2, 3, 4, 5}, 10**9):
        own = got[level.size]
        everything = np.arange(len(own.first))
        assert sorted(own.rows(1, everything)) == sorted(level.rows(1, np.arange(len(level.first))))
        texts = own.texts(everything)
        assert [own.find(c) for c in texts] == everything.tolist()
        assert (own.class_of(own.plan.sets) == own.of).all()
        whole = {}
        for _, at, bits, _, sample in census._by_size(row, {level.size}, 10**9):
            kinds = V.Classes(at, bits)
            for code, turns, s in zip(kinds.texts(np.arange(len(bits))), kinds.automorphisms.tolist(), map(tuple, sample.tolist())):
                whole[code] = (turns, min(s, whole.get(code, (0, s))[1]))
        assert whole == dict(zip(texts, zip(own.automorphisms().tolist(), map(tuple, own.sample.tolist()))))


def test_wide_shapes_are_not_shared(forget):
    """A star's places can change in too many ways."""
    star = [list(range(1, 30)), *[[0]] * 29]
    assert shared.levels([0] * 30, star, {6}) is None and shared.levels([0] * 30, star, {6}) is None


@pytest.mark.parametrize("sizes", [[3], [2, 4, 5]])
def test_best_of_each_graph(spark, small, sizes, monkeypatch):
    """The best classes alone, beside those picked from whole censuses; also where no graph is one unit of work."""
    graphs = G.saved(class_queries.session(spark, small))
    whole = census.exact_census(graphs, sizes)
    for then in ("code", "sample"):
        assert sorted(census.best_census(graphs, sizes, then).collect()) == sorted(census.most_frequent(whole, then=then).collect())
    want = sorted(mni.baseline(mni.mni_census(graphs, sizes)).collect())
    assert sorted(mni.best_support(graphs, sizes).collect()) == want
    monkeypatch.setattr(census, "UNIT", 16)
    monkeypatch.setattr(mni, "WHOLE", 0)
    assert sorted(census.best_census(graphs, sizes).collect()) == sorted(census.most_frequent(whole).collect())
    assert sorted(mni.best_support(graphs, sizes).collect()) == want


def test_best_of_samples(spark, small, monkeypatch):
    """The best drawn class of every seed, from shared structures and from those met once, beside drawing, counting and
    picking by joins."""
    rng = random.Random(7)
    alone = [random_graph(rng, n, 3) for n in range(3, 12)]
    rows = [(900 + i, len(nbrs), sum(map(len, nbrs)) // 2, labels, nbrs) for i, (labels, nbrs) in enumerate(alone)]
    session = class_queries.session(spark, small).filter("graph_id < 40")
    graphs = G.saved(session.unionByName(spark.createDataFrame(rows, session.schema)))
    want = sorted(process.random_baseline(graphs, process.random_rollouts(graphs, [3, 5], 20, 3)).collect())
    assert sorted(process.random_best(graphs, [3, 5], 20, 3).collect()) == want
    monkeypatch.setattr(census, "UNIT", 16)
    assert sorted(process.random_best(graphs, [3, 5], 20, 3).collect()) == want


@pytest.mark.parametrize("name", ["w2_accuracy_session", "w2_accuracy_session3", "l_ratio"])
def test_no_census_of_all_classes_is_saved(spark, small, name, monkeypatch):
    """These only need the best class of a graph and the frequencies of classes that a method found."""
    kept = []
    monkeypatch.setattr(G, "saved", lambda df, saved=G.saved: kept.append(saved(df)) or kept[-1])
    {**class_queries.QUERIES, **workload_queries.QUERIES}[name](spark, small)
    for df in kept:
        if {"graph_id", "k"} <= set(df.columns):
            assert not df.groupBy("graph_id", "k").count().filter("count > 1").count()


def test_theta_join_meets_few_rows(spark, tmp_path):
    """Pairs as a plain join has them; rows that no row of their type can match are left out before the join."""
    rows = [(i, f"t{i % 3}", (i * 7) % 11, float(300 * (i % 5)) if i % 3 else 900.0 + i) for i in range(120)] + [(200, "t1", None, 5000.0), (201, None, 1, 9e9), (202, "t2", 3, None)]
    parts = spark.createDataFrame(rows, "p_partkey long, p_type string, p_size int, p_retailprice double")
    parts.write.parquet(f"{tmp_path}/part.parquet")
    want = [(a[0], b[0]) for a in rows for b in rows if None not in (*a, *b) and a[1] == b[1] and a[2] < b[2] and a[3] > b[3] + 500]
    df = relational.QUERIES["op_join_theta"](spark, str(tmp_path))
    assert sorted(map(tuple, df.collect())) == sorted(want)
    assert "low" in df._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("whole", [0, 6, None])
def test_components_by_task_and_by_stars(spark, whole):
    """Graphs up to a number of edges are settled by a task each, the others by stars, with the same components."""
    rng = random.Random(5)
    nodes, edges, want = [], [], set()
    for graph in range(8):
        _, nbrs = random_graph(rng, 2 + 3 * graph, 1)
        nbrs = [[y for y in row if rng.random() < 0.5] for row in nbrs]
        ends = [(x, y) for x, row in enumerate(nbrs) for y in row]
        least = list(range(len(nbrs)))
        for _ in nbrs:
            for x, y in ends:
                least[x] = least[y] = min(least[x], least[y])
        nodes += [(graph, x) for x in range(len(nbrs))]
        edges += [(graph, x, y) for x, y in ends]
        want |= {(graph, x, c) for x, c in enumerate(least)}
    found = G.connected_components(spark.createDataFrame(nodes, "graph_id long, node int"), spark.createDataFrame(edges, "graph_id long, u int, v int"), whole=whole)
    assert {tuple(r) for r in found.collect()} == want


def test_matches_of_a_shared_structure():
    """Frequencies do not hang on whether a shape was grown in an earlier graph of the same neighbour lists."""
    rng = random.Random(9)
    _, nbrs = random_graph(rng, 12, 2)
    match._grown.clear()
    for _ in range(4):
        labels = [rng.randrange(2) for _ in nbrs]
        row = {"nbrs": nbrs, "label_ids": labels, "unit": 0, "units": 1}
        for k, own, bits, cnt, _ in census._by_size(row, {3, 4}, 10**9):
            want = {}
            for code, n in zip(V.Classes(own, bits).texts(np.arange(len(bits))), cnt.tolist()):
                want[code] = want.get(code, 0) + n
            assert match.matched(list(want), labels, nbrs) == list(want.values())
    assert any(x is not None and x.shape[1] for x in match._grown.values())
