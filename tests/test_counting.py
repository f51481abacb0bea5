"""Counts, codes, supports and matching against worked values and brute force."""

from __future__ import annotations

import random
from itertools import combinations, permutations
from math import comb

import pytest
from pyspark.sql import functions as F

from motif_spark.operators import census as C
from motif_spark.operators import graphs as G
from motif_spark.operators import match as M
from motif_spark.operators import mni as N
from motif_spark.operators.canonical import automorphisms, canonical, canonical_of, code_text, is_isomorphic, small_code
from motif_spark.sources import suites as S


@pytest.fixture(scope="module")
def worked(spark):
    return G.pack_graphs(*S.worked(spark)).cache()


@pytest.fixture(scope="module")
def session(spark, small):
    return S.packed(spark, small, "session", False).cache()


def random_graph(rng, n, p, labels):
    adj = [0] * n
    for i in range(n):
        for j in range(i + 1, n):
            if rng.random() < p:
                adj[i] |= 1 << j
                adj[j] |= 1 << i
    return [rng.randrange(labels) for _ in range(n)], adj


def connected(s, adj):
    seen, todo = {s[0]}, [s[0]]
    while todo:
        x = todo.pop()
        for y in s:
            if y not in seen and adj[x] >> y & 1:
                seen.add(y)
                todo.append(y)
    return len(seen) == len(s)


def test_worked_example(worked):
    census = C.exact_census(worked, [2, 3, 4, 5, 6]).collect()
    for k, sets, classes, best in ((2, 8, 2, 5), (3, 8, 4, 4), (4, 9, 4, 4), (5, 9, 5, 2), (6, 7, 5, 2)):
        rows = [r for r in census if r.k == k]
        assert (sum(r.freq for r in rows), len(rows), max(r.freq for r in rows)) == (sets, classes, best)
    support = {r.k: (r.freq, r.mni) for r in N.baseline(N.mni_census(worked, [2, 3, 4, 5, 6])).collect()}
    assert support == {2: (3, 3), 3: (1, 3), 4: (4, 1), 5: (2, 1), 6: (2, 1)}
    assert {r.k: (r.freq, r.mni) for r in N.baseline(N.descent(worked, [2, 3, 4, 5, 6], 0.9)).collect()} == support
    triangle = next(r for r in census if r.k == 3 and r.code == "0.0.0:7")
    assert triangle.freq == 1 and triangle.n_aut == 6
    path = canonical_of((0, 1, 0), 0b101)[0]
    matches = M.match_pattern(worked, path).cache()
    assert sorted({tuple(sorted(r.mapping)) for r in matches.collect()}) == [(2, 3, 4), (2, 4, 5), (3, 4, 5), (5, 6, 7)]
    assert N.mni(matches).first().mni == 2 and M.frequency(worked, path).first().freq == 4
    assert M.match_pattern(worked, "0.0.0:7").count() == 6
    assert {r.code: r.mappings for r in M.mapping_count(C.exact_census(worked, [3])).collect()}[path] == 8


def test_session_figures(session):
    census = C.exact_census(session, [3, 4, 5]).cache()
    assert [tuple(r) for r in census.groupBy("k").agg(F.sum("freq"), F.count("*"), F.count_distinct("code")).orderBy("k").collect()] == [(3, 3640, 1862, 110), (4, 6920, 5005, 899), (5, 13120, 10534, 5405)]
    assert [r.s for r in C.most_frequent(census).groupBy("k").agg(F.sum("freq").alias("s")).orderBy("k").collect()] == [187, 170, 159]
    assert C.most_frequent(census, ties=True).count() >= C.most_frequent(census).count()
    space = {r.k: r.s for r in C.search_space(session, [3, 5]).groupBy("k").agg(F.sum("sets").alias("s")).collect()}
    assert space == {3: 3640, 5: 13120}


def test_engines_agree(session, spark, small):
    rows, levels = C.enumerate_rows(session, 4), C.enumerate_levels(*S.session(spark, small), 4)
    assert rows.exceptAll(levels).count() == 0 and levels.exceptAll(rows).count() == 0
    few = session.orderBy("graph_id").limit(4)
    truth = C.exact_census(few, [3])
    two = C.two_stage(few, 3)
    assert two.join(truth, ["graph_id", "k", "code"]).filter(two.freq != truth.freq).count() == 0 and two.count() == truth.count()
    coded = C.code_sets(C.enumerate_rows(few, 3), few).groupBy("graph_id", "code").count()
    assert {tuple(r) for r in coded.collect()} == {(r.graph_id, r.code, r.freq) for r in truth.collect()}
    native = C.raw_counts(few, [3]).select("graph_id", small_code("labels", "bits", 3).alias("code"), "cnt").groupBy("graph_id", "code").agg(F.sum("cnt"))
    assert sorted(r[2] for r in native.collect()) == sorted(r.freq for r in truth.collect())


def test_enumeration_on_random_graphs():
    rng = random.Random(1)
    for _ in range(25):
        n = rng.randrange(1, 10)
        _, adj = random_graph(rng, n, rng.random(), 2)
        got = [tuple(sorted(s)) for s in C.enumerate_sets(adj, 5)]
        want = [s for k in range(1, 6) for s in combinations(range(n), k) if connected(s, adj)]
        assert len(got) == len(set(got)) and set(got) == set(want)


def test_closed_forms():
    star = [sum(1 << j for j in range(1, 9))] + [1] * 8
    path = [(1 << i - 1 if i else 0) | (1 << i + 1 if i < 8 else 0) for i in range(9)]
    clique = [(1 << 7) - 1 ^ 1 << i for i in range(7)]
    count = lambda adj, k: sum(len(s) == k for s in C.enumerate_sets(adj, k))
    for k in range(2, 6):
        assert (count(star, k), count(path, k), count(clique, k)) == (comb(8, k - 1), 9 - k + 1, comb(7, k))
    labels, _, n_aut, _, orbit = canonical((0,) * 9, star)
    assert n_aut == 40320 and len(set(orbit)) == 2 and labels == (0,) * 9
    with pytest.raises(C.SearchSpaceTooLarge):
        list(C.enumerate_sets(clique, 7, guard=10))


def test_codes_on_all_small_graphs():
    """Equal codes exactly for isomorphic graphs, with the automorphisms counted, up to four nodes and two labels."""
    for k in (1, 2, 3, 4):
        forms = {}
        for labels in ((0,) * k, (0, 1, 0, 1)[:k]):
            for bits in range(1 << k * (k - 1) // 2):
                pairs = list(combinations(range(k), 2))
                adj = [0] * k
                for b, (i, j) in enumerate(pairs):
                    if bits >> (len(pairs) - 1 - b) & 1:
                        adj[i] |= 1 << j
                        adj[j] |= 1 << i
                images = [(tuple(labels[p[i]] for i in range(k)), tuple(adj[p[i]] >> p[j] & 1 for i, j in pairs)) for p in permutations(range(k))]
                code = canonical_of(labels, bits)
                assert code[1] == images.count((labels, tuple(adj[i] >> j & 1 for i, j in pairs)))
                assert forms.setdefault(code[0], min(images)) == min(images)
        assert len(set(forms.values())) == len(forms)


def test_codes_survive_renumbering():
    rng = random.Random(2)
    for _ in range(60):
        k = rng.randrange(5, 9)
        labels, adj = random_graph(rng, k, 0.5, 2)
        p = rng.sample(range(k), k)
        other = [sum(1 << p.index(j) for j in range(k) if adj[x] >> j & 1) for x in p]
        a, b = canonical(tuple(labels), adj), canonical(tuple(labels[x] for x in p), other)
        assert a[:3] == b[:3]
    six = [0b110110 for _ in range(6)]
    k33, prism = [0b111000] * 3 + [0b000111] * 3, [0b001110, 0b010101, 0b100011, 0b110001, 0b101010, 0b011100]
    assert canonical((0,) * 6, k33)[1] != canonical((0,) * 6, prism)[1] and six
    assert is_isomorphic(code_text((0, 1), 1), code_text((1, 0), 1))


def test_automorphism_table(spark):
    got = {r.code: r.n_aut for r in automorphisms(spark.createDataFrame([("0.0.0:7",), ("0.0.1:3",)], "code string")).collect()}
    assert got["0.0.0:7"] == 6


def test_support_shrinks_as_patterns_grow(session):
    few = session.orderBy("graph_id").limit(3)
    census = N.mni_census(few, [1, 2, 3, 4]).collect()
    bound = {r.graph_id: r.bound for r in N.upper_bound(few).collect()}
    top = {}
    for r in census:
        assert r.mni <= bound[r.graph_id] and r.mni <= r.freq * 4
        top[r.graph_id, r.k] = max(top.get((r.graph_id, r.k), 0), r.mni)
    assert all(top[g, k] <= top[g, k - 1] for g, k in top if k > 1)
    mined = {(r.graph_id, r.k, r.code): (r.freq, r.mni) for r in N.mine(few, 4, 3).collect()}
    assert mined == {(r.graph_id, r.k, r.code): (r.freq, r.mni) for r in census if r.mni >= 3}


def test_plain_support(worked):
    got = {(r.k, r.code): r.mni for r in N.mine(worked, 3, 1, induced=False).collect()}
    assert got[2, "0.0:1"] == 3  # nodes 1, 2 and 3 of the triangle are all edges between two A
    assert got[3, "0.0.0:7"] == 3 and any(k == 3 for k, _ in got)


def test_graph_tools(spark, session, small):
    nodes, edges = G.unpack_graphs(session)
    again = G.pack_graphs(nodes, edges)
    assert again.exceptAll(session.select(*again.columns)).count() == 0
    moved = G.permute_graph(session, 3)
    a, b = (C.exact_census(x, [3]).select("graph_id", "code", "freq") for x in (session, moved))
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0
    split = G.split_targets(session, 0.8, 0.1)
    assert {r.split for r in split.collect()} <= {"train", "valid", "test"}
    assert split.exceptAll(G.split_targets(session.repartition(7), 0.8, 0.1)).count() == 0
    comp = G.connected_components(nodes, edges)
    assert comp.filter("comp != 0").count() == 0 and comp.count() == nodes.count()
    whole, ends = G.union_graphs(*S.session(spark, small))
    assert (whole.count(), ends.count()) == (1000, 1910)
    stats = G.graph_stats(G.pack_graphs(*S.worked(spark))).first()
    assert (stats.n, stats.m, stats.max_degree) == (8, 8, 3)


def test_odd_graphs(spark):
    nodes = spark.createDataFrame([(1, 0, "A"), (2, 0, "A"), (2, 1, "B"), (3, 0, "A"), (3, 1, "A"), (3, 2, "A")], "graph_id long, node int, label string")
    edges = spark.createDataFrame([(3, 0, 1)], "graph_id long, u int, v int")
    g = G.pack_graphs(nodes, edges)
    assert {(r.graph_id, r.n, r.m) for r in g.collect()} == {(1, 1, 0), (2, 2, 0), (3, 3, 1)}
    assert {(r.graph_id, r.k, r.sets) for r in C.search_space(g, [1, 2, 3]).collect()} == {(1, 1, 1), (2, 1, 2), (3, 1, 3), (3, 2, 1)}
    assert G.filter_targets(g, 0, 9).count() == 1
    assert C.exact_census(g.filter("n > 99"), [3]).count() == 0
    assert G.normalize_edges(spark.createDataFrame([(1, 2, 1), (1, 1, 2), (1, 3, 3)], "graph_id long, u int, v int")).count() == 1
    pieces = G.split_components(nodes.withColumn("ext_id", F.col("node").cast("long")), edges)[0]
    assert pieces.select("graph_id").distinct().count() == 5
