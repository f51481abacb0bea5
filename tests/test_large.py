"""Findings about larger tables, each in small."""

from __future__ import annotations

import random
import re

import duckdb
import numpy as np
import pyarrow as pa
import pytest

from motif_spark.operators import census, learning, match, mni, process
from motif_spark.operators import graphs as G
from motif_spark.operators import vector as V
from motif_spark.plans import class_queries, network_queries, process_queries, relational, stream_queries, workload_queries


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_lateral_rows_are_ranked_by_price(spark, tmp_path):
    """Row numbers are ordered in their own window, not by a sort that a shuffle follows: that held on small tables only."""
    spark.range(10).selectExpr("id AS c_custkey").write.parquet(f"{tmp_path}/customer.parquet")
    orders = spark.range(2000).selectExpr("id AS o_orderkey", "id % 10 AS o_custkey", "CAST(id AS DOUBLE) AS o_totalprice")
    orders.repartition(8).write.parquet(f"{tmp_path}/orders.parquet")
    df = relational.QUERIES["op_join_lateral"](spark, str(tmp_path))
    assert re.search(r"row_number\(\) windowspecdefinition\(o_custkey#\d+L, o_totalprice#\d+ DESC", plan(df))
    assert "rangepartitioning" not in plan(df)
    assert {r.c_custkey: r.o_orderkey for r in df.collect()} == {c: 1990 + c for c in range(10)}


@pytest.mark.parametrize("name", ["x_small_code_k5", "x_two_stage_k3", "x_census_k1_9_session", "r_best"])
def test_census_rows_are_not_broadcast(name, spark, small):
    """Spark guesses their size from the files behind them, which gathered millions of rows on the driver."""
    assert "BroadcastExchange" not in plan(class_queries.QUERIES.get(name, process_queries.QUERIES.get(name))(spark, small))


def random_graph(rng, nodes: int, labels: int) -> tuple[list[int], list[list[int]]]:
    near = [set() for _ in range(nodes)]
    for _ in range(2 * nodes):
        a, b = rng.randrange(nodes), rng.randrange(nodes)
        if a != b:
            near[a].add(b)
            near[b].add(a)
    return [rng.randrange(labels) for _ in range(nodes)], [sorted(x) for x in near]


def test_codes_matched_together(monkeypatch):
    """Frequencies of all codes of a graph from one growth of each shape, beside those of one code after the other."""
    rng = random.Random(3)
    for nodes in range(5, 13):
        labels, nbrs = random_graph(rng, nodes, 3)
        row = {"nbrs": nbrs, "label_ids": labels, "unit": 0, "units": 1}
        for k, own, bits, _, _ in census._by_size(row, {3, 4, 5}, 10**9):
            codes = sorted(set(V.Classes(own, bits).texts(np.arange(len(bits)))))
            shared = match.matched(codes, labels, nbrs)
            monkeypatch.setattr(match, "SHARED", 10**9)
            assert match.matched(codes, labels, nbrs) == shared
            monkeypatch.undo()


def test_walks_at_once():
    """All walks of a graph, beside one after the other, dead ends included."""
    rng = random.Random(4)
    for nodes in range(1, 13):
        _, nbrs = random_graph(rng, nodes, 3)
        key, near = (nodes, 4, 2), census.masks(nbrs)
        one = {i: s for i in range(30) if (s := process.walk(near, 4, (*key, i))) is not None}
        sample, members = process.walks(V.adjacency(nbrs), 4, key, 30)
        assert dict(zip(sample.tolist(), map(tuple, members.tolist()))) == one


def test_rows_are_handed_on_in_blocks(spark, small, monkeypatch):
    """Results of the support miners do not hang on how many rows a task holds, nor on how many are made of a batch."""
    graphs = class_queries.session(spark, small)
    whole = mni.mni_census(graphs, [3]).collect()
    monkeypatch.setattr(mni, "HELD", 5)
    assert sorted(mni.mni_census(graphs, [3]).collect()) == sorted(whole)
    batch = pa.RecordBatch.from_arrays([pa.array(range(10))], ["x"])
    assert [r["x"] for r in G.rows_of([batch, batch], 3)] == [*range(10)] * 2


def test_padded_blocks_sum_to_the_gradient(spark, small, monkeypatch):
    query = workload_queries.QUERIES["l_critic_gradient"]
    whole = query(spark, small).first()
    monkeypatch.setattr(learning, "PADDED", 3)
    few = query(spark, small).first()
    assert few.transitions == whole.transitions and abs(few.length - whole.length) < 1e-9


@pytest.mark.parametrize("name", ["m_task_embed", "w9_worked_example"])
def test_tables_are_read_by_spark(name, spark, small):
    """Both made their rows up on the driver."""
    found = {**network_queries.QUERIES, **workload_queries.QUERIES}[name](spark, small)
    assert any("events.parquet" in f for f in found.inputFiles())


HEAP = "org.apache.spark.sql.execution.streaming.state.HDFSBackedStateStoreProvider"


def test_sessions_of_the_stream_are_written_to_files(spark, tmp_path):
    """They went to the driver; over files that are not in the order of time, all are there, those still open too."""
    times = [(1, "01 00:00:00"), (1, "01 06:00:00"), (2, "01 00:00:00"), (2, "01 05:59:59.999999"), (3, "20 00:00:00"), (3, "02 00:00:00"), (3, "02 10:00:00"), (3, "02 05:00:00"), (4, "30 23:59:59")]
    for i, (user, t) in enumerate(times):
        row = f"CAST({i} AS LONG) AS event_id, TIMESTAMP_NTZ '2024-01-{t}' AS ts, CAST({user} AS LONG) AS user_id, 'view' AS event_type, 1D AS value, '{{}}' AS props"
        spark.sql(f"SELECT {row}").write.mode("append").parquet(f"{tmp_path}/events.parquet")
    own = spark.conf.get(stream_queries.STATE)
    spark.conf.set(stream_queries.STATE, HEAP)
    df = stream_queries.QUERIES["s_stream_sessions"](spark, str(tmp_path))
    assert spark.conf.get(stream_queries.STATE) == HEAP
    spark.conf.set(stream_queries.STATE, own)
    assert df.inputFiles() and "LocalTableScan" not in plan(df)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    assert sorted(map(tuple, df.collect())) == sorted(con.execute(stream_queries.SQL["s_stream_sessions"]).fetchall())


def test_no_row_of_every_class_is_saved(spark, small, monkeypatch):
    """There are about as many classes as connected sets; how many have each frequency is enough, and no code is made for it."""
    kept = []
    monkeypatch.setattr(G, "saved", lambda df, saved=G.saved: kept.append((plan(df), saved(df))) or kept[-1][1])
    found = class_queries.QUERIES["x_census_k1_9_session"](spark, small)
    for text, df in kept:
        assert not df.groupBy("graph_id", "k", "freq").count().filter("count > 1").count()
        assert "ArrowEvalPython" not in text
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{small}/events.parquet'")
    assert sorted(map(tuple, found.collect())) == sorted(con.execute(class_queries.SQL["x_census_k1_9_session"]).fetchall())


def test_classes_of_whole_graphs(spark, small, monkeypatch):
    """Classes that leave their task once, beside those of one set after the other and those put together by a shuffle; of
    graphs with shared and with own structures, of wide labels, and of more sets than are shared."""
    rng = random.Random(6)
    own = [random_graph(rng, n, labels) for n, labels in ((1, 1), (2, 2), (7, 3), (9, 40), (11, 2))]
    star = ([rng.randrange(3) for _ in range(30)], [[*range(1, 30)], *[[0]] * 29])
    again = [([rng.randrange(3) for _ in own[3][0]], own[3][1]) for _ in range(3)]
    rows = [(900 + i, len(nbrs), sum(map(len, nbrs)) // 2, labels, nbrs) for i, (labels, nbrs) in enumerate([*own, star, *again])]
    session = class_queries.session(spark, small).filter("graph_id < 30")
    graphs = G.saved(session.unionByName(spark.createDataFrame(rows, session.schema)).coalesce(1))
    sizes = [1, 2, 4]
    want = {}
    for g in graphs.collect():
        near = census.masks(g.nbrs)
        for s in census.enumerate_sets(near, 4):
            if len(s) in sizes:
                code, turns, _, _ = census.canonical_of(*census.raw_key(s, g.label_ids, near))
                n, _, least = want.get((g.graph_id, len(s), code), (0, 0, sorted(s)))
                want[g.graph_id, len(s), code] = n + 1, turns, min(least, sorted(s))
    want = sorted((*key, *x) for key, x in want.items())
    columns = ["graph_id", "k", "code", "freq", "n_aut", "sample"]
    for _ in range(2):
        assert sorted(map(tuple, census.exact_census(graphs, sizes).select(columns).collect())) == want
    monkeypatch.setattr(census, "UNIT", 16)
    assert sorted(map(tuple, census.exact_census(graphs, sizes).select(columns).collect())) == want


def test_parts_of_a_whole_graph_are_summed():
    """A class that came in several parts is one row, with the least of its sets."""
    part = lambda *rows: ([r[0] for r in rows], *(np.array([r[i] for r in rows]) for i in (1, 2, 3)))
    parts = [(2, *part(("b", 3, 1, [1, 5]), ("a", 1, 2, [2, 4]))), (1, *part(("c", 1, 1, [0]))), (2, *part(("a", 4, 2, [2, 3]), ("d", 1, 1, [0, 9])))]
    found = {(k, *row) for k, codes, *x in census._summed(iter(parts)) for row in zip(codes, *(y.tolist() for y in x[:2]), map(tuple, x[2].tolist()))}
    assert found == {(1, "c", 1, 1, (0,)), (2, "a", 5, 2, (2, 3)), (2, "b", 3, 1, (1, 5)), (2, "d", 1, 1, (0, 9))}
