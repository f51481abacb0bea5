"""SQL counterparts, sources, functions, streams and plans."""

from __future__ import annotations

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from motif_spark.functions.register import register_all, vec_sum_native
from motif_spark.operators import census as C
from motif_spark.operators import graphs as G
from motif_spark.plans import MODULES, graph_queries, relational
from motif_spark.sources import suites as S
from motif_spark.sources import textgraph
from motif_spark.streaming import motifs

OWN = {name: f for m in MODULES for name, f in m.QUERIES.items()}
STATEMENTS = {name: text for m in MODULES for name, text in m.SQL.items()}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def rows(pdf):
    cols = sorted(pdf.columns)
    norm = lambda x: round(float(x), 5) if isinstance(x, (float, np.floating)) else x
    clean = pdf[cols].astype(object).where(pdf[cols].notna(), None)
    return cols, sorted((tuple(str(norm(float(x) if isinstance(x, (int, np.integer)) and not isinstance(x, bool) else x)) for x in r) for r in clean.itertuples(index=False)))


@pytest.mark.parametrize("name", STATEMENTS)
def test_sql_says_the_same(name, spark, small, duck):
    assert rows(OWN[name](spark, small).toPandas()) == rows(duck.sql(STATEMENTS[name]).df())


#: What the columns of queries without a statement must hold, row by row.
HOLDS = {
    "g_dom_stats": lambda r: r.m == r.n - 1 and 0 < r.density < 1 and 1 <= r.max_degree < r.n,
    "g_similar_stats": lambda r: 10 < r.n < 500 and r.m >= 3 * r.n / 2 and r.max_degree >= 3,
    "r_enumeration_estimate": lambda r: r.sets >= 0,
    "w1_dataset_table": lambda r: r.graphs > 0 and 10 < r.mean_n < 500 and r.mean_m >= r.mean_n - 1,
    "w4_mni_disagreement_purchase": lambda r: r.k == 3 and 0 <= r.worse <= r.graphs,
    "l_mine_session": lambda r: r.members.count(",") == r.k - 1 and r.code.count(".") == r.k - 1,
    "l_ratio": lambda r: 0 < r.ratio <= 1 and 0 <= r.hit_rate <= r.ratio and r.graphs > 0,
    "l_train": lambda r: 0 < r.ratio <= 1 and r.samples == r.epoch * 4 * 64 * 4 and r.k in (3, 4),
    "l_critic_gradient": lambda r: r.transitions > 0 and r.length > 0,
    "w5_reward_settings": lambda r: 0 < r.ratio <= r.max_over_training + 1e-9 <= 1 + 1e-9 and r.setting in ("raw", "best", "density"),
    "w7_ablations": lambda r: 0 <= r.ratio <= r.max_over_training + 1e-9 <= 1 + 1e-9 and r.graphs > 0,
    "op_agg_approx": lambda r: r.orders > 0 and r.parts > 0,
}


@pytest.mark.parametrize("name", [n for n in OWN if n not in STATEMENTS])
def test_queries_without_sql(name, spark, small):
    found = OWN[name](spark, small).collect()
    assert found and all(HOLDS[name](r) for r in found), found[:3]


def test_entry(spark):
    assert entry.entry(spark).count() == 30
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_text_collections(spark, tmp_path):
    nodes, edges = S.worked(spark)
    textgraph.write_collection(nodes, edges, str(tmp_path), "toy")
    back = G.pack_graphs(*textgraph.read_collection(spark, str(tmp_path), "toy"))
    a, b = (C.exact_census(x, [3]).select("code", "freq") for x in (G.pack_graphs(nodes, edges), back))
    assert a.exceptAll(b).count() == 0 and a.count() == b.count()
    assert "0 -- 1;" in textgraph.graphviz(back).first().dot
    textgraph.save_packed(G.split_targets(back), str(tmp_path / "packed"))
    assert spark.read.parquet(str(tmp_path / "packed")).count() == 1


def test_functions(spark):
    register_all(spark)
    assert spark.sql("SELECT motif_isomorphic('0.1:1', '1.0:1') AS same").first().same
    assert [r.tag for r in spark.sql("SELECT tag FROM html_tree('<div><p>x<br></p><p>y</p></div>')").collect()] == ["div", "p", "br", "p"]
    df = spark.createDataFrame([(1, [1.0, 2.0]), (1, [3.0, 4.0])], "g int, v array<double>")
    assert vec_sum_native(df, ["g"], "v").first().v == [4.0, 6.0]


def test_html_tree():
    assert S.html_tree("<a><img><b></a><c></c></x>") == [(0, -1, "a"), (1, 0, "img"), (2, 0, "b"), (3, -1, "c")]


def test_plans(spark, small):
    plan = graph_queries.QUERIES["g_session_edges"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "Python" not in plan and "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,user_id:bigint>" in plan
    plan = relational.QUERIES["op_project_filter"](spark, small)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(value)" in plan or "GreaterThan(value" in plan


def _files(spark, small, folder):
    e = spark.read.parquet(f"{small}/events.parquet").orderBy("ts")
    e.repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(folder)


def test_stream_equals_batch(spark, small, tmp_path):
    _files(spark, small, str(tmp_path / "e"))
    batch = spark.read.parquet(f"{small}/events.parquet").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").count()
    got = motifs.run_once(motifs.windowed(motifs.event_stream(spark, str(tmp_path / "e"), "40 days", 10)), "tumbling", "complete")
    assert got.count() == batch.count() and got.agg(F.sum("events")).first()[0] == 1000


def test_stream_motifs(spark, small, tmp_path):
    _files(spark, small, str(tmp_path / "e"))
    spark.conf.set("spark.sql.shuffle.partitions", "2")
    got = motifs.run_once(motifs.count_motifs(motifs.event_stream(spark, str(tmp_path / "e"), files=10), 3), "closed_motifs")
    by = {(r.user_id, r.code): r.n for r in got.groupBy("user_id", "code").agg(F.sum("closed").alias("n")).collect()}
    e = spark.read.parquet(f"{small}/events.parquet").toPandas().sort_values(["ts", "event_id"])
    want: dict = {}
    for user, labels in e.groupby("user_id")["event_type"]:
        labels = list(labels)
        for i in range(len(labels)):
            for code in motifs.closed(labels[: i + 1], 3):
                want[user, code] = want.get((user, code), 0) + 1
    assert by == want


def test_late_rows_are_dropped(spark, tmp_path):
    def save(name, times):
        rows = [(i, t, 1, "view", 1.0, "{}") for i, t in enumerate(times)]
        df = spark.createDataFrame(rows, "event_id long, t string, user_id long, event_type string, value double, props string")
        df.select("event_id", F.to_timestamp_ntz("t").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(name)

    folder = str(tmp_path / "e")
    (tmp_path / "e").mkdir()
    stream = motifs.windowed(motifs.event_stream(spark, folder, "10 minutes", 1))
    where = str(tmp_path / "state")
    seen = {}

    def keep(df, number):
        seen.update({(r.start, r.event_type): r.events for r in df.collect()})

    for times in (["2024-01-01 00:10:00"], ["2024-01-01 03:00:00"], ["2024-01-01 00:20:00", "2024-01-01 02:55:00"], ["2024-01-01 09:00:00"], ["2024-01-01 09:01:00"]):
        save(folder, times)
        q = stream.writeStream.foreachBatch(keep).outputMode("append").option("checkpointLocation", where).trigger(availableNow=True).start()
        q.awaitTermination()
    counts = {k[0].hour: v for k, v in seen.items()}
    assert counts[0] == 1 and counts[2] == 1 and counts[3] == 1
