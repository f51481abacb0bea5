"""Cases of the review in the graph queries: each would have failed before its change."""

from __future__ import annotations

from pyspark.sql import functions as F

from motif_spark.operators import network as net
from motif_spark.operators import training as T
from motif_spark.plans import class_queries, policies, workload_queries, workloads


def test_ratio_is_over_all_test_graphs(spark, small):
    sf_dir = small.replace("0.001", "0.01")
    test = workloads.prepare(spark, sf_dir, "session3", [3, 4], valid=0.0)["test"]
    want = test.count()
    assert want > 60 and {(r.k, r.graphs) for r in workload_queries.l_ratio(spark, sf_dir).collect()} == {(k, want) for k in range(5, 10)}


def test_random_baselines_take_all_samples_and_seeds(spark, small):
    assert {r.seeds for r in class_queries.w2_random_ratio(spark, small).collect()} == {5}
    got = class_queries.QUERIES["r_rollouts"](spark, small).agg(F.max("sample"), F.max("seed")).first()
    assert tuple(got) == (99, 4)


def test_settings_evaluate_every_graph(spark, small):
    """Training takes at most one graph in each task; the ratios are over all graphs of their split."""
    lessons = policies.school(spark, small, "session3", [3])
    config = net.Config(labels=3, k_max=3, width=8, heads=2, layers=1)
    got = workloads.settings(lessons, {"x": (config, T.Rounds(sizes=(3,), rounds=1, steps=1, groups=2, per=4, most_graphs=1))}).collect()
    assert {r.split: r.graphs for r in got} == {split: held.count() for split, held in lessons.items()}
