"""Experiment queries: measures over methods on whole suites."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import census as C
from ..operators import graphs as G
from ..operators import learning as L
from ..operators import measures as A
from ..operators import mni as N
from ..operators import network as net
from ..operators import match as M
from ..operators import process as P
from ..operators import training as T
from ..sources import suites as S
from . import policies
from . import workloads as W
from .class_queries import csv, session, supports
from .graph_queries import SESSION, _mni_sql, _session

QUERIES, SQL = {}, {}
SIZES = [5, 6, 7, 8, 9]


def _keep(f):
    QUERIES[f.__name__] = f
    return f


@_keep
def w1_dataset_table(spark, sf_dir):
    return W.dataset_table(spark, sf_dir, ["session", "session3", "purchase", "dom", "similar", "trade"])


@_keep
def w4_mni_ratio_k3(spark, sf_dir):
    """Mean ratio of the highest-support class on session graphs."""
    census = G.saved(N.mni_census(_session(spark, sf_dir), [3]))
    return A.avg_ratio(A.approx_ratio(N.baseline(census), census)).select("k", F.round("ratio", 9).alias("ratio"), F.round("hit_rate", 9).alias("hit_rate"), "graphs")


SQL["w4_mni_ratio_k3"] = f"""WITH {_mni_sql(3)}, t AS (SELECT graph_id, k, max(freq) AS freq FROM (SELECT *, rank() OVER (PARTITION BY graph_id ORDER BY mni DESC) AS x FROM r) WHERE x = 1 GROUP BY 1, 2),
mx AS (SELECT graph_id, max(freq) AS best FROM r GROUP BY 1) SELECT k, round(avg(freq / best), 9) AS ratio, round(avg(CASE WHEN freq = best THEN 1.0 ELSE 0.0 END), 9) AS hit_rate, count(*) AS graphs FROM t JOIN mx USING (graph_id) GROUP BY 1"""


@_keep
def w4_mni_disagreement_purchase(spark, sf_dir):
    """How often support misleads on customer graphs, sizes 3."""
    graphs = G.pack_graphs(*S.purchase(spark, sf_dir, False), labels=["C", "O", "S"])
    return N.disagreement(N.mni_census(G.filter_targets(graphs), [3]))


@_keep
def w8_search_space(spark, sf_dir):
    """Connected sets of all session graphs for each size."""
    return C.search_space(_session(spark, sf_dir), [3, 4, 5, 6]).groupBy("k").agg(F.sum("sets").alias("sets"))


@_keep
def w9_worked_example(spark, sf_dir):
    """The worked example's measure, the class of highest support for sizes 2 to 6, on every session graph."""
    return N.baseline(N.mni_census(session(spark, sf_dir), [2, 3, 4, 5, 6])).select("graph_id", "k", "freq", "mni")


SQL["w9_worked_example"] = f"WITH {supports([2, 3, 4, 5, 6])} SELECT graph_id, k, freq, mni FROM top"


@_keep
def l_mine_session(spark, sf_dir):
    """Greedy search by the shipped policy in every folded session graph, sizes 5 to 9: one narrow stage."""
    found = L.mine_all(session(spark, sf_dir, True), SIZES, policies.load("session3"))
    return found.select("graph_id", "k", csv("members"), "code")


@_keep
def l_ratio(spark, sf_dir):
    """Ratio of the shipped policy on all test graphs of the folded session suite, sizes 5 to 9."""
    test = G.saved(G.split_targets(session(spark, sf_dir, True), 0.8).filter("split = 'test'"))
    found = G.saved(L.mine_all(G.dealt(test, "graph_id"), SIZES, policies.load("session3")).filter("not dead").select("graph_id", "k", "code"))
    return A.avg_ratio(A.approx_ratio(M.frequency_listed(test, found, SIZES), C.best_census(test, SIZES)))


@_keep
def l_train(spark, sf_dir):
    """A short training in Spark on sizes 3 and 4 with its curve on every split."""
    lessons = policies.school(spark, sf_dir, "session3", [3, 4])
    config = net.Config(labels=3, width=16, heads=2, layers=2, k_max=4, residual=True)
    how = T.Rounds(sizes=(3, 4), rounds=3, steps=4, groups=8, per=8, rate=2e-3, check_every=1)
    policy = T.train_rounds(lessons["train"], config, how, lessons)
    rows = [(c["epoch"], c["samples"], c["split"], int(k), c[f"k{k}"]) for c in policy.curve for k in "34"]
    return spark.createDataFrame(rows, "epoch int, samples long, split string, k int, ratio double")


@_keep
def l_critic_gradient(spark, sf_dir):
    """Length of the critic's gradient over a replay table, summed in Spark, beside that of one batch of all rows."""
    import numpy as np

    graphs = G.saved(session(spark, sf_dir, True))
    census = G.saved(C.exact_census(graphs, [3]))
    replay = P.transitions(P.random_rollouts(graphs, [3], 1, 1), census, graphs)
    rows = replay.join(G.shuffled(graphs.select("graph_id", "label_ids", "nbrs")), "graph_id")
    rows = G.saved(rows.select("label_ids", "nbrs", "selected", (F.col("k") - F.col("step")).alias("left"), "k", "action", F.col("reward").alias("target"), "reward"))
    config = net.Config(labels=3, width=8, heads=2, layers=1, k_max=3)
    params = net.init(config, "critic", 5)
    spread = L.distributed_gradients(rows, params, config)
    length = float(np.sqrt(sum((g**2).sum() for g in spread.values())))
    return spark.createDataFrame([(rows.count(), length)], "transitions long, length double")


def _settings_query(name: str, run) -> None:
    def query(spark, sf_dir):
        lessons = policies.school(spark, sf_dir, "session3", [3, 4])
        config = net.Config(labels=3, width=16, heads=2, layers=2, k_max=4, residual=True)
        return run(lessons, config, T.Rounds(sizes=(3, 4), rounds=2, steps=3, groups=8, per=8, rate=2e-3, check_every=1))

    query.__doc__ = f"{run.__doc__} A short run on sizes 3 and 4; experiments.py has the long ones."
    QUERIES[name] = query


_settings_query("w5_reward_settings", W.reward_settings)
_settings_query("w7_ablations", W.ablations)


SQL["w8_search_space"] = f"""WITH RECURSIVE {SESSION}, w AS (SELECT graph_id, n, node AS last, 1 AS k FROM s UNION ALL SELECT graph_id, n, last + d, k + 1 FROM w, (VALUES (1), (2)) AS t(d) WHERE k < 6 AND last + d < n)
SELECT CAST(k AS INT) AS k, count(*) AS sets FROM w WHERE k >= 3 GROUP BY 1"""
