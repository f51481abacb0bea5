"""The experiments: dataset table, accuracy and time of four methods, reward settings, ablations, cost growth."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import census as C
from ..operators import graphs as G
from ..operators import learning as L
from ..operators import measures as A
from ..operators import mni as N
from ..operators import network as net
from ..operators import process as P
from ..operators import training as T
from ..sources import suites as S

METRICS = "suite string, method string, k int, ratio double, graphs long, seconds double, seed int"


def dataset_table(spark: SparkSession, sf_dir: str, suites: list[str]) -> DataFrame:
    """Graphs, mean nodes and mean edges of each suite after the target filter."""
    rows = [G.suite_stats(S.packed(spark, sf_dir, s)).select(F.lit(s).alias("suite"), "*") for s in suites]
    return reduce(DataFrame.unionByName, rows)


def prepare(spark: SparkSession, sf_dir: str, suite: str, sizes: list[int], valid: float = 0.1, most_nodes: int | None = None) -> dict:
    """Split graphs of a suite and the exact census of them, saved."""
    graphs = S.packed(spark, sf_dir, suite)
    if most_nodes:
        graphs = graphs.filter(F.col("n") <= most_nodes)
    graphs = G.saved(G.split_targets(graphs, 0.8, valid))
    labels = graphs.agg(F.max(F.array_max("label_ids"))).first()[0]
    return {"suite": suite, "graphs": graphs, "sizes": sizes, "labels": (labels or 0) + 1, "train": graphs.filter("split = 'train'"), "valid": graphs.filter("split = 'valid'"), "test": graphs.filter("split = 'test'")}


def with_census(data: dict) -> dict:
    return data | {"census": G.saved(C.exact_census(data["graphs"], data["sizes"]))}


def train_policy(data: dict, how: L.Training, **network) -> L.Policy:
    config = net.Config(**{"labels": data["labels"], "k_max": max(data["sizes"])} | network)
    return L.train(data["train"], data["census"], config, replace(how, sizes=tuple(data["sizes"])), data["valid"], data["census"])


def compare_methods(data: dict, policy: L.Policy, n_samples: int = 100, seeds: int = 5) -> DataFrame:
    """Mean ratio and total seconds of the four methods on the test graphs, as metrics rows.

    Seconds are those of all sizes together: the exact census for the exact method, mining and counting for
    the two baselines, and the search alone for the learned miner.
    """
    spark, test, sizes = data["graphs"].sparkSession, G.saved(data["test"]), data["sizes"]
    exact = C.exact_census(test, sizes)
    t_exact, _ = A.timed(exact)
    census = G.saved(exact)
    truth = C.most_frequent(census)
    mni = N.baseline(N.descent(test, sizes))
    t_mni, _ = A.timed(mni)
    rollouts = P.random_rollouts(test, sizes, n_samples, seeds)
    t_random, _ = A.timed(P.random_baseline(test, P.random_rollouts(test, sizes, n_samples, 1)))
    random = P.random_baseline(test, rollouts, census)
    mined = L.mine_all(test, sizes, policy)
    t_learned, _ = A.timed(mined)
    learned = mined.join(G.shuffled(census.select("graph_id", "k", "code", "freq")), ["graph_id", "k", "code"])
    out = []
    for name, found, seconds in (("exact", truth, t_exact), ("mni", mni, t_mni), ("learned", learned, t_learned)):
        out += [(data["suite"], name, r["k"], r["ratio"], r["graphs"], seconds, 0) for r in A.avg_ratio(A.approx_ratio(found, truth)).collect()]
    each = A.approx_ratio(random, truth).groupBy("seed", "k").agg(F.avg("ratio").alias("ratio"), F.count(F.lit(1)).alias("graphs"))
    out += [(data["suite"], "random", r["k"], r["ratio"], r["graphs"], t_random, r["seed"]) for r in each.filter("seed is not null").collect()]
    return spark.createDataFrame(out, METRICS)


def accuracy_table(metrics: DataFrame) -> DataFrame:
    """suite, method, a column for each size, seconds: means over seeds."""
    wide = metrics.groupBy("suite", "method").pivot("k").agg(F.round(F.avg("ratio"), 3))
    return wide.join(metrics.groupBy("suite", "method").agg(F.round(F.avg("seconds"), 2).alias("seconds")), ["suite", "method"])


SETTINGS = "setting string, split string, k int, ratio double, graphs long, max_over_training double, samples long"


def reward_settings(lessons: dict[str, DataFrame], config: net.Config, how: T.Rounds) -> DataFrame:
    """A policy for each reward kind, from the same start."""
    return settings(lessons, {kind: (config, replace(how, reward=kind)) for kind in ("raw", "best", "density")})


def ablations(lessons: dict[str, DataFrame], config: net.Config, how: T.Rounds, names: list[str] | None = None) -> DataFrame:
    """A policy for each rung of the ladder and each single change."""
    return settings(lessons, {n: (c, how) for n, c in L.variants(config).items() if names is None or n in names})


def settings(lessons: dict[str, DataFrame], runs: dict[str, tuple[net.Config, T.Rounds]]) -> DataFrame:
    """Ratios over all graphs of every split: those of the policy that was best on `valid`, and beside them the
    largest that the split itself saw during training."""
    rows, spark = [], lessons["train"].sparkSession
    for name, (config, how) in runs.items():
        policy = T.train_rounds(lessons["train"], config, how, lessons)
        for split, held in lessons.items():
            for r in T.mean_ratios(held, policy, how.sizes).collect():
                seen = [c[f"k{r['k']}"] for c in policy.curve if c["split"] == split]
                rows.append((name, split, r["k"], r["ratio"], r["graphs"], max(seen), policy.samples))
    return spark.createDataFrame(rows, SETTINGS)


def cost_growth(graphs: DataFrame, policy: L.Policy, sizes: list[int]) -> list[dict]:
    """Seconds of the learned search for each size beside the number of connected sets."""
    space = {r["k"]: r["sets"] for r in C.search_space(graphs, sizes).groupBy("k").agg(F.sum("sets").alias("sets")).collect()}
    return [{"k": k, "seconds": A.timed(L.mine_all(graphs, [k], policy))[0], "sets": space[k]} for k in sizes]
