"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    from motif_spark.operators import census as C
    from motif_spark.operators import graphs as G
    from motif_spark.operators import learning as L
    from motif_spark.operators import mni as N
    from motif_spark.operators import process as P
    from motif_spark.plans import graph_queries as Q
    from motif_spark.plans import policies
    from motif_spark.sources import suites as S

    os.environ.setdefault("OMP_NUM_THREADS", "1")
    conf = {"spark.sql.shuffle.partitions": "32", "spark.ui.enabled": "false", "spark.driver.memory": "12g", "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    split = lambda suite: G.saved(G.split_targets(S.packed(spark, sf_dir, suite), 0.8).filter("split = 'test'"))
    test, folded, trees = split("session"), split("session3"), split("dom")
    policy = policies.load("session3")
    sizes = [5, 6, 7, 8, 9]
    work = {
        "graphs_session": lambda: S.packed(spark, sf_dir, "session"),
        "graphs_purchase": lambda: S.packed(spark, sf_dir, "purchase_kind"),
        "census_k3_session": lambda: Q.QUERIES["x_freq_k3_session"](spark, sf_dir),
        "census_k4_session": lambda: Q.QUERIES["x_freq_k4_session"](spark, sf_dir),
        "space_k7_session": lambda: Q.QUERIES["x_space_k7_session"](spark, sf_dir),
        "mni_k3_session": lambda: Q.QUERIES["n_best_k3"](spark, sf_dir),
        "exact_k5_9_test": lambda: C.most_frequent(C.exact_census(test, sizes)),
        "mni_k5_9_test": lambda: N.baseline(N.descent(test, sizes)),
        "random_k5_9_test": lambda: P.random_baseline(test, P.random_rollouts(test, sizes, 100, 1)),
        "learned_k5_9_test": lambda: L.mine_all(folded, sizes, policy),
        "exact_k5_7_trees": lambda: C.most_frequent(C.exact_census(trees, sizes[:3])),
        "mni_k5_7_trees": lambda: N.baseline(N.descent(trees, sizes[:3])),
    }
    seconds = {}
    for name, make in work.items():
        began = time.perf_counter()
        df = make()
        df.agg(F.count(F.lit(1)), *[F.max(F.xxhash64(c)) for c in df.columns[:1]]).collect()
        seconds[name] = round(time.perf_counter() - began, 3)
        print(name, seconds[name], file=sys.stderr)
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "test_graphs": test.count()}))
    spark.stop()


if __name__ == "__main__":
    main()
