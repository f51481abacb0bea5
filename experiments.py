"""The experiments on the folded session suite: python experiments.py SF_DIR [train|accuracy|rewards|ablations|growth ...]."""

from __future__ import annotations

import os
import sys
import time

from pyspark.sql import SparkSession

ROUNDS = int(os.environ.get("ROUNDS", "12"))


def main() -> None:
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    from motif_spark.operators import training as T
    from motif_spark.plans import policies
    from motif_spark.plans import workload_queries as Q
    from motif_spark.plans import workloads as W
    from motif_spark.plans.class_queries import QUERIES, session

    sf_dir, *what = sys.argv[1:] or ["/root/testdata/sf0.01"]
    conf = {"spark.sql.shuffle.partitions": "32", "spark.ui.enabled": "false", "spark.driver.memory": "12g", "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    sizes, began = [5, 6, 7, 8, 9], time.perf_counter()
    show = lambda df: df.show(200, False)
    if {"train", "rewards", "ablations"} & set(what):
        lessons = policies.school(spark, sf_dir, "session3", sizes)
        how = T.Rounds(rounds=ROUNDS, check_every=max(1, ROUNDS // 4))
        print("lessons", round(time.perf_counter() - began, 1), "s", flush=True)
    if "train" in what:
        policy = T.train_rounds(lessons["train"], policies.CONFIG, how, {"valid": lessons["valid"]}, tell=print)
        print(policies.save(policy, "session3"), round(time.perf_counter() - began, 1), "s")
    if "rewards" in what:
        show(W.reward_settings(lessons, policies.CONFIG, how).orderBy("setting", "split", "k"))
    if "ablations" in what:
        show(W.ablations(lessons, policies.CONFIG, how).filter("split = 'test'").orderBy("setting", "k"))
    if "accuracy" in what or not what:
        show(QUERIES["w2_accuracy_session3"](spark, sf_dir).orderBy("method", "k"))
        show(Q.QUERIES["l_ratio"](spark, sf_dir).orderBy("k"))
    if "growth" in what:
        for row in W.cost_growth(session(spark, sf_dir, True).cache(), policies.load("session3"), sizes):
            print(row)
    spark.stop()


if __name__ == "__main__":
    main()
