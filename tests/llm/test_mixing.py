"""Mixing: reruns agree at any partitioning, and large sources go down a tree of shards."""

from __future__ import annotations

from pyspark.sql import functions as F

from motif_spark.llm import mixing

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def test_mix_does_not_depend_on_partitions(spark):
    text = lambda k: " ".join(f"w{k}x{j}" for j in range(4))
    rows = [(7, text(k), "en", "s", 20) for k in range(400)] + [(None, text(1000 + k), "en", None, 20) for k in range(300)]
    rows += [(8, text(5), "en", "t", 20)] * 40 + [(9, "", "en", "t", 0), (9, None, None, None, None)]
    docs = spark.createDataFrame(rows, SCHEMA)
    got = []
    for n in (1, 3, 7):
        df = mixing.mixed_documents(docs.repartition(n, F.rand(n)), whole=True)
        got.append(sorted(tuple(str(x) for x in r) for r in df.collect()))
    assert got[0] and got[0] == got[1] == got[2]


def test_quotas_down_a_tree(spark, monkeypatch):
    rows = [(s, k, 1 + (k * 7 + s) % 13, 500 + s) for s in range(2) for k in range(40)]
    votes = spark.createDataFrame(rows, "sid long, shard long, votes long, seats long")
    flat = {(r.sid, r.shard): r.seats_won for r in mixing._quotas(votes, 1).collect()}
    monkeypatch.setattr(mixing, "FAN", 4)
    tree = {(r.sid, r.shard): r.seats_won for r in mixing._quotas(votes, 3).collect()}
    assert flat.keys() == tree.keys()
    for s in range(2):
        assert sum(n for (t, _), n in flat.items() if t == s) == sum(n for (t, _), n in tree.items() if t == s) == 500 + s
    for (s, k), n in tree.items():
        share = (500 + s) * (1 + (k * 7 + s) % 13) / sum(1 + (j * 7 + s) % 13 for j in range(40))
        assert abs(n - share) < 3
