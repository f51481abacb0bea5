"""Cases of the review: each would have failed before its change."""

from __future__ import annotations

from collections import Counter
from functools import lru_cache

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from motif_spark.llm import mixing, packing, simhash
from tests.llm.test_operators import brute_repeats


def prose(seed: int, n: int = 80) -> str:
    rng = np.random.default_rng(seed)
    return " ".join("".join(rng.choice(list("abcdefghij"), 6)) for _ in range(n))


def test_rows_with_null_or_shared_ids_stay_apart(spark):
    a, b, c, d = (prose(k) for k in range(4))
    rows = [(None, a), (None, b), (None, a), (5, c), (5, d), (3, d), (7, a)]
    got = simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(((r.doc_id or 0), r.text) for r in got) == sorted([(7, a), (0, b), (5, c), (3, d)])


def fives(text: str) -> set[str]:
    w = (text or "").lower().split()
    return {" ".join(w[k : k + 5]) for k in range(len(w) - 4)}


def alike(a: set, b: set) -> float:
    return len(a & b) / len(a | b) if a and b else 0.0


def test_near_copies_beyond_three_bits_are_one_group(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text")
    sets = {r.doc_id: (r.text, fives(r.text)) for r in docs.collect()}
    pairs = [(a, b) for a in sets for b in sets if a < b and sets[a][0] != sets[b][0] and alike(sets[a][1], sets[b][1]) >= 0.8]
    kept = {r.doc_id for r in simhash.one_of_each(docs).collect()}
    assert pairs and not any(a in kept and b in kept for a, b in pairs)
    plain = {r.doc_id for r in simhash.near_duplicates(docs).filter("doc_id = component_id").collect()}
    assert kept <= plain
    for x in plain - kept:  # nothing else goes
        assert any(x != y and alike(sets[x][1], sets[y][1]) >= 0.8 for y in sets)


def test_alike_forest_is_exact():
    rng = np.random.default_rng(6)
    base = [np.unique(rng.integers(0, 1 << 60, 60).astype(np.uint64)) for _ in range(6)]
    sets = [np.unique(np.concatenate([b[rng.random(60) < rng.choice([0.85, 0.95])], rng.integers(0, 1 << 60, 3).astype(np.uint64)])) for b in base for _ in range(12)]

    def groups(links):
        root = list(range(len(sets)))
        for _ in sets:
            for a, b in links:
                root[a] = root[b] = min(root[a], root[b])
        return root

    brute = [(a, b) for a in range(len(sets)) for b in range(a) if alike(set(sets[a].tolist()), set(sets[b].tolist())) >= 0.8]
    found = simhash.alike_forest(sets)
    assert brute and set(map(tuple, map(sorted, found))) <= set(map(tuple, map(sorted, brute))) and groups(found) == groups(brute)


def test_stages_after_near_copies(spark, small, tmp_path):
    """The checks of test_pipeline.test_stages that follow the near-duplicate stage."""
    docs, seen = spark.read.parquet(f"{small}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, small).write.parquet(str(tmp_path / name))
        docs = seen[name] = spark.read.parquet(str(tmp_path / name))
    before = sorted((r.doc_id, r.text) for r in seen["simhash_near_dedup"].collect())
    gone, after = brute_repeats(before), seen["suffix_array_dedup"].collect()
    assert sorted(r.doc_id for r in after) == [i for i, _ in before]
    for r in after:
        assert abs(len(r.text.encode()) - (gone[r.doc_id][0] - gone[r.doc_id][1])) <= 8 * gone[r.doc_id][2]
    assert seen["best_fit_packing"].groupBy("sequence_id").agg({"length": "sum"}).filter("`sum(length)` > 2048").count() == 0


def bins(plan):
    return sum(n for _, n in plan)


def packed(plan):
    used = Counter()
    for filling, n in plan:
        for x in filling:
            used[x] += n
    return used


def test_plan_goes_back_over_its_fillings():
    counts = Counter([1224, 1088, 816, 816, 816, 748, 680, 680, 544, 408])
    plan = packing.plan(dict(counts), 2048)
    assert bins(plan) == 4 and packed(plan) == counts and all(sum(f) <= 2048 for f, _ in plan)
    many = {x: 1000 * n for x, n in counts.items()}
    plan = packing.plan(many, 2048)
    assert bins(plan) <= 4000 and packed(plan) == many and all(sum(f) <= 2048 for f, _ in plan)


def fewest(items, capacity):
    """Fewest bins by trying every bin for every item."""

    @lru_cache(None)
    def place(k, rooms):
        if k == len(items):
            return 0
        new = place(k + 1, tuple(sorted((*rooms, capacity - items[k])))) + 1
        return min([new, *(place(k + 1, tuple(sorted((*rooms[:j], r - items[k], *rooms[j + 1 :])))) for j, r in enumerate(rooms) if r >= items[k])])

    return place(0, ())


def test_plan_needs_the_fewest_bins():
    rng = np.random.default_rng(9)
    for _ in range(150):
        items = sorted(rng.integers(12, 60, rng.integers(4, 10)).tolist(), reverse=True)
        best = fewest(tuple(items), 100)
        assert packing.lower_bound(Counter(items), 100) <= best == bins(packing.plan(Counter(items), 100))


def test_mixing_stage_cuts_no_text(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    text = {r.doc_id: (r.text, r.source, len((r.text or "").split())) for r in docs.collect()}
    taken, made = Counter(), Counter()
    for r in mixing.mix(docs).collect():
        taken[r.source] += r.taken
    rows = corpus_pipeline.source_mixing(spark, docs, small).collect()
    for r in rows:
        assert r.text == text[r.doc_id][0] and r.n_chars == len(r.text)
        made[r.source] += text[r.doc_id][2]
    assert max(Counter(r.doc_id for r in rows).values()) <= 2
    longest = max(n for _, _, n in text.values())
    assert all(abs(made[s] - taken[s]) <= longest * -(-sum(n for _, t, n in text.values() if t == s) // mixing.SHARD_WORDS) for s in taken)
