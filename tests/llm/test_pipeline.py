"""The pipeline's stages against what each must do to its own input."""

from __future__ import annotations

import corpus_pipeline
from motif_spark.llm import quality, simhash
from tests.llm.test_operators import brute_repeats


def kept_by_brute_force(docs) -> list[int]:
    """The smallest id of each group, joined by both kinds of links that the stage's docstring names: fingerprints
    of three words within three bits, and 0.8 of the five-word shingles in common; all pairs are compared."""
    rows = sorted((r.doc_id, r.text.encode().lower().split()) for r in docs.select("doc_id", "text").collect())
    prints = [simhash.fingerprint(w) for _, w in rows]
    fives = [{b" ".join(w[k : k + 5]) for k in range(len(w) - 4)} for _, w in rows]
    root = list(range(len(rows)))

    def find(x: int) -> int:
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            near = (prints[a] ^ prints[b]).bit_count() <= 3
            both = len(fives[a] & fives[b])
            if near or both and both >= 0.8 * (len(fives[a]) + len(fives[b]) - both):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return [i for k, (i, _) in enumerate(rows) if root[k] == k]


def test_stages(spark, small, tmp_path):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    seen = {"start": docs}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, small)
        assert name == "best_fit_packing" or out.columns == seen["start"].columns
        out.write.parquet(str(tmp_path / name))
        docs = seen[name] = spark.read.parquet(str(tmp_path / name))
    keep = {r.doc_id for r in quality.assess(seen["start"]).filter("kept").collect()}
    ids = lambda n: sorted(r.doc_id for r in seen[n].select("doc_id").collect())
    assert ids("quality_rules") == sorted(keep)
    assert ids("simhash_near_dedup") == kept_by_brute_force(seen["quality_rules"])
    assert ids("suffix_array_dedup") == ids("simhash_near_dedup")
    before = sorted((r.doc_id, r.text) for r in seen["simhash_near_dedup"].collect())
    gone = brute_repeats(before)
    for r in seen["suffix_array_dedup"].collect():
        assert abs(len(r.text.encode()) - (gone[r.doc_id][0] - gone[r.doc_id][1])) <= 8 * gone[r.doc_id][2]
    assert seen["best_fit_packing"].groupBy("sequence_id").agg({"length": "sum"}).filter("`sum(length)` > 2048").count() == 0


def test_run(spark, small):
    assert corpus_pipeline.run(spark, small).count() > 0
