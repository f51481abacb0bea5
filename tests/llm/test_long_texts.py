"""Very long texts are gone through in slices with the results of the whole, and EM against plain loops."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pytest

from motif_spark.llm import classifier, fingerprint
from motif_spark.llm.common import slices, utf8


@pytest.fixture(params=[1, 7, 64, 1000])
def cut(request, monkeypatch):
    monkeypatch.setattr(classifier, "SLICE_BYTES", request.param)
    monkeypatch.setattr(fingerprint, "SLICE_BYTES", request.param)
    return request.param


def test_slices_give_what_the_whole_gives(cut, monkeypatch):
    rng = np.random.default_rng(3)
    text = " ".join(rng.choice(["ab", "Cé", "x|y", "end.", "#", "a", "longerword\n"], 400)) + " "
    data, at = utf8(pa.array([text]))
    assert "".join(text.encode()[a:b].decode() for a, b in slices(data, cut)) == text
    part = (classifier.statistics(data, at), fingerprint.digests(data, at))
    features = classifier.features(data, at, part[0])
    monkeypatch.setattr(classifier, "SLICE_BYTES", 1 << 20)
    monkeypatch.setattr(fingerprint, "SLICE_BYTES", 1 << 20)
    whole = (classifier.statistics(data, at), fingerprint.digests(data, at))
    assert (part[0] == whole[0]).all() and all((a == b).all() for a, b in zip(part[1], whole[1]))
    assert (features == classifier.features(data, at, whole[0])).all()


def test_label_model_against_loops():
    """The same EM in plain loops over votes, one document at a time."""
    rng = np.random.default_rng(8)
    docs = [[int(x) for x in row] for row in np.where(rng.random((300, 4)) < 0.3, 0, rng.integers(1, 3, (300, 4)))]
    m, rounds = 4, 25
    cast = [[sum(d[j] == k for d in docs) / len(docs) for k in range(3)] for j in range(m)]
    chance = [[[0.0] * 3 for _ in range(m)] for _ in (0, 1)]
    for c in (0, 1):
        for j in range(m):
            chance[c][j][0] = cast[j][0]
            chance[c][j][1 + c] = 0.8 * (1 - cast[j][0]) + 1e-6
            chance[c][j][2 - c] = 0.2 * (1 - cast[j][0]) + 1e-6
    good = 0.7
    for _ in range(rounds):
        post = []
        for d in docs:
            like = [math.prod(max(chance[c][j][d[j]], 1e-12) for j in range(m)) * (good if c else 1 - good) for c in (0, 1)]
            post.append(like[1] / sum(like))
        good = min(max((sum(post) + 1) / (len(docs) + 2), 1e-4), 1 - 1e-4)
        for c in (0, 1):
            for j in range(m):
                n = [sum((p if c else 1 - p) for d, p in zip(docs, post) if d[j] == k) + 1 for k in range(3)]
                chance[c][j] = [x / sum(n) for x in n]
    codes, counts = np.unique(np.array(docs) @ 3 ** np.arange(m), return_counts=True)
    got = classifier.label_model(classifier.patterns_to_votes(codes, m), counts.astype(float), rounds=rounds)
    by_code = dict(zip(codes.tolist(), got["posterior"].tolist()))
    if abs(float(got["good"]) - good) < 1e-9:  # the engine may stop earlier, once nothing moves
        assert np.allclose([by_code[int(np.array(d) @ 3 ** np.arange(m))] for d in docs], post, atol=1e-9)
    assert abs(float(got["good"]) - good) < 1e-4
    assert np.allclose([by_code[int(np.array(d) @ 3 ** np.arange(m))] for d in docs], post, atol=1e-3)


def test_votes_on_single_traits():
    words, distinct, marks, capitals, bars, ends, size, lines = range(8)
    plain = [100, 0.8, 0.0, 0.02, 0.0, 0.1, 5.0, 0.03]
    names = {x: i for i, x in enumerate(classifier.LABELLERS)}
    vote = lambda **change: classifier.votes(np.array([[change.get(str(i), x) for i, x in enumerate(plain)]]))[0]
    assert vote().tolist() == [0, 0, 0, 0, 0, 2, 2, 2, 2]
    for at, value, who in ((words, 3, "length"), (distinct, 0.1, "repetition"), (marks, 0.5, "marks"), (capitals, 0.9, "case"), (bars, 0.4, "bars")):
        got = vote(**{str(at): value})
        assert got[names[who]] == classifier.BAD and (got == classifier.BAD).sum() >= 2
    assert vote(**{str(marks): 0.2}).tolist() == [0] * 9
