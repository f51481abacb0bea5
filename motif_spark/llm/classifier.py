"""Quality scores without gold labels: heuristic labellers, a label model, and a hashed linear scorer.

Labellers vote good, bad or nothing. The corpus is reduced to counts of vote patterns (at most 3 to the
number of labellers), on which expectation-maximisation estimates each labeller's accuracies and the share
of good documents; posteriors of patterns are the soft labels. A logistic scorer over hashed byte triplets
and text statistics is fitted to them on a bounded sample and scores every document.

Defined cases: a null or empty text is voted bad by the length labeller and is scored like any other; rows
are scored alone, so repeated rows get equal scores; an empty table gives an empty result; where all
documents have one pattern the scorer returns that posterior's side; a very long text is gone through in slices
and judged whole; a score at the threshold is kept; rows of one id are ordered by their features where the sample
is drawn; extra columns are left out, so their names do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices, spans, utf8

#: The scorer is fitted to at most this many documents, those with the smallest hashes; scores cover all.
SAMPLE = 4_096
HASHED = 2_048
PATTERNS = 3**9
LABELLERS = ("length", "repetition", "marks", "case", "bars", "variety", "shape", "body", "prose")
BLOCK_BYTES = 1 << 20
#: A longer text is gone through in slices of this size.
SLICE_BYTES = 4 << 20
ABSTAIN, BAD, GOOD = 0, 1, 2
_STATS = 8


def _raw(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Counts of words, marks, capitals, small letters, bars, sentence ends, solid bytes and line breaks of each
    text; the hash of every word and its text."""
    n = len(at) - 1
    space = (data == 32) | ((data >= 9) & (data <= 13))
    text = np.repeat(np.arange(n), np.diff(at))
    begin = ~space
    first = np.zeros(len(data), bool)
    first[at[:-1][at[:-1] < at[1:]]] = True
    begin[1:] &= space[:-1] | first[1:]
    starts = np.flatnonzero(begin)
    # A word's hash: the sum of its bytes' hashes, each weighted by its place in the word.
    weight = (data.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    origin = np.zeros(len(data), np.int64)
    origin[starts] = starts
    place = np.arange(len(data)) - np.maximum.accumulate(origin) if len(data) else origin
    weight ^= weight >> np.uint64(29)
    turn = (place.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    weight *= turn ^ turn >> np.uint64(32) | np.uint64(1)
    weight[space] = 0
    hashes = np.add.reduceat(weight, starts) if len(starts) else np.zeros(0, np.uint64)
    count = lambda mask: np.bincount(text[mask], minlength=n).astype(float)
    mark = np.isin(data, np.frombuffer(b"#*$%&<>!@^~=+_\\{}[]", np.uint8))
    capital, letter = (data >= 65) & (data <= 90), (data >= 97) & (data <= 122)
    end = (data == ord(".")) | (data == ord("?"))
    counts = np.stack([count(x) for x in (begin, mark, capital, letter, data == ord("|"), end, ~space, data == 10)], 1)
    return counts, hashes, text[starts]


def statistics(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Eight statistics of each text: words, share of distinct word hashes, and rates of marks, capitals, bars,
    sentence ends, word bytes and line breaks. A long text that is alone is gone through slice by slice."""
    n = len(at) - 1
    if n == 1 and len(data) > SLICE_BYTES:
        counts, seen = np.zeros((1, 8)), np.zeros(0, np.uint64)
        for a, b in slices(data, SLICE_BYTES):
            got, hashes, _ = _raw(data[a:b], np.array([0, b - a]))
            counts, seen = counts + got, np.unique(np.concatenate([seen, hashes]))
        distinct = np.array([len(seen)], float)
    else:
        counts, hashes, text = _raw(data, at)
        _, index = np.unique(hashes ^ (text.astype(np.uint64) * np.uint64(0x165667B19E3779F9)), return_index=True)
        distinct = np.bincount(text[index], minlength=n).astype(float)
    words, marks, capitals, letters, bars, ends, solid, breaks = counts.T
    per_word = np.maximum(words, 1)
    shares = [words, distinct / per_word, marks / per_word, capitals / np.maximum(capitals + letters, 1), bars / per_word]
    return np.stack([*shares, ends / per_word, np.maximum(solid, 1) / per_word, breaks / per_word], 1)


def votes(stats: np.ndarray) -> np.ndarray:
    """Votes of the labellers (columns) on each text (rows).

    Five look for one fault each and have nothing to say where it is absent. Four judge several traits that
    overlap, and vote good, bad or, in between, nothing.
    """
    words, distinct, marks, capitals, bars, ends, size, lines = stats.T
    long = words >= 20
    spread = np.where(words > 400, 0.12, 0.3)
    varied, dull = ~long | (distinct >= spread), long & (distinct < spread * 0.7)
    odd, far = long & ((ends < 0.005) | (ends > 0.7)), (size < 2) | (size > 20)
    tidy = varied & (marks < 0.1) & (capitals < 0.2) & (bars < 0.02)
    sized = (words >= 10) & (size >= 2.5) & (size <= 15)
    single = [words < 6, dull, marks > 0.4, capitals > 0.5, bars > 0.2]
    faults = np.sum([*single, odd, far, lines > 0.5], 0)
    several = [
        (tidy, dull | (capitals > 0.5)),
        (tidy & (ends < 0.6), (marks > 0.4) | (bars > 0.2) | odd),
        (tidy & sized & (lines < 0.3), (words < 6) | far | (lines > 0.5)),
        (tidy & sized & (ends < 0.6), faults >= 2),
    ]
    cast = [np.where(bad, BAD, ABSTAIN) for bad in single] + [np.where(bad, BAD, np.where(good, GOOD, ABSTAIN)) for good, bad in several]
    return np.stack(cast, 1).astype(np.int64)


def pattern(v: np.ndarray) -> np.ndarray:
    return v @ (3 ** np.arange(v.shape[1]))


def patterns_to_votes(codes: np.ndarray, labellers: int = len(LABELLERS)) -> np.ndarray:
    return codes[:, None] // 3 ** np.arange(labellers) % 3


def label_model(v: np.ndarray, counts: np.ndarray, rounds: int = 200, start_good: float = 0.7) -> dict[str, np.ndarray]:
    """EM for the chance of each vote given good or bad, votes independent given the class.

    It starts from labellers that are right in 80 of 100 votes, so classes keep their meaning; counts of one
    are added, so no chance is zero.
    """
    m = v.shape[1]
    chance = np.zeros((2, m, 3))
    cast = np.array([(v == k).T @ counts for k in range(3)]).T / max(counts.sum(), 1)
    for c in (0, 1):
        right, wrong = 1 + c, 2 - c
        chance[c, :, ABSTAIN] = cast[:, ABSTAIN]
        chance[c, :, right], chance[c, :, wrong] = 0.8 * (1 - cast[:, ABSTAIN]) + 1e-6, 0.2 * (1 - cast[:, ABSTAIN]) + 1e-6
    good, before = start_good, -np.inf
    for _ in range(rounds):
        logs = np.stack([np.log(np.maximum(chance[c], 1e-12))[np.arange(m), v].sum(1) for c in (0, 1)], 1) + np.log([1 - good, good])
        top = logs.max(1, keepdims=True)
        whole = top[:, 0] + np.log(np.exp(logs - top).sum(1))
        post = np.exp(logs - whole[:, None])
        weight = post * counts[:, None]
        good = float(np.clip((weight[:, 1].sum() + 1) / (counts.sum() + 2), 1e-4, 1 - 1e-4))
        for c in (0, 1):
            chance[c] = np.stack([(v == k).T @ weight[:, c] for k in range(3)], 1) + 1
            chance[c] /= chance[c].sum(1, keepdims=True)
        now = float(whole @ counts)
        if now - before < 1e-7 * abs(now):
            break
        before = now
    accuracy = np.array([[chance[c, j, 1 + c] / max(chance[c, j, BAD] + chance[c, j, GOOD], 1e-12) for c in (0, 1)] for j in range(m)])
    return {"posterior": post[:, 1], "accuracy": accuracy, "good": np.array(good)}


def _triplets(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Counts of hashed byte triplets of each text."""
    n = len(at) - 1
    if len(data) < 3:
        return np.zeros((n, HASHED), np.int64)
    wide = data.astype(np.uint32)
    x = (wide[:-2] | wide[1:-1] << np.uint32(8) | wide[2:] << np.uint32(16)) * np.uint32(0x9E3779B1)
    x ^= x >> np.uint32(15)
    x = (x * np.uint32(0x85EBCA77)) >> np.uint32(32 - int(np.log2(HASHED)))
    if n == 1:
        return np.bincount(x, minlength=HASHED).reshape(1, HASHED)
    text = np.repeat(np.arange(n, dtype=np.int64), np.diff(at))
    inside = text[:-2] == text[2:]
    return np.bincount((text[:-2] * HASHED + x)[inside], minlength=n * HASHED).reshape(n, HASHED)


def features(data: np.ndarray, at: np.ndarray, stats: np.ndarray) -> np.ndarray:
    """Square roots of hashed byte-triplet shares, and squashed statistics."""
    n = len(at) - 1
    out = np.zeros((n, HASHED + _STATS + 1), np.float32)
    if n == 1 and len(data) > SLICE_BYTES:
        parts = [data[a : a + SLICE_BYTES + 2] for a in range(0, len(data), SLICE_BYTES)]
        counts = sum(_triplets(x, np.array([0, len(x)])) for x in parts)
    else:
        counts = _triplets(data, at)
    out[:, :HASHED] = np.sqrt(counts / np.maximum(counts.sum(1, keepdims=True), 1))
    out[:, HASHED : HASHED + _STATS] = np.stack([np.log1p(stats[:, 0]) / 10, stats[:, 1], *(np.minimum(stats[:, k], 2) for k in (2, 3, 4, 5)), np.minimum(stats[:, 6], 20) / 10, np.minimum(stats[:, 7], 1)], 1)
    out[:, -1] = 1
    return out


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 300, rate: float = 2.0, decay: float = 1e-4) -> np.ndarray:
    """Logistic weights for soft labels, by full gradients with momentum."""
    w, speed = np.zeros(x.shape[1], np.float64), np.zeros(x.shape[1], np.float64)
    for _ in range(rounds if len(x) else 0):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        speed = 0.9 * speed - rate * (x.T @ (p - y) / len(x) + decay * w)
        w += speed
    return w


def _judged(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id and vote pattern of every row."""
    kind = dict(docs.dtypes)[id_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column(1))
            codes = [pattern(votes(statistics(data[at[a] : at[b]], at[a : b + 1] - at[a]))) for a, b in spans(at, BLOCK_BYTES)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(codes) if codes else np.zeros(0, np.int64))], ["doc_id", "pattern"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(kernel, f"doc_id {kind}, pattern bigint")


def train(docs: DataFrame, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> dict[str, np.ndarray]:
    """Pattern posteriors from counts over all documents, and scorer weights from the bounded sample."""
    rows = _judged(docs, id_col, text_col).groupBy("pattern").agg(F.count(F.lit(1)).alias("n")).collect()  # at most PATTERNS rows
    codes, counts = np.array([r["pattern"] for r in rows], np.int64), np.array([r["n"] for r in rows], np.float64)
    order = np.argsort(codes)
    codes, counts = codes[order], counts[order]
    posterior = np.full(PATTERNS, 0.5)
    if not len(codes):
        return {"posterior": posterior, "weights": np.zeros(HASHED + _STATS + 1), "accuracy": np.zeros((len(LABELLERS), 2))}
    model = label_model(patterns_to_votes(codes), counts)
    posterior[codes] = model["posterior"]
    key = F.xxhash64(F.col(id_col), F.lit(17))
    chosen = docs.select(F.col(id_col).alias("doc_id"), key.alias("k")).orderBy("k", "doc_id").limit(sample).agg(F.max("k").alias("k")).first()["k"]
    some = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).filter(F.xxhash64("doc_id", F.lit(17)) <= chosen)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column(1))
            for a, b in spans(at, BLOCK_BYTES):
                block, cut = data[at[a] : at[b]], at[a : b + 1] - at[a]
                stats = statistics(block, cut)
                x = features(block, cut, stats).astype(np.float16)
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array(posterior[pattern(votes(stats))]), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "y", "x"])

    kind = dict(docs.dtypes)[id_col]
    got = some.mapInArrow(kernel, f"doc_id {kind}, y double, x binary").orderBy(F.xxhash64("doc_id", F.lit(17)), "doc_id", "x").limit(sample).collect()
    x = np.stack([np.frombuffer(r["x"], np.float16) for r in got]).astype(np.float32)
    return {"posterior": posterior, "weights": fit(x, np.array([r["y"] for r in got])), "accuracy": model["accuracy"]}


def classify(docs: DataFrame, threshold: float = 0.5, sample: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_votes, posterior, score (0 to 1) and kept for every row."""
    model = train(docs, sample, id_col, text_col)
    posterior, weights = model["posterior"], model["weights"]
    kind = dict(docs.dtypes)[id_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column(1))
            for a, b in spans(at, BLOCK_BYTES):
                block, cut = data[at[a] : at[b]], at[a : b + 1] - at[a]
                stats = statistics(block, cut)
                v = votes(stats)
                score = 1 / (1 + np.exp(-np.clip(features(block, cut, stats) @ weights, -30, 30)))
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array((v != ABSTAIN).sum(1)), pa.array(posterior[pattern(v)]), pa.array(score), pa.array(score >= threshold)], ["doc_id", "n_votes", "posterior", "score", "kept"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(kernel, f"doc_id {kind}, n_votes bigint, posterior double, score double, kept boolean")
