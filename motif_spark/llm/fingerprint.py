"""Quartile bucket digests of documents and their comparison.

Byte triplets (three shapes within five bytes) are hashed into 256 buckets; the digest holds for each bucket
the quartile of its count, with the text's length on a logarithmic scale and the quartiles' ratios. Two
digests differ by a sum of bucket steps, length and ratio steps, bounded by MOST.

Defined cases: a null or empty text has no triplets and the digest of zeros; texts under three bytes likewise
but for their length; rows that repeat an id follow each other ordered by text; a null id comes after all
others in descending order; an empty table gives an empty result; a lone document is its own successor; a very
long text is counted in slices; counts at a quartile fall below it; extra columns are left out, so their names do
not matter.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NO_ID, code_points, cuts, ids, known_ids, parts_for, spans, utf8

BUCKETS = 256
SHAPES = ((0, 1, 2), (0, 1, 3), (0, 2, 4))
#: Difference at which two digests share nothing; about that of unrelated random digests.
MOST = 416
#: Steps between quartile codes 0 to 3 apart.
STEPS = np.array([0, 1, 2, 6], np.int64)
PART_BYTES = 8 << 20
BLOCK_BYTES = 1 << 20
#: A longer text is gone through in slices of this size.
SLICE_BYTES = 4 << 20


def _counts(data: np.ndarray, offsets: np.ndarray, whole: int) -> np.ndarray:
    """Bucket counts of the triplets that begin among the first `whole` bytes and stay in their text."""
    n = len(offsets) - 1
    counts = np.zeros(n * BUCKETS, np.int64)
    wide = data.astype(np.uint32)
    if n > 1:
        text = np.repeat(np.arange(n, dtype=np.int64) * BUCKETS, np.diff(offsets))
        end = np.repeat(offsets[1:], np.diff(offsets))
    for salt, (a, b, c) in enumerate(SHAPES):
        m = min(whole, len(data) - c)
        if m <= 0:
            continue
        x = wide[a : m + a] | wide[b : m + b] << np.uint32(8) | wide[c : m + c] << np.uint32(16)
        x *= np.uint32(0x9E3779B1)
        x ^= x >> np.uint32(15)
        x *= np.uint32(0x85EBCA77 + 2 * salt)
        x >>= np.uint32(24)
        if n > 1:
            x = (text[:m] + x)[np.arange(m) + c < end[:m]]
        counts += np.bincount(x, minlength=n * BUCKETS)
    return counts


def digests(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Header (length code, two ratio codes) and bucket codes 0..3 of each text; a lone long text in slices."""
    n = len(offsets) - 1
    if n == 1 and len(data) > SLICE_BYTES:
        reach = max(c for _, _, c in SHAPES)
        starts = range(0, len(data), SLICE_BYTES)
        parts = ((data[a : a + SLICE_BYTES + reach], min(SLICE_BYTES, len(data) - a)) for a in starts)
        counts = sum(_counts(x, np.array([0, len(x)]), m) for x, m in parts)
    else:
        counts = _counts(data, offsets, len(data))
    counts = counts.reshape(n, BUCKETS)
    ordered = np.sort(counts, axis=1)
    q1, q2, q3 = (ordered[:, k * BUCKETS // 4 - 1] for k in (1, 2, 3))
    codes = (counts > q1[:, None]).astype(np.uint8) + (counts > q2[:, None]) + (counts > q3[:, None])
    size = np.diff(offsets)
    length = np.minimum(255, np.round(np.log(np.maximum(size, 1)) / np.log(1.25)) + (size > 0)).astype(np.uint8)
    top = np.maximum(q3, 1)
    header = np.stack([length, (q1 * 15 // top).astype(np.uint8) << 4 | (q2 * 15 // top).astype(np.uint8)], 1)
    return header, codes


def as_text(header: np.ndarray, codes: np.ndarray) -> list[str]:
    """Hexadecimal digests: two bytes of header and two bits for each bucket."""
    four = codes.reshape(len(codes), -1, 4)
    body = four[:, :, 0] << 6 | four[:, :, 1] << 4 | four[:, :, 2] << 2 | four[:, :, 3]
    whole = np.ascontiguousarray(np.concatenate([header, body], 1))
    return [row.tobytes().hex() for row in whole]


def difference(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Bounded difference of digests, row by row."""
    apart = np.abs(a[1].astype(np.int8) - b[1].astype(np.int8))
    ratio = lambda h, s: (h[:, 1] >> s & 15).astype(np.int64)
    other = np.abs(a[0][:, 0].astype(np.int64) - b[0][:, 0]) + sum(np.abs(ratio(a[0], s) - ratio(b[0], s)) for s in (0, 4))
    return np.minimum(STEPS[apart].sum(1) + other, MOST)


def likeness(a, b) -> np.ndarray:
    return 1.0 - difference(a, b) / MOST


def parse(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Digests from their hexadecimal form."""
    raw = np.frombuffer(b"".join(map(bytes.fromhex, texts)), np.uint8).reshape(len(texts), 2 + BUCKETS // 4)
    body = raw[:, 2:, None] >> np.array([6, 4, 2, 0], np.uint8) & 3
    return raw[:, :2], body.reshape(len(texts), BUCKETS)


def _of(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    at = np.concatenate([[0], np.cumsum([len(t) for t in texts], dtype=np.int64)])
    found = [digests(np.frombuffer(b"".join(texts[a:b]), np.uint8), at[a : b + 1] - at[a]) for a, b in spans(at, BLOCK_BYTES)]
    none = (np.zeros((0, 2), np.uint8), np.zeros((0, BUCKETS), np.uint8))
    return tuple(np.concatenate([f[k] for f in found]) if found else none[k] for k in (0, 1))


def edit(text: str, following: str) -> str:
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_chars, fingerprint for every row, without a shuffle."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, at = utf8(batch.column(1))
            for a, b in spans(at, BLOCK_BYTES):
                block, cut = data[at[a] : at[b]], at[a : b + 1] - at[a]
                yield pa.RecordBatch.from_arrays([batch.column(0)[a:b], pa.array(code_points(block, cut)), pa.array(as_text(*digests(block, cut)))], ["doc_id", "n_chars", "fingerprint"])

    kind = dict(docs.dtypes)[id_col]
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(kernel, f"doc_id {kind}, n_chars bigint, fingerprint string")


def _places(bounds: np.ndarray, halo: dict[int, int]):
    """Pandas UDF: twice the range of the id; for a range's largest id also its place as another's successor."""

    @F.pandas_udf("array<int>")
    def places(key):
        import numpy as np
        import pandas as pd

        key = key.to_numpy().astype(np.int64)
        at = np.searchsorted(bounds, key, "right") * 2
        return pd.Series([[a, halo[k] * 2 + 1] if k in halo else [a] for k, a in zip(key.tolist(), at.tolist())])

    return places


def _kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]

    def out(ids_: np.ndarray, texts: list[bytes]) -> pa.RecordBatch:
        """texts: the documents and after them the successor of the last."""
        plain = [t.decode() for t in texts]
        edited = [edit(a, b).encode() for a, b in zip(plain, plain[1:])]
        header, codes = _of(texts)
        mine, following, changed = (header[:-1], codes[:-1]), (header[1:], codes[1:]), _of(edited)
        return pa.RecordBatch.from_arrays([
            known_ids(ids_), pa.array([len(t) for t in plain[:-1]], pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in edited], pa.string()),
            pa.array(as_text(*mine), pa.string()), pa.array(as_text(*changed), pa.string()), pa.array(likeness(mine, changed)), pa.array(likeness(mine, following)),
        ], names)

    held_id, held = np.zeros(0, np.int64), []
    for batch in batches:
        kind = batch.column(0).to_numpy(zero_copy_only=False)
        key, (data, at) = ids(batch.column(1)), utf8(batch.column(2))
        for a, b in spans(at, BLOCK_BYTES):
            if len(held_id) == 0 and kind[a] % 2:
                return
            texts = [data[at[k] : at[k + 1]].tobytes() for k in range(a, b)]
            real = int((kind[a:b] % 2 == 0).sum())
            key_ = np.concatenate([held_id, key[a : a + real]])
            whole = held + texts
            end = min(len(whole), len(key_) + 1)
            if end == len(key_) + 1:
                yield out(key_, whole[:end])
                return
            if len(key_) > 1:
                yield out(key_[:-1], whole[: len(key_)])
            held_id, held = key_[-1:], whole[len(key_) - 1 : len(key_)]


def compare_with_edits(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for every row.

    The successor is the next document in descending id, after the last the first. Ids are cut into ranges;
    each range's rows are read in order, with a copy of the one row that follows them.
    """
    df = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    parts = parts_for(df, PART_BYTES)
    bounds = cuts(df, "doc_id", parts)
    top = F.pandas_udf(lambda key: __import__("pandas").Series(np.searchsorted(bounds, key.to_numpy(), "right")), "int")
    most = {r["p"]: r["m"] for r in df.select("doc_id").withColumn("p", top("doc_id")).groupBy("p").agg(F.max("doc_id").alias("m")).collect()}
    full = sorted(most)
    halo = {most[low]: high for low, high in zip(full, full[1:])} | ({most[full[-1]]: full[0]} if full else {})
    dealt = df.withColumn("kind", F.explode(_places(bounds, halo)("doc_id"))).select("kind", "doc_id", "text")
    dealt = dealt.repartitionById(max(1, len(full) and full[-1] + 1), F.floor(F.col("kind") / 2).cast("int"))
    ordered = dealt.sortWithinPartitions(F.col("kind") % 2, F.desc("doc_id"), "text")
    return ordered.mapInArrow(_kernel, "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
