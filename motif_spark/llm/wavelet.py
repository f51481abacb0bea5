"""Token ids of a corpus as one wavelet matrix per shard, written to and read from files.

A shard is a range of document ids. Its token ids become bit planes from the highest bit down, each
followed by a stable partition, zeros first; counts of ones every SAMPLE bits give rank and select. The file
of a shard is a Parquet file of one row: planes, samples, zeros of each plane, and the document table, so
any store that Spark writes can hold it. One file answers access, count and occurrence lookup.

Defined cases: a null or empty text has only the end id; rows that repeat an id follow each other ordered
by text; rows with a null id come first; an empty table writes no shard and gives an empty result.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import NO_ID, cuts, freeing, ids, known_ids, parts_for, shared_folder
from .tokens import coder

END = 1
SHARD_BYTES = 16 << 20
SAMPLE = 512
FILE = "shard int, n bigint, zeros array<bigint>, planes array<binary>, samples array<binary>, doc_ids binary, doc_tokens binary"


class WaveletMatrix:
    """Bit planes of a sequence of unsigned numbers with rank and select."""

    def __init__(self, n: int, planes: list[np.ndarray], samples: list[np.ndarray], zeros: list[int]):
        self.n, self.planes, self.samples, self.zeros = n, planes, samples, zeros

    @classmethod
    def build(cls, values: np.ndarray) -> WaveletMatrix:
        top = int(values.max()) if len(values) else 0
        kind = np.uint16 if top < 1 << 16 else np.uint32
        cur, planes, samples, zeros = values.astype(kind), [], [], []
        for shift in range(max(1, top.bit_length()) - 1, -1, -1):
            bit = (cur & kind(1 << shift)) != 0
            plane = np.packbits(bit, bitorder="little")
            plane = np.concatenate([plane, np.zeros(-len(plane) % (SAMPLE // 8), np.uint8)])
            ones = np.bitwise_count(plane.view(np.uint64)).reshape(-1, SAMPLE // 64).sum(1, dtype=np.uint32)
            samples.append(np.concatenate([[0], np.cumsum(ones)]).astype(np.uint32))
            planes.append(plane)
            low = cur[~bit]
            zeros.append(len(low))
            cur = np.concatenate([low, cur[bit]])
        return cls(len(values), planes, samples, zeros)

    def rank1(self, level: int, i: int) -> int:
        """Ones of a plane before place i."""
        block = i // SAMPLE
        part = self.planes[level][block * SAMPLE // 8 : (i + 7) // 8]
        bits = np.unpackbits(part, bitorder="little")[: i - block * SAMPLE]
        return int(self.samples[level][block]) + int(bits.sum())

    def select(self, level: int, bit: int, k: int) -> int:
        """Place of the k-th (from 0) one or zero of a plane."""
        s = self.samples[level].astype(np.int64)
        if not bit:
            s = np.arange(len(s)) * SAMPLE - s
        block = int(np.searchsorted(s, k, "right")) - 1
        bits = np.unpackbits(self.planes[level][block * SAMPLE // 8 : (block + 1) * SAMPLE // 8], bitorder="little")
        return block * SAMPLE + int(np.flatnonzero(bits == bit)[k - s[block]])

    def access(self, i: int) -> int:
        value = 0
        for level, zeros in enumerate(self.zeros):
            bit = int(self.planes[level][i >> 3] >> (i & 7) & 1)
            ones = self.rank1(level, i)
            i = zeros + ones if bit else i - ones
            value = value << 1 | bit
        return value

    def _range(self, value: int, i: int) -> tuple[int, int]:
        a, b = 0, i
        if value >> len(self.zeros):
            return 0, 0
        for level, zeros in enumerate(self.zeros):
            x, y = self.rank1(level, a), self.rank1(level, b)
            a, b = (zeros + x, zeros + y) if value >> (len(self.zeros) - 1 - level) & 1 else (a - x, b - y)
        return a, b

    def count(self, value: int, i: int | None = None) -> int:
        """Occurrences of the value before place i."""
        a, b = self._range(value, self.n if i is None else i)
        return b - a

    def occurrence(self, value: int, k: int) -> int:
        """Place of the k-th (from 0) occurrence of the value; -1 if there is none."""
        a, b = self._range(value, self.n)
        if k >= b - a:
            return -1
        i = a + k
        for level in range(len(self.zeros) - 1, -1, -1):
            bit = value >> (len(self.zeros) - 1 - level) & 1
            i = self.select(level, bit, i - self.zeros[level] if bit else i)
        return i

    def decode(self) -> np.ndarray:
        """All values in order, from the lowest plane up."""
        kind = np.uint16 if len(self.zeros) <= 16 else np.uint32
        cur = np.zeros(self.n, kind)
        for shift, level in enumerate(range(len(self.zeros) - 1, -1, -1)):
            bit = np.unpackbits(self.planes[level], count=self.n, bitorder="little").view(bool)
            out = np.empty(self.n, kind)
            out[~bit] = cur[: self.zeros[level]]
            out[bit] = cur[self.zeros[level] :] | kind(1 << shift)
            cur = out
        return cur


def _squeeze(x: np.ndarray) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(x.tobytes())


def _open(x: bytes, kind) -> np.ndarray:
    import zstandard

    return np.frombuffer(zstandard.ZstdDecompressor().decompress(x), kind)


def load(row: dict) -> tuple[WaveletMatrix, np.ndarray, np.ndarray]:
    """Matrix, document ids and their token counts of one shard's row."""
    planes = [_open(p, np.uint8) for p in row["planes"]]
    matrix = WaveletMatrix(row["n"], planes, [_open(s, np.uint32) for s in row["samples"]], list(row["zeros"]))
    return matrix, _open(row["doc_ids"], np.int64), _open(row["doc_tokens"], np.int64)


def _encode(path: str, end_id: int):
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = coder(path), np.array([end_id], "<u4")
        shard, keys, sizes, parts = None, [], [], []
        for batch in batches:
            if not batch.num_rows:
                continue
            shard = batch.column(0)[0].as_py()
            keys.append(ids(batch.column(1)))
            for own in encode(batch.column(2)):
                sizes.append(len(own) + 1)
                parts += [own, end.astype(own.dtype)] if end_id < 1 << 16 else [own, end]
        if shard is None:
            return
        matrix = WaveletMatrix.build(np.concatenate(parts))
        row = {"shard": shard, "n": matrix.n, "zeros": matrix.zeros, "planes": [_squeeze(p) for p in matrix.planes], "samples": [_squeeze(s) for s in matrix.samples], "doc_ids": _squeeze(np.concatenate(keys)), "doc_tokens": _squeeze(np.array(sizes, np.int64))}
        schema = pa.schema([("shard", pa.int32()), ("n", pa.int64()), ("zeros", pa.list_(pa.int64())), ("planes", pa.list_(pa.binary())), ("samples", pa.list_(pa.binary())), ("doc_ids", pa.binary()), ("doc_tokens", pa.binary())])
        yield pa.RecordBatch.from_pylist([row], schema=schema)

    return kernel


def write(docs: DataFrame, folder: str, tokenizer: str, end_id: int = END, id_col: str = "doc_id", text_col: str = "text") -> None:
    """One file for each range of document ids, in ascending order of shards and of documents in them."""
    df = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    bounds = cuts(df, "doc_id", parts_for(df, SHARD_BYTES))
    shard = F.pandas_udf(lambda key: __import__("pandas").Series(np.searchsorted(bounds, key.to_numpy(), "right")), "int")
    dealt = df.withColumn("shard", shard("doc_id")).select("shard", "doc_id", "text").repartitionById(len(bounds) + 1, "shard")
    dealt.sortWithinPartitions("doc_id", "text").mapInArrow(freeing(_encode(tokenizer, end_id)), FILE).write.parquet(folder)


def read(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files. Only the shards' sizes reach the driver."""
    files = spark.read.schema(FILE).parquet(folder)
    sizes = sorted((r["shard"], r["n"]) for r in files.select("shard", "n").collect())
    before = dict(zip([s for s, _ in sizes], np.concatenate([[0], np.cumsum([n for _, n in sizes])]).tolist()))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                matrix, doc_ids, counts = load(row)
                values = matrix.decode().astype("<u4")
                at = np.concatenate([[0], np.cumsum(counts)])
                crc = [zlib.crc32(values[a:b]) for a, b in zip(at, at[1:])]
                yield pa.RecordBatch.from_arrays([known_ids(doc_ids), pa.array(at[:-1] + before[row["shard"]]), pa.array(counts), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.mapInArrow(kernel, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = END) -> DataFrame:
    """write() to a new folder beside the checkpoints, then read()."""
    spark = docs.sparkSession
    folder = f"{shared_folder(spark)}/wavelet-{uuid.uuid4().hex}"
    write(docs, folder, tokenizer, end_id)
    return read(spark, folder)
