"""Shared helpers of the training-data operators.

Text columns reach Python as Arrow buffers and are worked on as byte arrays; order-dependent operators
cut the document order into ranges whose bounds (not rows) reach the driver.
"""

from __future__ import annotations

import math
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space that ends a word: space and U+0009 to U+000D.
SPACE = r"[\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint(df: DataFrame) -> DataFrame:
    """Cut the lineage in the folder of spark.checkpoint.dir; a folder of our own only where none is set."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def words(text: Column) -> Column:
    """Words of the text, split at ASCII white space; null gives an empty array."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")


def ascii_lower(text: Column) -> Column:
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def code_points(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Code points of each text: its bytes that continue none."""
    starts = np.zeros(len(data) + 1, np.int64)
    np.cumsum((data & 0xC0) != 0x80, out=starts[1:])
    return starts[offsets[1:]] - starts[offsets[:-1]]


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts and len + 1 offsets, without copying them; null counts as empty."""
    column = pc.fill_null(column, "" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    if offsets is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    got = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] else np.zeros(0, np.uint8)
    return got, at - at[0]


def spans(offsets: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Consecutive runs of texts of about `most` bytes; a longer text is a run of its own."""
    k, n = 0, len(offsets) - 1
    while k < n:
        end = max(k + 1, int(np.searchsorted(offsets, offsets[k] + most, "right")) - 1)
        yield k, min(end, n)
        k = end


def slices(data: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Consecutive slices of about `most` bytes that end after white space; one without any is whole."""
    a, n = 0, len(data)
    while a < n:
        b = a + most
        while b < n:
            blank = np.flatnonzero((data[b : b + most] == 32) | (data[b : b + most] - 9 < 5))
            if len(blank):
                b += int(blank[0]) + 1
                break
            b += most
        yield a, min(b, n)
        a = min(b, n)


def cuts(df: DataFrame, key: str, parts: int) -> np.ndarray:
    """At most parts - 1 ascending bounds that deal the rows about evenly by key. Only bounds reach the driver."""
    probs = [k / parts for k in range(1, parts)]
    if not probs:
        return np.zeros(0, np.int64)
    found = df.select(F.percentile_approx(F.col(key), probs, 20 * parts).alias("q")).first()["q"]
    return np.unique(np.array([x for x in found or [] if x is not None], np.int64))


#: A key with more than this share of all rows, and this many at least, is hot; so at most 1 / HOT_SHARE keys are.
HOT_SHARE, HOT_ROWS = 0.001, 100_000


def hot_salts(counts: DataFrame, key: str) -> Column:
    """From rows of a key column and n (rows that have the key): into how many salts a key's rows are dealt, 1 for most.

    Only hot keys reach the driver, 1,000 at most by their share.
    """
    total = counts.agg(F.sum("n")).first()[0] or 0
    most = max(HOT_ROWS, total * HOT_SHARE)
    hot = {r[key]: math.ceil(r["n"] / most) for r in counts.filter(F.col("n") > most).select(key, "n").collect()}
    salts = F.lit(1)
    if None in hot:
        salts = F.when(F.col(key).isNull(), F.lit(hot.pop(None))).otherwise(salts)
    if hot:
        known = F.create_map(*[F.lit(x) for pair in hot.items() for x in pair])
        salts = F.coalesce(F.try_element_at(known, F.col(key)), salts)
    return salts.cast("int")


def release() -> None:
    """Give freed memory back to the system: workers are kept for later stages, whose share it would be."""
    import ctypes

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def freeing(kernel):
    """The kernel over batches, with its memory released at the end of each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from kernel(batches)
        release()

    return run


NO_ID = -(2**63)


def ids(column: pa.Array) -> np.ndarray:
    """Document ids; null becomes the least number, so such rows come before all others."""
    return column.cast(pa.int64()).fill_null(NO_ID).to_numpy(zero_copy_only=False)


def known_ids(x: np.ndarray) -> pa.Array:
    return pa.array(x, pa.int64(), mask=x == NO_ID)


def parts_for(docs: DataFrame, part_bytes: int, text_col: str = "text") -> int:
    """Parts of about part_bytes of text, from the size of the plan's files; where that is unknown, from the texts."""
    known = int(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    size = 2 * known if 0 < known < 1 << 50 else docs.agg(F.sum(F.octet_length(text_col))).first()[0] or 0
    return max(partitions(docs.sparkSession), math.ceil(size / part_bytes))


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder, which all executors share; only a local master may do without spark.checkpoint.dir."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = sc.getConf().get("spark.checkpoint.dir")
        if not folder and not (sc.master.startswith("local") and "cluster" not in sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()
