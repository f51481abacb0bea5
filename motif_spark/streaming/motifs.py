"""Event streams: windows with late rows, stream dedupe, joins, and an incremental motif counter."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
#: State outside the heap, of which a batch saves its changes alone.
STORE = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true",
}


def event_stream(spark: SparkSession, folder: str, late: str = "10 minutes", files: int = 1, end: str | None = None) -> DataFrame:
    """Parquet files of events as a stream; the zoneless time is cast, as watermarks need an instant.

    end is a glob where an end marker may appear (see all_sessions).
    """
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(folder)
    if end:
        raw = raw.unionByName(spark.readStream.schema(EVENTS).parquet(end))
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def windowed(events: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events by label in tumbling or sliding windows."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "events")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """A user's events less than the gap apart; Spark's own windows also take in an event that is exactly the gap away."""
    w = F.session_window("ts", f"{gap} -1 microseconds")
    end = F.col("w.end") + F.expr("interval 1 microsecond")
    return events.groupBy(w.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")).select("user_id", F.col("w.start").alias("start"), end.alias("end"), "events")


@contextmanager
def settings(spark: SparkSession, wanted: dict[str, str]) -> Iterator[None]:
    """Settings of the session for the streams that start meanwhile; put back afterwards."""
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def all_sessions(spark: SparkSession, source: str, late: str = "10 minutes", gap: str = "6 hours") -> DataFrame:
    """The sessions of all events that are there now, those still open included, by executors into Parquet files.

    Sessions that end under the watermark are written once, batch by batch. When the events have been read, an end
    marker (an event of nobody in the year 9999) moves the watermark past all of them, and a second run from the same
    progress writes those that were open. The marker's own session stays open and is never written.
    """
    from ..operators.graphs import shared_folder

    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    found = sessions(event_stream(spark, source, late, end=f"{folder}/end*"), gap)
    marker = {"ts": F.lit("9999-01-01").cast("timestamp_ntz")}
    columns = [marker.get(f.name, F.lit(None)).cast(f.dataType).alias(f.name) for f in StructType.fromDDL(EVENTS)]
    with settings(spark, STORE):
        run_to_files(found, folder)
        spark.range(1).select(*columns).write.parquet(f"{folder}/end")
        return run_to_files(found, folder)


def once(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def with_labels(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join to a label dictionary, broadcast if it is small."""
    from ..operators.graphs import LITERAL_LABELS

    small = dictionary.limit(LITERAL_LABELS + 1).count() <= LITERAL_LABELS
    return events.join(F.broadcast(dictionary) if small else dictionary, "event_type")


def purchase_then_error(events: DataFrame, errors: DataFrame, within: str = "1 hour") -> DataFrame:
    """Interval join of two streams: a user's errors after a purchase."""
    a = events.filter("event_type = 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("bought"))
    b = errors.filter("event_type = 'error'").select("user_id", F.col("ts").alias("failed"))
    return b.join(a, F.expr(f"user_id = u AND failed >= bought AND failed <= bought + interval {within}")).select("user_id", "bought", "failed")


class MotifCounter(StatefulProcessor):
    """Counts induced k-subgraphs of a user's growing session graph (each event joined to the next two).

    A k-set that ends at the new event picks gaps of one or two, so only the last 2 (k - 1) events are kept and
    an event closes at most 2^(k-1) sets. Rows are the classes closed by each batch with their counts.
    """

    def __init__(self, k: int, forget_ms: int = 0):
        self.k, self.forget_ms = k, forget_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.recent = handle.getListState("recent", "label string", ttlDurationMs=self.forget_ms or None)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values=None) -> Iterator[pd.DataFrame]:
        recent = [r[0] for r in self.recent.get()] if self.recent.exists() else []
        counts: dict[str, int] = {}
        for pdf in rows:
            for label in pdf.sort_values(["ts", "event_id"])["event_type"]:
                recent.append(label)
                for code in closed(recent, self.k):
                    counts[code] = counts.get(code, 0) + 1
                recent = recent[-2 * (self.k - 1) :]
        self.recent.put([(x,) for x in recent])
        yield pd.DataFrame({"user_id": [key[0]] * len(counts), "code": list(counts), "closed": list(counts.values())})

    def close(self) -> None:
        pass


def closed(recent: list[str], k: int) -> Iterator[str]:
    """Codes of the k-sets that end at the last event; labels are numbered in their order."""
    from itertools import product

    from ..operators.canonical import canonical_of

    names = {x: i for i, x in enumerate(sorted(("click", "error", "purchase", "signup", "view")))}
    last = len(recent) - 1
    for gaps in product((1, 2), repeat=k - 1):
        places = [last]
        for g in gaps:
            places.append(places[-1] - g)
        if places[-1] < 0:
            continue
        places.reverse()
        bits = 0
        for i in range(k):
            for j in range(i + 1, k):
                bits = bits << 1 | (places[j] - places[i] <= 2)
        yield canonical_of(tuple(names.get(recent[p], len(names)) for p in places), bits)[0]


def count_motifs(events: DataFrame, k: int = 3, forget_ms: int = 0) -> DataFrame:
    """user_id, code, closed, as updates; needs the RocksDB state store.

    With forget_ms the last events of a user who is silent for that long (by the clock) are dropped, so state is
    bounded by active users; sets across such a silence are then not counted.
    """
    rows = events.select("user_id", "event_id", "ts", "event_type")
    mode = "ProcessingTime" if forget_ms else "None"
    return rows.groupBy("user_id").transformWithStateInPandas(MotifCounter(k, forget_ms), "user_id long, code string, closed long", "Append", mode)


def run_once(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what is there now, into a memory table."""
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def run_to_files(df: DataFrame, folder: str | None = None) -> DataFrame:
    """Runs a stream over what is there now into Parquet files, exactly once, in a folder that all executors share."""
    from ..operators.graphs import shared_folder

    spark = df.sparkSession
    folder = folder or f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    sink = df.writeStream.format("parquet").option("path", f"{folder}/rows").option("checkpointLocation", f"{folder}/progress")
    sink.outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows")


def mine_closed_sessions(events: DataFrame, policy, sizes: list[int], gap: str = "6 hours", folder: str | None = None) -> DataFrame:
    """Greedy search in the graph of every closed session: user_id, start, k, nodes, members.

    A session's events are gathered by the stream and given out once the watermark has passed its end, so no
    batch sees a part of it and sessions that are still open give no row yet; a session is bounded by its user's
    events without a break. Sessions of fewer than k nodes have no answer.
    """
    w = F.session_window("ts", gap)
    item = F.struct("ts", "event_id", "event_type")
    closed_rows = events.groupBy(w.alias("w"), "user_id").agg(F.sort_array(F.collect_list(item)).alias("e"))
    rows = run_to_files(closed_rows.select("user_id", F.col("w.start").alias("start"), F.col("e.event_type").alias("labels")), folder)
    return mine_sessions(rows, policy, sizes)


def mine_sessions(rows: DataFrame, policy, sizes: list[int]) -> DataFrame:
    """Greedy search in the graphs of rows user_id, start, labels (in time order), batch by batch."""
    from ..operators.learning import mine_all

    names = F.array(*[F.lit(x) for x in sorted(("click", "error", "purchase", "signup", "view"))])
    n = F.size("labels")
    near = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.filter(F.array(i - 2, i - 1, i + 1, i + 2), lambda j: (j >= 0) & (j < n)))
    labels = F.transform("labels", lambda x: (F.array_position(names, x) - 1).cast("int"))
    key = F.xxhash64("user_id", "start")
    graphs = rows.filter(n >= min(sizes)).select(key.alias("graph_id"), "user_id", "start", n.alias("nodes"), labels.alias("label_ids"), near.alias("nbrs"))
    found = mine_all(graphs, sizes, policy).filter("not dead")
    return graphs.select("graph_id", "user_id", "start", "nodes").join(found, "graph_id").select("user_id", "start", "k", F.col("nodes").cast("long").alias("nodes"), "members")
