"""Stream operators run over the events that are there, as streams, beside batch SQL of what they must say."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import learning
from ..operators import network as net
from ..streaming import motifs as M
from .class_queries import classes
from .graph_queries import EVENT_LABELS, SESSION

QUERIES, SQL = {}, {}
STATE = "spark.sql.streaming.stateStore.providerClass"
ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


def _events(spark: SparkSession, sf_dir: str, late: str = "60 days") -> DataFrame:
    return M.event_stream(spark, f"{sf_dir}/events.parquet*", late)


def _table(df: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's rows, from a folder beside the checkpoints; complete results through a memory table."""
    if mode == "append":
        return M.run_to_files(df)
    return M.run_once(df, f"stream_{uuid.uuid4().hex}", mode)


@query("SELECT CAST(time_bucket(INTERVAL 1 HOUR, ts) AS VARCHAR) AS start, event_type, count(*) AS events FROM events GROUP BY 1, 2")
def s_stream_tumbling(spark, sf_dir):
    df = _table(M.windowed(_events(spark, sf_dir)), "complete")
    return df.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "events")


@query("SELECT CAST(time_bucket(INTERVAL 1 HOUR, ts) - k * INTERVAL 1 HOUR AS VARCHAR) AS start, event_type, count(*) AS events FROM events, (VALUES (0), (1)) AS t(k) GROUP BY 1, 2")
def s_stream_sliding(spark, sf_dir):
    df = _table(M.windowed(_events(spark, sf_dir), "2 hours", "1 hour"), "complete")
    return df.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "events")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
x AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS part FROM g) SELECT user_id, count(*) AS events FROM x GROUP BY user_id, part""")
def s_stream_sessions(spark, sf_dir):
    """As files: there is a session for every second event, more than a memory table on the driver holds."""
    return M.all_sessions(spark, f"{sf_dir}/events.parquet*", "60 days").select("user_id", "events")


@query("SELECT event_id, user_id FROM events")
def s_stream_once(spark, sf_dir):
    """Every event is sent twice; one of each is left."""
    twice = _events(spark, sf_dir).unionByName(_events(spark, sf_dir))
    return _table(M.once(twice).select("event_id", "user_id"))


@query("SELECT event_id, CAST(list_position(" + str(EVENT_LABELS) + ", event_type) - 1 AS INT) AS label_id FROM events")
def s_stream_labels(spark, sf_dir):
    labels = spark.createDataFrame([(x, i) for i, x in enumerate(EVENT_LABELS)], "event_type string, label_id int")
    return _table(M.with_labels(_events(spark, sf_dir), labels).select("event_id", "label_id"))


@query("SELECT a.user_id, CAST(a.ts AS VARCHAR) AS bought, CAST(b.ts AS VARCHAR) AS failed FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'error' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def s_stream_join(spark, sf_dir):
    """A user's errors within an hour of a purchase: two streams joined by key and time."""
    df = _table(M.purchase_then_error(_events(spark, sf_dir), _events(spark, sf_dir)))
    text = lambda c: F.regexp_replace(F.col(c).cast("string"), r"(\.\d*?)0+$", "$1").alias(c)
    return df.select("user_id", text("bought"), text("failed"))


@query(f"WITH {SESSION.replace('user_id * 10 + CASE WHEN day(ts) <= 15 THEN 0 ELSE 1 END', 'user_id')} SELECT x.graph_id AS user_id, CAST(count(*) AS BIGINT) AS closed FROM s x JOIN s y ON x.graph_id = y.graph_id AND y.node BETWEEN x.node + 1 AND x.node + 2 JOIN s z ON z.graph_id = x.graph_id AND z.node BETWEEN y.node + 1 AND y.node + 2 GROUP BY 1")
def s_stream_motifs(spark, sf_dir):
    """Three-node sets of every user's growing graph, counted event by event."""
    spark.conf.set(STATE, ROCKS)
    rows = _table(M.count_motifs(_events(spark, sf_dir), 3))
    return rows.groupBy("user_id").agg(F.sum("closed").alias("closed"))


@query(f"WITH {classes([3]).replace('user_id * 10 + CASE WHEN day(ts) <= 15 THEN 0 ELSE 1 END', 'user_id')} SELECT graph_id AS user_id, freq AS closed FROM classes")
def s_stream_motif_classes(spark, sf_dir):
    """The same by class: what was counted event by event is the census of the whole graph."""
    spark.conf.set(STATE, ROCKS)
    rows = _table(M.count_motifs(_events(spark, sf_dir), 3))
    return rows.groupBy("user_id", "code").agg(F.sum("closed").alias("closed")).select("user_id", "closed")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
x AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS part FROM g) SELECT user_id, CAST(3 AS INT) AS k, count(*) AS nodes FROM x GROUP BY user_id, part HAVING count(*) >= 3 AND max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events)""")
def s_stream_mine(spark, sf_dir):
    """Greedy search in every closed session's graph, once the watermark has passed its end."""
    config = net.Config(labels=len(EVENT_LABELS), width=8, layers=1)
    policy = learning.Policy(config, net.init(config, "actor", 1))
    mined = M.mine_closed_sessions(_events(spark, sf_dir, "0 seconds"), policy, [3], "6 hours")
    return mined.select("user_id", "k", "nodes")
