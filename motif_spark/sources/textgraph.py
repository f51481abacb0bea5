"""Graph collections as text: the public layout of five files with one value or pair in each line.

NAME_A.txt has "u, v" over node numbers that run through all graphs from 1, NAME_graph_indicator.txt the
graph of each node, NAME_node_labels.txt its label. Registered as the batch source and sink "textgraph".
"""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from ..operators.graphs import normalize_edges

NODES = "node long, graph_id long, label string"


class TextGraphSource(DataSource):
    """Options: path, name, part (nodes or edges)."""

    @classmethod
    def name(cls) -> str:
        return "textgraph"

    def schema(self) -> str:
        return NODES if self.options.get("part", "nodes") == "nodes" else "u long, v long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options)


class _Slice(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__(first)
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.folder, self.title, self.part = options["path"], options["name"], options.get("part", "nodes")

    def _file(self, kind: str) -> str:
        return os.path.join(self.folder, f"{self.title}_{kind}.txt")

    def partitions(self):
        with open(self._file("A" if self.part == "edges" else "graph_indicator")) as f:
            lines = sum(1 for _ in f)
        step = 1_000_000
        return [_Slice(a, min(a + step, lines)) for a in range(0, max(lines, 1), step)]

    def read(self, at) -> Iterator[tuple]:
        from itertools import islice

        with open(self._file("A" if self.part == "edges" else "graph_indicator")) as f:
            lines = islice(f, at.first, at.last)
            if self.part == "edges":
                for line in lines:
                    u, v = line.split(",")
                    yield int(u), int(v)
                return
            with open(self._file("node_labels")) as labels:
                for k, (g, label) in enumerate(zip(lines, islice(labels, at.first, at.last)), at.first + 1):
                    yield k, int(g), label.strip()


class _Done(WriterCommitMessage):
    def __init__(self, lines):
        self.lines = lines


class _Writer(DataSourceWriter):
    """Each task sends its lines; the commit writes one file in order. For collections that fit one file."""

    def __init__(self, options):
        self.folder, self.title, self.part = options["path"], options["name"], options.get("part", "nodes")

    def write(self, iterator) -> WriterCommitMessage:
        return _Done([tuple(r) for r in iterator])

    def commit(self, messages) -> None:
        os.makedirs(self.folder, exist_ok=True)
        rows = sorted(r for m in messages if m for r in m.lines)
        save = lambda kind, lines: open(os.path.join(self.folder, f"{self.title}_{kind}.txt"), "w").write("".join(f"{x}\n" for x in lines))
        if self.part == "edges":
            save("A", (f"{u}, {v}" for u, v in rows))
        else:
            save("graph_indicator", (r[1] for r in rows))
            save("node_labels", (r[2] for r in rows))


def read_collection(spark: SparkSession, path: str, name: str) -> tuple[DataFrame, DataFrame]:
    """nodes and edges of a collection, nodes numbered from 0 within each graph."""
    spark.dataSource.register(TextGraphSource)
    part = lambda p: spark.read.format("textgraph").option("name", name).option("part", p).load(path)
    nodes = part("nodes")
    order = Window.partitionBy("graph_id").orderBy("node")
    numbered = nodes.withColumn("new", (F.row_number().over(order) - 1).cast("int"))
    end = lambda c: numbered.select(F.col("node").alias(c), F.col("new").alias(f"n_{c}"), *([F.col("graph_id")] if c == "u" else []))
    edges = part("edges").join(end("u"), "u").join(end("v"), "v").select("graph_id", F.col("n_u").alias("u"), F.col("n_v").alias("v"))
    return numbered.select("graph_id", F.col("new").alias("node"), "label"), normalize_edges(edges)


def write_collection(nodes: DataFrame, edges: DataFrame, path: str, name: str) -> None:
    """Writes the three files; labels must be texts or numbers without line breaks."""
    spark = nodes.sparkSession
    spark.dataSource.register(TextGraphSource)
    order = Window.orderBy("graph_id", "node")
    graph = F.dense_rank().over(Window.orderBy("graph_id")).cast("long")
    every = nodes.withColumns({"id": F.row_number().over(order).cast("long"), "g": graph})
    out = lambda df, part: df.coalesce(1).write.format("textgraph").option("name", name).option("part", part).mode("append").save(path)
    out(every.select(F.col("id").alias("node"), F.col("g").alias("graph_id"), F.col("label").cast("string").alias("label")), "nodes")
    end = lambda c: every.select("graph_id", F.col("node").alias(c), F.col("id").alias(f"i_{c}"))
    ends = edges.join(end("u"), ["graph_id", "u"]).join(end("v"), ["graph_id", "v"])
    out(ends.select(F.col("i_u").alias("u"), F.col("i_v").alias("v")), "edges")


def save_packed(graphs: DataFrame, path: str, by: str = "split") -> None:
    graphs.write.mode("overwrite").partitionBy(by).parquet(path)


def graphviz(graphs: DataFrame) -> DataFrame:
    """graph_id and its text in the dot language."""
    nodes = F.array_join(F.transform("label_ids", lambda x, i: F.format_string('  %d [label="%d"];', i, x)), "\n")
    ends = F.flatten(F.transform("nbrs", lambda row, i: F.transform(F.filter(row, lambda j: j > i), lambda j: F.format_string("  %d -- %d;", i, j))))
    return graphs.select("graph_id", F.concat(F.lit("graph {\n"), nodes, F.lit("\n"), F.array_join(ends, "\n"), F.lit("\n}")).alias("dot"))
