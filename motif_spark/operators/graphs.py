"""Graphs as node and edge tables and as one packed row per graph.

nodes: graph_id, node (dense from 0), label; edges: graph_id, u < v; graphs: graph_id, n, m, label_ids, nbrs.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Dictionaries up to this size are put into the plan; larger ones are joined.
LITERAL_LABELS = 1_000


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder; only a local master may do without spark.checkpoint.dir."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        folder = sc.getConf().get("spark.checkpoint.dir")
        if not folder and not (sc.master.startswith("local") and "cluster" not in sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def saved(df: DataFrame) -> DataFrame:
    """Cut the lineage in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def shuffled(df: DataFrame) -> DataFrame:
    """Rows that a join must not broadcast: Spark guesses the size of what Python tasks make from the files they read,
    far below what a census holds, and would gather it on the driver."""
    return df.hint("merge")


def dealt(df: DataFrame, *key: str) -> DataFrame:
    """Rows dealt by a hash of their key over all cores. The number is given, as Spark would else put rows together by their
    bytes, and few bytes of graphs hold much work."""
    spark = df.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 3 * spark.sparkContext.defaultParallelism)
    return df.repartition(parts, F.xxhash64(*key))


def rows_of(batches: Iterator[pa.RecordBatch], most: int = 256) -> Iterator[dict]:
    """The rows of batches as dictionaries, of which no more than a slice are made at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, most):
            yield from batch.slice(at, most).to_pylist()


def normalize_edges(pairs: DataFrame, u: str = "u", v: str = "v", by: tuple[str, ...] = ("graph_id",)) -> DataFrame:
    """Undirected edges without loops and repeats."""
    ends = pairs.filter(F.col(u) != F.col(v)).select(*by, F.least(u, v).alias("u"), F.greatest(u, v).alias("v"))
    return ends.distinct()


def index_graphs(nodes: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Dense node numbers from ext_id; edges given between ext ids become edges between numbers."""
    order = Window.partitionBy("graph_id").orderBy("ext_id")
    numbered = nodes.withColumn("node", (F.row_number().over(order) - 1).cast("int"))
    end = lambda name: numbered.select("graph_id", F.col("ext_id").alias(name), F.col("node").alias(f"n_{name}"))
    ends = edges.join(end("u"), ["graph_id", "u"]).join(end("v"), ["graph_id", "v"])
    return numbered, normalize_edges(ends.select("graph_id", F.col("n_u").alias("u"), F.col("n_v").alias("v")))


def label_dictionary(nodes: DataFrame) -> DataFrame:
    """label, label_id in the order of labels."""
    return nodes.select("label").distinct().withColumn("label_id", (F.row_number().over(Window.orderBy("label")) - 1).cast("int"))


def encode_labels(nodes: DataFrame, labels: list[str] | None = None) -> DataFrame:
    """Adds label_id. Known or few labels become a literal, more are joined."""
    if labels is None:
        found = [r["label"] for r in nodes.select("label").distinct().limit(LITERAL_LABELS + 1).collect()]
        if len(found) > LITERAL_LABELS:
            return nodes.join(label_dictionary(nodes), "label")
        labels = sorted(found)
    known = F.array(*[F.lit(x) for x in labels])
    return nodes.withColumn("label_id", (F.array_position(known, F.col("label")) - 1).cast("int"))


def pack_graphs(nodes: DataFrame, edges: DataFrame, labels: list[str] | None = None) -> DataFrame:
    """graph_id, n, m, label_ids, nbrs (sorted neighbour lists). Nodes and ends of edges are shuffled once, together, by graph."""
    nodes = nodes if "label_id" in nodes.columns else encode_labels(nodes, labels)
    ends = F.explode(F.array(F.struct(F.col("u").alias("node"), F.col("v").alias("to")), F.struct(F.col("v").alias("node"), F.col("u").alias("to"))))
    both = edges.select("graph_id", ends.alias("x")).select("graph_id", "x.node", F.lit(None).cast("int").alias("label_id"), "x.to", F.lit(0).alias("own"))
    own = nodes.select("graph_id", "node", "label_id", F.lit(None).cast("int").alias("to"), F.lit(1).alias("own"))
    rows = own.unionByName(both).repartition("graph_id").groupBy("graph_id", "node").agg(F.max("label_id").alias("label_id"), F.sort_array(F.collect_list("to")).alias("near"), F.max("own").alias("own")).filter("own = 1")
    packed = rows.groupBy("graph_id").agg(F.sort_array(F.collect_list(F.struct("node", "label_id", "near"))).alias("g"))
    nbrs = F.col("g.near")
    m = (F.aggregate(nbrs, F.lit(0), lambda a, x: a + F.size(x)) / 2).cast("int")
    return packed.select("graph_id", F.size("g").alias("n"), m.alias("m"), F.col("g.label_id").alias("label_ids"), nbrs.alias("nbrs"))


def unpack_graphs(graphs: DataFrame) -> tuple[DataFrame, DataFrame]:
    nodes = graphs.select("graph_id", F.posexplode("label_ids").alias("node", "label_id"))
    ends = graphs.select("graph_id", F.posexplode("nbrs").alias("u", "to")).select("graph_id", "u", F.explode("to").alias("v"))
    return nodes, ends.filter("u < v")


def graph_stats(graphs: DataFrame) -> DataFrame:
    """n, m, density and largest degree of each graph."""
    degree = F.array_max(F.transform("nbrs", F.size))
    density = F.when(F.col("n") > 1, 2 * F.col("m") / (F.col("n") * (F.col("n") - 1)))
    return graphs.select("graph_id", "n", "m", density.alias("density"), degree.alias("max_degree"))


def suite_stats(graphs: DataFrame) -> DataFrame:
    return graphs.agg(F.count(F.lit(1)).alias("graphs"), F.avg("n").alias("mean_n"), F.avg("m").alias("mean_m"))


#: Edges up to which a task takes a whole graph for its components.
WHOLE_EDGES = 1_000_000


def least_reached(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes that have edges, and the smallest node of the component of each."""
    nodes, ends = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = ends.reshape(2, -1)
    root = np.arange(len(nodes))
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            return nodes, nodes[root]
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(root, root[root]):
            root = root[root]


def connected_components(nodes: DataFrame, edges: DataFrame, rounds: int = 60, whole: int | None = None) -> DataFrame:
    """graph_id, node, comp: the smallest node of its component; nodes without edges are their own."""
    found = shuffled(linked_components(edges, rounds, whole))
    return nodes.select("graph_id", "node").join(found, ["graph_id", "node"], "left").withColumn("comp", F.coalesce("comp", "node"))


def linked_components(edges: DataFrame, rounds: int = 60, whole: int | None = None) -> DataFrame:
    """connected_components() of the nodes that have edges.

    Graphs of up to `whole` edges (WHOLE_EDGES if not given) are settled by one task each, larger ones by stars.
    """
    whole = WHOLE_EDGES if whole is None else whole
    edges = saved(edges.select("graph_id", "u", "v").filter("u != v").repartition("graph_id"))
    sizes = edges.groupBy("graph_id").agg(F.count(F.lit(1)).alias("_m"))
    wide = saved(sizes.filter(F.col("_m") > whole).select("graph_id"))
    kind = {f.name: f.dataType.simpleString() for f in edges.schema.fields}

    def kernel(table: pa.Table) -> pa.Table:
        at, least = least_reached(table.column("u").to_numpy(), table.column("v").to_numpy())
        cols = [pa.repeat(table.column("graph_id")[0], len(at)), pa.array(at), pa.array(least)]
        return pa.Table.from_arrays([c.cast(t) for c, t in zip(cols, (cols[0].type, table.schema.field("u").type, table.schema.field("u").type))], ["graph_id", "node", "comp"])

    found = edges.join(wide, "graph_id", "left_anti").groupBy("graph_id").applyInArrow(kernel, f"graph_id {kind['graph_id']}, node {kind['u']}, comp {kind['u']}")
    if not wide.isEmpty():
        found = found.unionByName(_by_stars(edges.join(wide, "graph_id", "left_semi"), rounds))
    return found


def _by_stars(edges: DataFrame, rounds: int) -> DataFrame:
    """graph_id, node, comp of nodes with edges, by alternating large and small stars.

    Neighbours are only aggregated to their minimum, so hubs are never gathered; lineage is cut each round.
    """
    links = saved(edges.select("graph_id", F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct())
    before = None
    for _ in range(rounds):
        both = links.unionByName(links.select("graph_id", F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("graph_id", "a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.join(least, ["graph_id", "a"]).filter("b > a").select("graph_id", F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        star = large.join(large.groupBy("graph_id", "a").agg(F.min("b").alias("m")), ["graph_id", "a"])
        small = star.select("graph_id", F.col("b").alias("a"), F.col("m").alias("b")).unionByName(star.select("graph_id", "a", F.col("m").alias("b")))
        links = saved(small.filter("a != b").distinct())
        now = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("graph_id", "a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return links.select("graph_id", F.col("a").alias("node"), F.col("b").alias("comp"))


def split_components(nodes: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Each component as a graph of its own; graph_id becomes a hash of the old id and the smallest node."""
    comp = connected_components(nodes, edges)
    key = F.xxhash64("graph_id", "comp")
    parts = nodes.join(comp, ["graph_id", "node"]).select(key.alias("graph_id"), F.col("node").cast("long").alias("ext_id"), *[c for c in nodes.columns if c not in ("graph_id", "node", "ext_id")])
    ends = edges.join(comp.select("graph_id", F.col("node").alias("u"), "comp"), ["graph_id", "u"]).select(key.alias("graph_id"), F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    return index_graphs(parts, ends)


def filter_targets(graphs: DataFrame, above: int = 10, below: int = 500, connected: bool = True) -> DataFrame:
    """Graphs with above < n < below that are connected."""
    kept = graphs.filter((F.col("n") > above) & (F.col("n") < below))
    return _connected(kept) if connected else kept


def _connected(graphs: DataFrame) -> DataFrame:
    def kernel(batches):
        for batch in batches:
            keep = []
            for nbrs in batch.column("nbrs").to_pylist():
                seen, todo = {0}, [0]
                while todo:
                    new = set(nbrs[todo.pop()]) - seen
                    seen |= new
                    todo += new
                keep.append(len(seen) == len(nbrs))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return graphs.mapInArrow(kernel, graphs.schema)


def split_targets(graphs: DataFrame, train: float = 0.8, valid: float = 0.0, seed: int = 1) -> DataFrame:
    """Adds split by a hash of the id, the same at any parallelism."""
    from .process import chance

    at = chance("graph_id", F.lit(seed))
    return graphs.withColumn("split", F.when(at < train * (1 - valid), "train").when(at < train, "valid").otherwise("test"))


def induce(graphs: DataFrame, members: str = "members") -> DataFrame:
    """Adds labels and bits (upper triangle, row by row) of the subgraph induced by a sorted member array."""
    k, at = F.size(members), F.col(members)
    labels = F.transform(at, lambda x: F.element_at("label_ids", x + 1))
    pairs = F.flatten(F.transform(F.sequence(F.lit(0), k - 1), lambda i: F.transform(F.sequence(F.lit(0), k - 1), lambda j: F.when(i < j, F.array_contains(F.element_at("nbrs", F.element_at(at, i + 1) + 1), F.element_at(at, j + 1))))))
    bits = F.aggregate(F.filter(pairs, lambda b: b.isNotNull()), F.lit(0).cast("long"), lambda a, b: a * 2 + b.cast("long"))
    return graphs.withColumns({"labels": labels, "bits": bits})


def induce_rows(nodes: DataFrame, edges: DataFrame, sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges of the subgraphs induced by rows graph_id, set_id, node, by joins; set_id is the new key."""
    chosen = sets.select("graph_id", "set_id", "node").distinct()
    start = edges.join(chosen.withColumnRenamed("node", "u"), ["graph_id", "u"])
    inside = start.join(chosen.withColumnRenamed("node", "v"), ["graph_id", "set_id", "v"])
    return nodes.join(chosen, ["graph_id", "node"]), inside.select("graph_id", "set_id", "u", "v")


def permute_graph(graphs: DataFrame, seed: int = 1) -> DataFrame:
    """Renumbers the nodes of every graph by a seeded order."""
    nodes, edges = unpack_graphs(graphs)
    order = Window.partitionBy("graph_id").orderBy(F.xxhash64("graph_id", "node", F.lit(seed)), "node")
    new = nodes.withColumn("new", (F.row_number().over(order) - 1).cast("int"))
    end = lambda name: new.select("graph_id", F.col("node").alias(name), F.col("new").alias(f"n_{name}"))
    ends = edges.join(end("u"), ["graph_id", "u"]).join(end("v"), ["graph_id", "v"])
    return pack_graphs(new.select("graph_id", F.col("new").alias("node"), "label_id"), normalize_edges(ends.select("graph_id", F.col("n_u").alias("u"), F.col("n_v").alias("v"))))


def union_graphs(nodes: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All graphs as one disconnected graph with id 0; nodes are numbered in order of graph and node.

    Only sizes of graphs are summed up: first within ranges of graph ids, then over the ranges.
    """
    sizes = nodes.groupBy("graph_id").agg(F.count(F.lit(1)).alias("size"))
    ranged = saved(sizes.repartitionByRange("graph_id").withColumn("range", F.spark_partition_id()))
    before = lambda w: F.coalesce(F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = ranged.groupBy("range").agg(F.sum("size").alias("size")).select("range", before(Window.orderBy("range")).alias("start"))
    own = ranged.withColumn("own", before(Window.partitionBy("range").orderBy("graph_id")))
    at = own.join(starts, "range").select("graph_id", (F.col("start") + F.col("own")).alias("first"))
    whole = F.lit(0).cast("long").alias("graph_id")
    number = lambda c: (F.col("first") + F.col(c)).cast("int").alias(c)
    labels = [c for c in ("label", "label_id") if c in nodes.columns]
    return nodes.join(at, "graph_id").select(whole, number("node"), *labels), edges.join(at, "graph_id").select(whole, number("u"), number("v"))
