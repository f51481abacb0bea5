"""Graph suites built from the given tables with DataFrame operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import graphs as G

KIND = 1 << 40
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
FOLD = {"view": "browse", "click": "browse", "signup": "convert", "purchase": "convert", "error": "error"}


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def worked(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    """The eight-node example with two labels, nodes numbered from 0."""
    labels = ["A", "A", "A", "A", "B", "A", "B", "A"]
    ends = [(0, 1), (0, 2), (1, 2), (2, 4), (3, 4), (4, 5), (5, 6), (6, 7)]
    nodes = spark.createDataFrame([(0, i, x) for i, x in enumerate(labels)], "graph_id long, node int, label string")
    return nodes, spark.createDataFrame([(0, u, v) for u, v in ends], "graph_id long, u int, v int")


def session(spark: SparkSession, sf_dir: str, fold: bool = False) -> tuple[DataFrame, DataFrame]:
    """A graph for each user and half month: events in time order, joined to the next two."""
    e = _table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    graph = F.col("user_id") * 10 + F.when(F.dayofmonth("ts") <= 15, 0).otherwise(1)
    label = F.col("event_type")
    if fold:
        label = F.coalesce(*[F.when(label == a, b) for a, b in FOLD.items()], label)
    w = Window.partitionBy("graph_id")
    e = e.withColumn("graph_id", graph)
    nodes = e.select("graph_id", (F.row_number().over(w.orderBy("ts", "event_id")) - 1).cast("int").alias("node"), label.alias("label"), F.count(F.lit(1)).over(w).alias("_n"))
    edges = nodes.select("graph_id", F.col("node").alias("u"), F.explode(F.array(F.col("node") + 1, F.col("node") + 2)).alias("v"), "_n").filter("v < _n").drop("_n")
    return nodes.drop("_n"), edges


def purchase(spark: SparkSession, sf_dir: str, detail: bool = True) -> tuple[DataFrame, DataFrame]:
    """A graph for each customer: it, its orders that have lines, and their suppliers."""
    t = lambda n: _table(spark, sf_dir, n)
    region = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    supplier = t("supplier").join(F.broadcast(region), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "r_name")
    lines = t("lineitem").select("l_orderkey", "l_suppkey").distinct()
    orders = t("orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    os = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("graph_id"), "o_orderkey", "o_orderpriority", "l_suppkey")
    label = lambda c, kind: (F.col(c) if detail else F.lit(kind)).alias("label")
    o = os.select("graph_id", (F.lit(KIND) + F.col("o_orderkey")).alias("ext_id"), label("o_orderpriority", "O")).distinct()
    c = t("customer").join(os.select(F.col("graph_id").alias("c_custkey")).distinct(), "c_custkey", "left_semi").select(F.col("c_custkey").alias("graph_id"), F.col("c_custkey").alias("ext_id"), label("c_mktsegment", "C"))
    s = os.select("graph_id", "l_suppkey").distinct().join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).select("graph_id", (F.lit(2 * KIND) + F.col("l_suppkey")).alias("ext_id"), label("r_name", "S"))
    ends = os.select("graph_id", F.col("graph_id").alias("u"), (F.lit(KIND) + F.col("o_orderkey")).alias("v")).unionByName(os.select("graph_id", (F.lit(KIND) + F.col("o_orderkey")).alias("u"), (F.lit(2 * KIND) + F.col("l_suppkey")).alias("v"))).distinct()
    return G.index_graphs(c.unionByName(o).unionByName(s), ends)


def trade_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """graph_id (nation and month), customer, supplier: who bought from whom."""
    t = lambda n: _table(spark, sf_dir, n)
    o = t("orders").select("o_orderkey", "o_custkey", (F.year("o_orderdate") * 12 + F.month("o_orderdate")).alias("month"))
    lines = t("lineitem").select("l_orderkey", "l_suppkey")
    df = lines.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return df.select((F.col("c_nationkey").cast("long") * 100_000 + F.col("month")).alias("graph_id"), "c_custkey", "l_suppkey").distinct()


def trade(spark: SparkSession, sf_dir: str, components: bool = True) -> tuple[DataFrame, DataFrame]:
    """Nation and month trade graphs, split into their components."""
    pairs = trade_pairs(spark, sf_dir)
    t = lambda n: _table(spark, sf_dir, n)
    region = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    seg = t("customer").select("c_custkey", F.col("c_mktsegment").alias("label"))
    sup = t("supplier").join(F.broadcast(region), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", F.col("r_name").alias("label"))
    c = pairs.select("graph_id", "c_custkey").distinct().join(seg, "c_custkey").select("graph_id", F.col("c_custkey").alias("ext_id"), "label")
    s = pairs.select("graph_id", "l_suppkey").distinct().join(sup, F.col("l_suppkey") == F.col("s_suppkey")).select("graph_id", (F.lit(KIND) + F.col("l_suppkey")).alias("ext_id"), "label")
    nodes, edges = G.index_graphs(c.unionByName(s), pairs.select("graph_id", F.col("c_custkey").alias("u"), (F.lit(KIND) + F.col("l_suppkey")).alias("v")))
    return G.split_components(G.saved(nodes), G.saved(edges)) if components else (nodes, edges)


def similar(spark: SparkSession, sf_dir: str, near: int = 3) -> tuple[DataFrame, DataFrame]:
    """A graph for each embedding label: every vector joined to its nearest by cosine, ties by id.

    A label's vectors are compared in blocks by one task each; meant for label groups that fit a task.
    """
    e = _table(spark, sf_dir, "embeddings").select("vec_id", "embedding", F.col("label").cast("long").alias("graph_id"))

    def kernel(key, pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.sort_values("vec_id")
        x, ids = np.stack(pdf["embedding"]).astype(float), pdf["vec_id"].to_numpy()
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        rows = []
        for a in range(0, len(x), 512):
            cos = np.round(x[a : a + 512] @ x.T, 12)
            cos[np.arange(len(cos)), np.arange(a, a + len(cos))] = -9
            best = np.argsort(-cos, axis=1, kind="stable")[:, :near]
            rows += [(key[0], int(ids[a + i]), int(ids[j])) for i, js in enumerate(best) for j in js]
        return pd.DataFrame(rows, columns=["graph_id", "u", "v"])

    sign = lambda k: F.when(F.col("embedding")[k] >= 0, "+").otherwise("-")
    nodes = e.select("graph_id", F.col("vec_id").alias("ext_id"), F.concat(sign(0), sign(1)).alias("label"))
    ends = e.groupBy("graph_id").applyInPandas(kernel, "graph_id long, u long, v long")
    return G.index_graphs(nodes, ends)


def html_tree(html: str) -> list[tuple[int, int, str]]:
    """(node, parent or -1, tag) of a page's elements; void tags are leaves, an end tag closes up to its match."""
    from html.parser import HTMLParser

    void = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
    out: list[tuple[int, int, str]] = []
    open_: list[tuple[int, str]] = []

    class Tree(HTMLParser):
        def handle_starttag(self, tag, attrs):
            out.append((len(out), open_[-1][0] if open_ else -1, tag))
            if tag not in void:
                open_.append((len(out) - 1, tag))

        def handle_endtag(self, tag):
            if any(t == tag for _, t in open_):
                while open_.pop()[1] != tag:
                    pass

    Tree().feed(html or "")
    return out


def dom(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """A tree of elements for each page."""
    pages = _table(spark, sf_dir, "pages").select(F.col("page_id").alias("graph_id"), "html")

    def kernel(frames):
        import pandas as pd

        for pdf in frames:
            yield pd.DataFrame([(g, *x) for g, h in zip(pdf["graph_id"], pdf["html"]) for x in html_tree(h)], columns=["graph_id", "node", "parent", "label"])

    rows = pages.mapInPandas(kernel, "graph_id long, node int, parent int, label string")
    return rows.select("graph_id", "node", "label"), rows.filter("parent >= 0").select("graph_id", F.col("parent").alias("u"), F.col("node").alias("v"))


def dialog(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """A path of turns for each conversation."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    nodes = _table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("graph_id"), (F.row_number().over(w) - 1).cast("int").alias("node"), F.col("role").alias("label"))
    return nodes, nodes.filter("node > 0").select("graph_id", (F.col("node") - 1).alias("u"), F.col("node").alias("v"))


def geo(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """A tree for each region: its nations, and their suppliers."""
    t = lambda n: _table(spark, sf_dir, n)
    n = t("nation").select(F.col("n_regionkey").cast("long").alias("graph_id"), "n_nationkey")
    s = t("supplier").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("graph_id", "s_suppkey", "n_nationkey")
    region = t("region").select(F.col("r_regionkey").cast("long").alias("graph_id"), F.lit(0).cast("long").alias("ext_id"), F.lit("region").alias("label"))
    nations = n.select("graph_id", (F.lit(KIND) + F.col("n_nationkey")).alias("ext_id"), F.lit("nation").alias("label"))
    nodes = region.unionByName(nations).unionByName(s.select("graph_id", (F.lit(2 * KIND) + F.col("s_suppkey")).alias("ext_id"), F.lit("supplier").alias("label")))
    ends = n.select("graph_id", F.lit(0).cast("long").alias("u"), (F.lit(KIND) + F.col("n_nationkey")).alias("v")).unionByName(s.select("graph_id", (F.lit(KIND) + F.col("n_nationkey")).alias("u"), (F.lit(2 * KIND) + F.col("s_suppkey")).alias("v")))
    return G.index_graphs(nodes, ends)


def coorder(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """One graph: parts (by type) that were ordered together."""
    lines = _table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = lines.join(lines.withColumnRenamed("l_partkey", "v"), "l_orderkey").filter("l_partkey < v").select(F.lit(0).cast("long").alias("graph_id"), F.col("l_partkey").alias("u"), "v").distinct()
    used = lines.select(F.col("l_partkey").alias("p_partkey")).distinct()
    nodes = _table(spark, sf_dir, "part").join(used, "p_partkey", "left_semi").select(F.lit(0).cast("long").alias("graph_id"), F.col("p_partkey").alias("ext_id"), F.col("p_type").alias("label"))
    return G.index_graphs(nodes, pairs)


SUITES = {
    "session": session,
    "session3": lambda s, d: session(s, d, True),
    "purchase": purchase,
    "purchase_kind": lambda s, d: purchase(s, d, False),
    "trade": trade,
    "similar": similar,
    "dom": dom,
    "dialog": dialog,
    "geo": geo,
    "coorder": coorder,
}


def packed(spark: SparkSession, sf_dir: str, suite: str, filtered: bool = True) -> DataFrame:
    """Packed graphs of a suite; by default those that pass the target filter."""
    graphs = G.pack_graphs(*SUITES[suite](spark, sf_dir))
    return G.filter_targets(graphs) if filtered else graphs
