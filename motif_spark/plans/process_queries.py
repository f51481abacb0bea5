"""Queries of graph tools, the decision process, SQL functions and cost measures, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.register import register_all, vec_sum_native
from ..operators import census as C
from ..operators import graphs as G
from ..operators import layers as L
from ..operators import learning
from ..operators import measures as A
from ..operators import network as net
from ..operators import process as P
from ..operators.canonical import small_code
from ..sources import suites as S
from .class_queries import chance_sql, classes, csv, session
from .graph_queries import _PURCHASE, _TRADE, SESSION, coded

QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


# --- graphs ---------------------------------------------------------------------------------------------------


@query(f"WITH {SESSION} SELECT graph_id, CAST(u AS INT) AS u, CAST(v AS INT) AS v FROM e")
def g_unpack_edges(spark, sf_dir):
    return G.unpack_graphs(session(spark, sf_dir))[1]


@query(f"WITH {SESSION} SELECT graph_id, node, CAST(label_id AS INT) AS label_id FROM s")
def g_unpack_nodes(spark, sf_dir):
    return G.unpack_graphs(session(spark, sf_dir))[0]


@query(f"WITH {SESSION}, g AS (SELECT DISTINCT graph_id FROM s), x AS (SELECT graph_id, {chance_sql('graph_id', '1')} AS u FROM g) SELECT graph_id, CASE WHEN u < 0.8 * 0.9 THEN 'train' WHEN u < 0.8 THEN 'valid' ELSE 'test' END AS split FROM x")
def g_split(spark, sf_dir):
    return G.split_targets(session(spark, sf_dir), 0.8, 0.1).select("graph_id", "split")


@query(f"""WITH {SESSION}, d AS (SELECT s.graph_id, s.node, s.label_id, coalesce(c, 0) AS c FROM s LEFT JOIN (SELECT graph_id, a, count(*) AS c FROM b GROUP BY 1, 2) t ON t.graph_id = s.graph_id AND t.a = s.node),
q AS (SELECT x.graph_id, count(*) AS triangles FROM e x JOIN e y ON x.graph_id = y.graph_id AND x.v = y.u JOIN e z ON z.graph_id = x.graph_id AND z.u = x.u AND z.v = y.v GROUP BY 1)
SELECT graph_id, string_agg(label_id || ':' || c, ',' ORDER BY label_id, c) AS profile, any_value(triangles) AS triangles, false AS same FROM d JOIN q USING (graph_id) GROUP BY 1""")
def g_permute(spark, sf_dir):
    """A renumbered graph has another order but the same labels with degrees, and the same triangles."""
    graphs = session(spark, sf_dir)
    moved = G.saved(G.permute_graph(graphs, 3))
    degree = F.zip_with("label_ids", "nbrs", lambda x, r: F.struct(x.alias("l"), F.size(r).alias("d")))
    profile = F.array_join(F.transform(F.sort_array(degree), lambda x: F.concat_ws(":", x["l"].cast("string"), x["d"].cast("string"))), ",")
    triangles = C.exact_census(moved, [3]).filter(F.split("code", ":")[1] == "7").groupBy("graph_id").agg(F.sum("freq").alias("triangles"))
    rows = moved.join(graphs.select("graph_id", F.col("nbrs").alias("before")), "graph_id").select("graph_id", profile.alias("profile"), (F.col("nbrs") == F.col("before")).alias("same"))
    return rows.join(triangles, "graph_id")


@query(f"""WITH {SESSION}, f AS (SELECT graph_id, coalesce(sum(n) OVER (ORDER BY graph_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS beg FROM (SELECT graph_id, count(*) AS n FROM s GROUP BY 1))
SELECT CAST(0 AS BIGINT) AS graph_id, CAST(beg + u AS INT) AS u, CAST(beg + v AS INT) AS v FROM e JOIN f USING (graph_id)""")
def g_union_edges(spark, sf_dir):
    return G.union_graphs(*S.session(spark, sf_dir))[1]


@query(f"""WITH {SESSION}, f AS (SELECT graph_id, coalesce(sum(n) OVER (ORDER BY graph_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS beg FROM (SELECT graph_id, count(*) AS n FROM s GROUP BY 1))
SELECT CAST(0 AS BIGINT) AS graph_id, CAST(beg + node AS INT) AS node, label FROM s JOIN f USING (graph_id)""")
def g_union_nodes(spark, sf_dir):
    return G.union_graphs(*S.session(spark, sf_dir))[0]


@query(f"WITH {_PURCHASE}, n AS (SELECT graph_id, count(*) AS n FROM p GROUP BY 1), m AS (SELECT graph_id, count(*) AS m FROM pe GROUP BY 1) SELECT graph_id, round(2.0 * m / (n * (n - 1)), 9) AS density FROM n JOIN m USING (graph_id) WHERE n > 1")
def g_density(spark, sf_dir):
    graphs = S.packed(spark, sf_dir, "purchase", False)
    return G.graph_stats(graphs).filter("n > 1").select("graph_id", F.round("density", 9).alias("density"))


_THREE = "array(array(0, 1, 2), array(0, 1, 3), array(1, 2, 4))"


@query(f"""WITH {SESSION}, m AS (SELECT DISTINCT graph_id, i, x FROM s, (VALUES (0, [0, 1, 2]), (1, [0, 1, 3]), (2, [1, 2, 4])) AS t(i, x) WHERE n > 4)
SELECT graph_id, array_to_string(x, ',') AS members, (SELECT count(*) FROM e WHERE e.graph_id = m.graph_id AND list_contains(x, u) AND list_contains(x, v)) AS edges FROM m""")
def g_induce_rows(spark, sf_dir):
    """Induced subgraphs by joins, for graphs beyond one row."""
    nodes, edges = S.session(spark, sf_dir)
    chosen = nodes.filter("node = 4").select("graph_id", F.explode(F.expr(_THREE)).alias("members"))
    chosen = chosen.withColumn("set_id", F.xxhash64("graph_id", "members"))
    found = G.induce_rows(nodes, edges, chosen.select("graph_id", "set_id", F.explode("members").alias("node")))[1]
    counts = found.groupBy("set_id").agg(F.count(F.lit(1)).alias("edges"))
    return chosen.join(counts, "set_id", "left").select("graph_id", csv("members"), F.coalesce("edges", F.lit(0)).alias("edges"))


@query(f"""WITH RECURSIVE {_TRADE}, {SESSION}, {_PURCHASE}, x AS (SELECT graph_id, c_custkey AS u, 1099511627776 + l_suppkey AS v FROM tp),
y AS (SELECT graph_id, u, v FROM x UNION ALL SELECT graph_id, v, u FROM x), r AS (SELECT DISTINCT graph_id, u AS a, u AS o FROM y UNION SELECT r.graph_id, r.a, y.v FROM r JOIN y ON r.graph_id = y.graph_id AND r.o = y.u),
c AS (SELECT graph_id, a, min(o) AS comp FROM r GROUP BY 1, 2), tn AS (SELECT graph_id, comp, count(*) AS n FROM c GROUP BY 1, 2),
te AS (SELECT x.graph_id, comp, count(*) AS m FROM x JOIN c ON c.graph_id = x.graph_id AND c.a = x.u GROUP BY 1, 2),
sz AS (SELECT 'session' AS suite, graph_id, 0 AS comp, count(*) AS n FROM s GROUP BY 2 UNION ALL SELECT 'purchase', graph_id, 0, count(*) FROM p GROUP BY 2 UNION ALL SELECT 'trade', graph_id, comp, n FROM tn),
sm AS (SELECT 'session' AS suite, graph_id, 0 AS comp, count(*) AS m FROM e GROUP BY 2 UNION ALL SELECT 'purchase', graph_id, 0, count(*) FROM pe GROUP BY 2 UNION ALL SELECT 'trade', graph_id, comp, m FROM te),
w AS (SELECT suite, count(*) AS graphs, round(avg(n), 6) AS mean_n, round(avg(m), 6) AS mean_m FROM sz JOIN sm USING (suite, graph_id, comp) WHERE n > 10 AND n < 500 GROUP BY 1)
SELECT * FROM w UNION ALL SELECT 'session3', graphs, mean_n, mean_m FROM w WHERE suite = 'session' UNION ALL SELECT 'purchase_kind', graphs, mean_n, mean_m FROM w WHERE suite = 'purchase'""")
def w1_table_suites(spark, sf_dir):
    """The dataset table of the suites that SQL can build."""
    from .workloads import dataset_table

    table = dataset_table(spark, sf_dir, ["session", "session3", "purchase", "purchase_kind", "trade"])
    return table.select("suite", "graphs", F.round("mean_n", 6).alias("mean_n"), F.round("mean_m", 6).alias("mean_m"))


@query("""WITH t AS (SELECT page_id AS graph_id, len(regexp_extract_all(html, '<[a-zA-Z]')) AS n FROM pages) SELECT graph_id, CAST(n AS INT) AS n, CAST(n - 1 AS INT) AS m FROM t WHERE n > 10 AND n < 500""")
def g_dom_sizes(spark, sf_dir):
    """Elements and links of every page's tree."""
    return S.packed(spark, sf_dir, "dom").select("graph_id", "n", "m")


@query("""WITH v AS (SELECT label AS graph_id, vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS x FROM embeddings), u AS (SELECT graph_id, vec_id, x, sqrt(list_sum(list_transform(x, lambda y: y * y))) AS len FROM v),
c AS (SELECT a.graph_id, a.vec_id AS i, b.vec_id AS j, row_number() OVER (PARTITION BY a.graph_id, a.vec_id ORDER BY round(list_dot_product(a.x, b.x) / (a.len * b.len), 12) DESC, b.vec_id) AS r FROM u a JOIN u b ON a.graph_id = b.graph_id AND a.vec_id <> b.vec_id),
e AS (SELECT DISTINCT graph_id, least(i, j) AS u, greatest(i, j) AS v FROM c WHERE r <= 3), n AS (SELECT graph_id, count(*) AS n FROM v GROUP BY 1), m AS (SELECT graph_id, count(*) AS m FROM e GROUP BY 1)
SELECT CAST(graph_id AS BIGINT) AS graph_id, CAST(n AS INT) AS n, CAST(m AS INT) AS m FROM n JOIN m USING (graph_id)""")
def g_similar_sizes(spark, sf_dir):
    """Vectors and links of every label's nearest-neighbour graph, whatever its size."""
    return S.packed(spark, sf_dir, "similar", False).select("graph_id", "n", "m")


_SPACE = f"WITH {_PURCHASE}, b AS (SELECT graph_id, u AS a, v AS o FROM pe UNION ALL SELECT graph_id, v, u FROM pe), d AS (SELECT graph_id, a, count(*) AS d FROM b GROUP BY 1, 2)"


def _space_purchase(k: int, sql: str) -> None:
    def space(spark: SparkSession, sf_dir: str) -> DataFrame:
        return C.search_space(S.packed(spark, sf_dir, "purchase", False), [k])

    QUERIES[f"x_space_k{k}_purchase"], SQL[f"x_space_k{k}_purchase"] = space, sql


_space_purchase(2, f"{_SPACE} SELECT graph_id, CAST(2 AS INT) AS k, count(*) AS sets FROM pe GROUP BY 1")
_space_purchase(3, f"{_SPACE} SELECT * FROM (SELECT graph_id, CAST(3 AS INT) AS k, CAST(sum(d * (d - 1) // 2) AS BIGINT) AS sets FROM d GROUP BY 1) WHERE sets > 0")
#: Customer graphs have no triangle, so a connected four-set is a star, a path or a ring, and a ring holds four paths.
_space_purchase(4, f"""{_SPACE}, star AS (SELECT graph_id, sum(d * (d - 1) * (d - 2) // 6) AS x FROM d GROUP BY 1),
path AS (SELECT pe.graph_id, sum((x.d - 1) * (y.d - 1)) AS x FROM pe JOIN d x ON x.graph_id = pe.graph_id AND x.a = pe.u JOIN d y ON y.graph_id = pe.graph_id AND y.a = pe.v GROUP BY 1),
ring AS (SELECT graph_id, sum(c * (c - 1) // 2) / 2 AS x FROM (SELECT x.graph_id, x.a AS i, y.a AS j, count(*) AS c FROM b x JOIN b y ON y.graph_id = x.graph_id AND y.o = x.o AND x.a < y.a GROUP BY 1, 2, 3) GROUP BY 1)
SELECT * FROM (SELECT star.graph_id, CAST(4 AS INT) AS k, CAST(star.x + path.x - 3 * coalesce(ring.x, 0) AS BIGINT) AS sets FROM star JOIN path USING (graph_id) LEFT JOIN ring USING (graph_id)) WHERE sets > 0""")


@query(f"WITH {coded(5)} SELECT graph_id, code, count(*) AS freq FROM c GROUP BY 1, 2")
def x_small_code_k5(spark, sf_dir):
    """Classes of five nodes by the native code, made once for each distinct (labels, bits)."""
    raw = G.saved(C.raw_counts(session(spark, sf_dir), [5]).select("graph_id", "labels", "bits", "cnt"))
    named = raw.select("labels", "bits").distinct().withColumn("code", small_code("labels", "bits", 5))
    return raw.join(G.shuffled(named), ["labels", "bits"]).groupBy("graph_id", "code").agg(F.sum("cnt").alias("freq"))


# --- decision process -----------------------------------------------------------------------------------------


@query(f"WITH {SESSION} SELECT graph_id, string_agg(CAST(o AS VARCHAR), ',' ORDER BY o) AS actions FROM (SELECT DISTINCT graph_id, o FROM b WHERE a = 3) GROUP BY 1")
def p_valid_actions_t1(spark, sf_dir):
    states = P.step(P.reset(session(spark, sf_dir), [5]), F.lit(3))
    return states.select("graph_id", csv_of(P.valid_actions()).alias("actions"))


def csv_of(column: F.Column) -> F.Column:
    return F.array_join(F.transform(column, lambda x: x.cast("string")), ",")


@query(f"""WITH {coded(3)}, z AS (SELECT graph_id, code, count(*) AS freq FROM c GROUP BY 1, 2), t AS (SELECT graph_id, max(freq) AS best FROM z GROUP BY 1)
SELECT graph_id, CAST(step AS INT) AS step, CAST(3 - step AS INT) AS remaining, CAST(3 AS INT) AS k, step = 3 AS done, round(CASE WHEN step = 3 THEN freq / best ELSE 0 END, 9) AS reward
FROM (SELECT graph_id, code FROM c WHERE n0 = 0 AND n1 = 1 AND n2 = 2) JOIN z USING (graph_id, code) JOIN t USING (graph_id), range(4) AS r(step)""")
def p_trajectory(spark, sf_dir):
    """Task, end and reward of every step of picking nodes 0, 1 and 2: nothing is paid before the end."""
    graphs = G.saved(session(spark, sf_dir))
    census = G.saved(C.exact_census(graphs, [3]).select("graph_id", "code", "freq"))
    last = C.code_sets(graphs.select("graph_id", F.array(F.lit(0), F.lit(1), F.lit(2)).alias("members")), graphs)
    own = last.join(census, ["graph_id", "code"]).join(census.groupBy("graph_id").agg(F.max("freq").alias("best")), "graph_id")
    states, rows = P.reset(graphs, [3]), None
    for t in range(4):
        task = states.select("graph_id", "n", "m", F.lit(t).alias("step"), P.task().alias("task"), P.done().alias("done"))
        rows = task if rows is None else rows.unionByName(task)
        states = P.step(states, F.lit(t))
    paid = rows.join(own.select("graph_id", "freq", "best"), "graph_id").withColumn("k", F.col("task.k"))
    return paid.select("graph_id", "step", "task.remaining", "k", "done", F.round(P.reward("best"), 9).alias("reward"))


@query("SELECT conv_id AS graph_id, CAST(k AS INT) AS k, count(*) < k AS dead FROM conversations, (VALUES (3), (9)) AS t(k) GROUP BY conv_id, k")
def p_dead_ends(spark, sf_dir):
    """Searches that run out of valid nodes: paths of at most eight turns have no nine."""
    graphs = G.pack_graphs(*S.dialog(spark, sf_dir))
    labels = graphs.agg(F.max(F.array_max("label_ids"))).first()[0] or 0
    config = net.Config(labels=labels + 1, width=8, layers=1)
    return learning.mine_all(graphs, [3, 9], learning.Policy(config, net.init(config, "actor", 1))).select("graph_id", "k", "dead")


_SCORES = f"{SESSION}, sc AS (SELECT graph_id, node, (node % 7) / 2.0 AS score, node % 2 = 1 AS valid FROM s)"


def _probabilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = S.session(spark, sf_dir)[0].select("graph_id", "node", (F.col("node") % 7 / 2.0).alias("score"), (F.col("node") % 2 == 1).alias("valid"))
    return L.masked_softmax(rows)


@query(f"WITH {_SCORES} SELECT graph_id, node AS action FROM sc WHERE valid QUALIFY row_number() OVER (PARTITION BY graph_id ORDER BY score DESC, node) = 1")
def p_greedy(spark, sf_dir):
    """The most probable valid node."""
    return P.greedy_action(_probabilities(spark, sf_dir))


@query(f"""WITH {_SCORES}, d AS (SELECT graph_id, seed, node, exp(score) AS e, {chance_sql('graph_id', 'seed')} AS u FROM sc, range(20) AS t(seed) WHERE valid),
c AS (SELECT *, sum(e) OVER (PARTITION BY graph_id, seed ORDER BY node) AS upto, sum(e) OVER (PARTITION BY graph_id, seed) AS total FROM d)
SELECT graph_id, CAST(seed AS INT) AS seed, min(node) AS action FROM c WHERE upto > u * total GROUP BY 1, 2""")
def p_sampled(spark, sf_dir):
    """Twenty actions for each graph, drawn by their probabilities."""
    rows = _probabilities(spark, sf_dir).withColumn("seed", F.explode(F.sequence(F.lit(0), F.lit(19))))
    return P.sample_action(rows, "seed")


# --- SQL functions --------------------------------------------------------------------------------------------


@query(f"WITH {coded(3)}, z AS (SELECT graph_id, code FROM c WHERE n0 = 0 AND n1 = 1 AND n2 = 2) SELECT graph_id, min(graph_id) OVER (PARTITION BY code) AS first_alike FROM z")
def op_udf(spark, sf_dir):
    """Codes of each session graph's first three nodes by the registered function: equal codes are one class."""
    register_all(spark)
    rows = G.saved(G.induce(session(spark, sf_dir).withColumn("members", F.array(F.lit(0), F.lit(1), F.lit(2)))).select("graph_id", "labels", "bits"))
    coded_rows = spark.sql("SELECT graph_id, motif_code(labels, bits) AS code FROM {rows}", rows=rows)
    return coded_rows.select("graph_id", F.min("graph_id").over(Window.partitionBy("code")).alias("first_alike"))


@query(f"""WITH {coded(3)}, r AS (SELECT code, l0 || '.' || l1 || '.' || l2 || ':' || (CASE WHEN n1 - n0 <= 2 THEN 4 ELSE 0 END + CASE WHEN n2 - n0 <= 2 THEN 2 ELSE 0 END + CASE WHEN n2 - n1 <= 2 THEN 1 ELSE 0 END) AS raw FROM c),
k AS (SELECT DISTINCT raw, code FROM r) SELECT x.raw AS a, y.raw AS b, x.code = y.code AS alike FROM k x JOIN k y ON x.raw <= y.raw AND list_sort(string_split(split_part(x.raw, ':', 1), '.')) = list_sort(string_split(split_part(y.raw, ':', 1), '.'))""")
def f_isomorphic(spark, sf_dir):
    """Isomorphism of all kinds of three-node subgraphs that share their labels, by the registered function."""
    register_all(spark)
    raw = C.raw_counts(session(spark, sf_dir), [3]).select(F.concat_ws(":", csv_dots("labels"), F.col("bits").cast("string")).alias("raw"), F.array_join(F.array_sort(F.transform("labels", lambda x: x.cast("string"))), ".").alias("key")).distinct()
    held = G.saved(raw)
    pairs = held.select(F.col("raw").alias("a"), "key").join(held.select(F.col("raw").alias("b"), "key"), "key").filter("a <= b").select("a", "b")
    return spark.sql("SELECT a, b, motif_isomorphic(a, b) AS alike FROM {pairs}", pairs=G.saved(pairs))


def csv_dots(column: str) -> F.Column:
    return F.array_join(F.transform(column, lambda x: x.cast("string")), ".")


@query(f"""WITH {SESSION}, g AS (SELECT DISTINCT graph_id FROM s WHERE n > 4) SELECT graph_id, CAST(7 AS BIGINT) AS first, CAST(6 AS BIGINT) AS wide FROM g""")
def op_induced_bits(spark, sf_dir):
    """Adjacency bits of given members by the SQL function: 0, 1, 2 are a triangle; of 0, 1, 3 the last two are joined to 1."""
    register_all(spark)
    g = session(spark, sf_dir).filter("n > 4")
    return spark.sql("SELECT graph_id, induced_bits(nbrs, array(0, 1, 2)) AS first, induced_bits(nbrs, array(1, 0, 3)) AS wide FROM {g}", g=g)


@query("""WITH v AS (SELECT label, unnest(range(1, 65)) AS place, unnest(embedding) AS x FROM embeddings), s AS (SELECT label, place, sum(CAST(x AS DOUBLE)) AS x FROM v GROUP BY 1, 2) SELECT label, CAST(place AS INT) AS place, round(x, 5) + 0.0 AS x FROM s""")
def op_udaf(spark, sf_dir):
    """Sums of vectors by the registered aggregate."""
    register_all(spark)
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("label", F.col("embedding").cast("array<double>").alias("v"))
    summed = e.groupBy("label").agg(F.call_function("vec_sum", F.col("v")).alias("s"))
    return summed.select("label", F.posexplode("s").alias("at", "x")).select("label", (F.col("at") + 1).alias("place"), (F.round("x", 5) + 0.0).alias("x"))


@query(SQL["op_udaf"])
def op_vec_sum_native(spark, sf_dir):
    """The same sums by DataFrame functions alone."""
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("label", F.col("embedding").cast("array<double>").alias("v"))
    return vec_sum_native(e, ["label"], "v").select("label", F.posexplode("v").alias("at", "x")).select("label", (F.col("at") + 1).alias("place"), (F.round("x", 5) + 0.0).alias("x"))


@query(f"WITH {classes([1, 2, 3])} SELECT graph_id, k, count(*) AS sets FROM sets GROUP BY 1, 2")
def op_udtf(spark, sf_dir):
    """Sets of every size by the table function."""
    register_all(spark)
    g = session(spark, sf_dir)
    return spark.sql("SELECT graph_id, t.k, count(*) AS sets FROM {g}, LATERAL enumerate_subgraphs(label_ids, nbrs, 3) t GROUP BY graph_id, t.k", g=g).select("graph_id", "k", "sets")


SQL["op_udtf"] = f"WITH {classes([1, 2, 3])} SELECT graph_id, CAST(k AS INT) AS k, count(*) AS sets FROM sets GROUP BY 1, 2"


@query(f"WITH {classes([3])} SELECT graph_id, CAST(k AS INT) AS k, count(*) AS sets FROM sets GROUP BY 1, 2")
def op_udtf_partitioned(spark, sf_dir):
    """The table function over a partitioned table argument: a partition holds the packed rows of one graph."""
    register_all(spark)
    session(spark, sf_dir).createOrReplaceTempView("motif_graphs")
    return spark.sql("SELECT graph_id, k, sets FROM count_subgraphs(TABLE(SELECT graph_id, label_ids, nbrs FROM motif_graphs) PARTITION BY (graph_id), 3) WHERE k = 3")


@query("SELECT page_id, CAST(len(regexp_extract_all(html, '<[a-zA-Z]')) AS BIGINT) AS elements FROM pages")
def op_html_tree(spark, sf_dir):
    """Elements of every page by the table function."""
    register_all(spark)
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "html")
    return spark.sql("SELECT page_id, count(*) AS elements FROM {p}, LATERAL html_tree(html) t GROUP BY page_id", p=pages)


@query(f"WITH {SESSION} SELECT DISTINCT graph_id, CAST(3 AS INT) AS size, true AS connected FROM s")
def op_mine_udtf(spark, sf_dir):
    """Greedy search by the table function: three connected nodes of every graph."""
    config = net.Config(labels=5, width=8, layers=1)
    register_all(spark, learning.Policy(config, net.init(config, "actor", 1)))
    g = session(spark, sf_dir)
    found = spark.sql("SELECT graph_id, members FROM {g}, LATERAL mine(label_ids, nbrs, 3) t", g=g)
    near = lambda i, j: F.element_at("members", j) - F.element_at("members", i) <= 2
    return found.select("graph_id", F.size("members").alias("size"), (near(1, 2) & near(2, 3)).alias("connected"))


# --- costs ----------------------------------------------------------------------------------------------------


@query(f"WITH {SESSION}, n AS (SELECT graph_id, count(*) AS n FROM s GROUP BY 1), m AS (SELECT graph_id, count(*) AS m FROM e GROUP BY 1) SELECT graph_id, CAST((n * 1024 + m * 32 + n * n * 32 + n * 1024) * 5 AS BIGINT) AS operations FROM n JOIN m USING (graph_id)")
def a_cost_model(spark, sf_dir):
    """Operations of one search of size 5 by graph, from the cost formulas."""
    return session(spark, sf_dir).select("graph_id", A.cost_model(F.col("n").cast("long"), F.col("m").cast("long"), 32, 5)["search"].cast("long").alias("operations"))


@query(f"""WITH {SESSION}, n AS (SELECT graph_id, count(*) AS n FROM s GROUP BY 1), m AS (SELECT graph_id, count(*) AS m FROM e GROUP BY 1)
SELECT graph_id, CAST(n * 1024 + m * 32 + n * n * 32 + n * 1024 AS DOUBLE) AS per_size, 0.0::DOUBLE AS bend FROM n JOIN m USING (graph_id)""")
def a_linear_in_k(spark, sf_dir):
    """Growth of a search's operations with its size: the slope of a line, and nothing beside the line."""
    sizes = F.explode(F.array(*[F.lit(k) for k in range(5, 10)]))
    rows = session(spark, sf_dir).withColumn("k", sizes)
    cost = rows.select("graph_id", "k", A.cost_model(F.col("n").cast("double"), F.col("m").cast("double"), 32, F.col("k"))["search"].alias("cost"))
    return A.growth(cost, "graph_id", "k", "cost").select("graph_id", F.round("slope", 3).alias("per_size"), F.round("bend", 9).alias("bend"))
