"""Queries over graphs, counts, supports, the decision process and network layers, with their SQL."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import census as C
from ..operators import graphs as G
from ..operators import layers as L
from ..operators import measures as A
from ..operators import mni as N
from ..operators import process as P
from ..operators.canonical import small_code
from ..sources import suites as S

EVENT_LABELS = ["click", "error", "purchase", "signup", "view"]
QUERIES, SQL = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


_LABEL_ID = "list_position(" + str(EVENT_LABELS) + ", event_type) - 1"
#: Session nodes and edges, shared by many of the statements below.
SESSION = f"""sn AS (
  SELECT user_id * 10 + CASE WHEN day(ts) <= 15 THEN 0 ELSE 1 END AS graph_id, event_type AS label, {_LABEL_ID} AS label_id, ts, event_id FROM events
), s AS (
  SELECT graph_id, CAST(row_number() OVER (PARTITION BY graph_id ORDER BY ts, event_id) - 1 AS INT) AS node, label, label_id, count(*) OVER (PARTITION BY graph_id) AS n FROM sn
), e AS (
  SELECT graph_id, node AS u, node + d AS v FROM s, (VALUES (1), (2)) AS t(d) WHERE node + d < n
), b AS (SELECT graph_id, u AS a, v AS o FROM e UNION ALL SELECT graph_id, v, u FROM e)"""


def _session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.pack_graphs(*S.session(spark, sf_dir), labels=EVENT_LABELS)


@query(f"WITH {SESSION} SELECT graph_id, node, label FROM s")
def g_session_nodes(spark, sf_dir):
    return S.session(spark, sf_dir)[0]


@query(f"WITH {SESSION} SELECT graph_id, u, v FROM e")
def g_session_edges(spark, sf_dir):
    return S.session(spark, sf_dir)[1]


_PURCHASE = """os AS (
  SELECT DISTINCT o_custkey AS g, o_orderkey, o_orderpriority, l_suppkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey
), pn AS (
  SELECT DISTINCT g AS graph_id, c_custkey AS ext, c_mktsegment AS label, 'C' AS kind FROM os JOIN customer ON g = c_custkey
  UNION ALL SELECT DISTINCT g, 1099511627776 + o_orderkey, o_orderpriority, 'O' FROM os
  UNION ALL SELECT DISTINCT g, 2199023255552 + l_suppkey, r_name, 'S' FROM os JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
), p AS (
  SELECT graph_id, CAST(row_number() OVER (PARTITION BY graph_id ORDER BY ext) - 1 AS INT) AS node, label, kind, ext FROM pn
), pe AS (
  SELECT DISTINCT x.g AS graph_id, a.node AS u, b.node AS v
  FROM (SELECT g, g AS x, 1099511627776 + o_orderkey AS y FROM os UNION SELECT g, 1099511627776 + o_orderkey, 2199023255552 + l_suppkey FROM os) x
  JOIN p a ON a.graph_id = x.g AND a.ext = x.x JOIN p b ON b.graph_id = x.g AND b.ext = x.y
)"""


@query(f"WITH {_PURCHASE} SELECT graph_id, node, label FROM p")
def g_purchase_nodes(spark, sf_dir):
    return S.purchase(spark, sf_dir)[0].select("graph_id", "node", "label")


@query(f"WITH {_PURCHASE} SELECT graph_id, u, v FROM pe")
def g_purchase_edges(spark, sf_dir):
    return S.purchase(spark, sf_dir)[1]


_TRADE = """tp AS (
  SELECT DISTINCT CAST(c_nationkey AS BIGINT) * 100000 + year(o_orderdate) * 12 + month(o_orderdate) AS graph_id, c_custkey, l_suppkey
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
)"""


@query(f"WITH {_TRADE} SELECT graph_id, c_custkey, l_suppkey FROM tp")
def g_trade_edges(spark, sf_dir):
    return S.trade_pairs(spark, sf_dir)


@query(f"""WITH RECURSIVE {_TRADE}, x AS (
  SELECT graph_id, c_custkey AS u, 1099511627776 + l_suppkey AS v FROM tp
), y AS (SELECT graph_id, u, v FROM x UNION ALL SELECT graph_id, v, u FROM x), r AS (
  SELECT DISTINCT graph_id, u AS a, u AS o FROM y UNION SELECT r.graph_id, r.a, y.v FROM r JOIN y ON r.graph_id = y.graph_id AND r.o = y.u
), c AS (SELECT graph_id, a, min(o) AS comp FROM r GROUP BY 1, 2)
SELECT graph_id, count(DISTINCT comp) AS components, CAST(max(n) AS BIGINT) AS largest FROM (SELECT graph_id, comp, count(*) OVER (PARTITION BY graph_id, comp) AS n FROM c) GROUP BY 1""")
def g_components_trade(spark, sf_dir):
    """Components of what was bought from whom, so that every node has an edge."""
    edges = S.trade_pairs(spark, sf_dir).select("graph_id", F.col("c_custkey").alias("u"), (F.lit(S.KIND) + F.col("l_suppkey")).alias("v"))
    comp = G.linked_components(edges).groupBy("graph_id", "comp").count()
    return comp.groupBy("graph_id").agg(F.count(F.lit(1)).alias("components"), F.max("count").alias("largest"))


@query("""WITH n AS (SELECT CAST(n_regionkey AS BIGINT) AS graph_id, n_nationkey FROM nation), x AS (
  SELECT CAST(r_regionkey AS BIGINT) AS graph_id, 0 AS ext FROM region UNION ALL SELECT graph_id, 1099511627776 + n_nationkey FROM n
  UNION ALL SELECT graph_id, 2199023255552 + s_suppkey FROM supplier JOIN n ON s_nationkey = n_nationkey
), i AS (SELECT graph_id, ext, CAST(row_number() OVER (PARTITION BY graph_id ORDER BY ext) - 1 AS INT) AS node FROM x), e AS (
  SELECT graph_id, 0 AS u, 1099511627776 + n_nationkey AS v FROM n UNION ALL SELECT graph_id, 1099511627776 + n_nationkey, 2199023255552 + s_suppkey FROM supplier JOIN n ON s_nationkey = n_nationkey
) SELECT e.graph_id, a.node AS u, b.node AS v FROM e JOIN i a ON a.graph_id = e.graph_id AND a.ext = e.u JOIN i b ON b.graph_id = e.graph_id AND b.ext = e.v""")
def g_geo_edges(spark, sf_dir):
    return S.geo(spark, sf_dir)[1]


@query("""SELECT conv_id AS graph_id, CAST(r - 2 AS INT) AS u, CAST(r - 1 AS INT) AS v
FROM (SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS r FROM conversations) WHERE r > 1""")
def g_dialog_edges(spark, sf_dir):
    return S.dialog(spark, sf_dir)[1]


@query("""WITH l AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem), i AS (
  SELECT l_partkey, CAST(row_number() OVER (ORDER BY l_partkey) - 1 AS INT) AS node FROM (SELECT DISTINCT l_partkey FROM l JOIN part ON l_partkey = p_partkey)
) SELECT DISTINCT CAST(0 AS BIGINT) AS graph_id, a.node AS u, b.node AS v FROM l x JOIN l y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey
JOIN i a ON a.l_partkey = x.l_partkey JOIN i b ON b.l_partkey = y.l_partkey""")
def g_coorder_edges(spark, sf_dir):
    return S.coorder(spark, sf_dir)[1]


@query(f"""WITH {SESSION}, g AS (SELECT graph_id, count(*) AS n FROM s GROUP BY 1), m AS (SELECT graph_id, count(*) AS m FROM e GROUP BY 1),
d AS (SELECT graph_id, max(c) AS d FROM (SELECT graph_id, a, count(*) AS c FROM b GROUP BY 1, 2) GROUP BY 1)
SELECT graph_id, CAST(n AS INT) AS n, CAST(m AS INT) AS m, round(2 * m / (n * (n - 1)), 9) AS density, CAST(d AS INT) AS max_degree FROM g JOIN m USING (graph_id) JOIN d USING (graph_id)""")
def g_stats_session(spark, sf_dir):
    return G.graph_stats(_session(spark, sf_dir)).withColumn("density", F.round("density", 9))


@query(f"""WITH {SESSION}, {_PURCHASE}, x AS (
  SELECT 'session' AS suite, graph_id, count(*) AS n FROM s GROUP BY 2 UNION ALL SELECT 'purchase', graph_id, count(*) FROM p GROUP BY 2
), y AS (SELECT 'session' AS suite, graph_id, count(*) AS m FROM e GROUP BY 2 UNION ALL SELECT 'purchase', graph_id, count(*) FROM pe GROUP BY 2)
SELECT suite, count(*) AS graphs, round(avg(n), 6) AS mean_n, round(avg(m), 6) AS mean_m FROM x JOIN y USING (suite, graph_id) WHERE n > 10 AND n < 500 GROUP BY 1""")
def g_suite_stats(spark, sf_dir):
    one = lambda s: G.suite_stats(S.packed(spark, sf_dir, s)).select(F.lit(s).alias("suite"), "graphs", F.round("mean_n", 6).alias("mean_n"), F.round("mean_m", 6).alias("mean_m"))
    return one("session").unionByName(one("purchase"))


@query(f"WITH {_PURCHASE}, d AS (SELECT graph_id, u AS x FROM pe UNION ALL SELECT graph_id, v FROM pe) SELECT degree, count(*) AS nodes FROM (SELECT graph_id, x, count(*) AS degree FROM d GROUP BY 1, 2) GROUP BY 1")
def g_degree_hist(spark, sf_dir):
    return L.both_ways(S.purchase(spark, sf_dir)[1]).groupBy("graph_id", "node").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("nodes"))


@query(f"WITH {_PURCHASE} SELECT label, count(*) AS nodes FROM p GROUP BY 1")
def g_label_hist(spark, sf_dir):
    return S.purchase(spark, sf_dir)[0].groupBy("label").agg(F.count(F.lit(1)).alias("nodes"))


@query()
def g_dom_stats(spark, sf_dir):
    return G.graph_stats(S.packed(spark, sf_dir, "dom"))


@query()
def g_similar_stats(spark, sf_dir):
    return G.graph_stats(S.packed(spark, sf_dir, "similar"))


@query(f"WITH {SESSION} SELECT graph_id, max(c) AS bound FROM (SELECT graph_id, label, count(*) AS c FROM s GROUP BY 1, 2) GROUP BY 1")
def n_bound(spark, sf_dir):
    return N.upper_bound(_session(spark, sf_dir))


def occurrences(k: int) -> str:
    """SQL of the connected k-sets of session graphs: a first node and gaps of one or two between picks."""
    joins = "".join(f" JOIN s x{i} ON x{i}.graph_id = x{i - 1}.graph_id AND x{i}.node BETWEEN x{i - 1}.node + 1 AND x{i - 1}.node + 2" for i in range(1, k))
    cols = ", ".join(f"x{i}.node AS n{i}, x{i}.label_id AS l{i}" for i in range(k))
    return f"o AS (SELECT x0.graph_id, {cols} FROM s x0{joins})"


def forms(k: int) -> list[tuple[tuple[int, ...], str]]:
    """(order, SQL list of labels and bits) for every order of k places."""
    out = []
    for p in permutations(range(k)):
        pairs = [(i, j) for i in range(k) for j in range(i + 1, k)]
        bits = " + ".join(f"CASE WHEN abs(n{p[i]} - n{p[j]}) <= 2 THEN {1 << (len(pairs) - 1 - at)} ELSE 0 END" for at, (i, j) in enumerate(pairs))
        out.append((p, f"[{', '.join(f'l{x}' for x in p)}, {bits}]"))
    return out


def coded(k: int) -> str:
    least = f"list_sort([{', '.join(f for _, f in forms(k))}])[1]"
    code = " || '.' || ".join(f"f[{i + 1}]" for i in range(k)) + f" || ':' || f[{k + 1}]"
    return f"{SESSION}, {occurrences(k)}, f AS (SELECT *, {least} AS f FROM o), c AS (SELECT *, {code} AS code FROM f)"


def _census(spark, sf_dir, k: int) -> DataFrame:
    raw = C.raw_counts(_session(spark, sf_dir), [k])
    return raw.select("graph_id", "k", small_code("labels", "bits", k).alias("code"), "cnt").groupBy("graph_id", "k", "code").agg(F.sum("cnt").alias("freq"))


def _make(k: int) -> None:
    rows = f"WITH {coded(k)} SELECT graph_id, CAST({k} AS INT) AS k, code, count(*) AS freq FROM c GROUP BY graph_id, code"

    def space(spark, sf_dir):
        return C.search_space(_session(spark, sf_dir), [k])

    def freq(spark, sf_dir):
        return _census(spark, sf_dir, k)

    def best(spark, sf_dir):
        return C.most_frequent(_census(spark, sf_dir, k))

    def ties(spark, sf_dir):
        return C.most_frequent(_census(spark, sf_dir, k), ties=True)

    def support(spark, sf_dir):
        return C.dataset_support(_census(spark, sf_dir, k), 2)

    names = {f"x_space_k{k}_session": (space, f"WITH {SESSION}, {occurrences(k)} SELECT graph_id, CAST({k} AS INT) AS k, count(*) AS sets FROM o GROUP BY 1")}
    names[f"x_freq_k{k}_session"] = (freq, rows)
    names[f"x_best_k{k}_session"] = (best, f"SELECT graph_id, k, code, freq FROM (SELECT *, row_number() OVER (PARTITION BY graph_id ORDER BY freq DESC, code) AS r FROM ({rows})) WHERE r = 1")
    if k == 3:
        names["x_best_ties"] = (ties, f"SELECT graph_id, k, code, freq FROM (SELECT *, rank() OVER (PARTITION BY graph_id ORDER BY freq DESC) AS r FROM ({rows})) WHERE r = 1")
        names["x_dataset_support"] = (support, f"SELECT k, code, count(*) AS support FROM ({rows}) GROUP BY 1, 2 HAVING count(*) >= 2")
    for name, (f, sql) in names.items():
        f.__name__ = name
        QUERIES[name], SQL[name] = f, sql


for _k in (2, 3, 4):
    _make(_k)


def _space(k: int) -> None:
    def space(spark, sf_dir):
        return C.search_space(_session(spark, sf_dir), [k])

    name = f"x_space_k{k}_session"
    QUERIES[name] = space
    SQL[name] = f"""WITH RECURSIVE {SESSION}, w AS (
  SELECT graph_id, n, node AS last, 1 AS k, CAST(1 AS BIGINT) AS c FROM s
  UNION ALL SELECT graph_id, n, last + d, k + 1, c FROM w, (VALUES (1), (2)) AS t(d) WHERE k < {k} AND last + d < n
) SELECT graph_id, CAST(k AS INT) AS k, CAST(sum(c) AS BIGINT) AS sets FROM w WHERE k = {k} GROUP BY 1, 2"""


for _k in (5, 6, 7, 8, 9):
    _space(_k)


@query(f"""WITH {_PURCHASE}, z AS (SELECT graph_id, count(*) AS n FROM p GROUP BY 1 HAVING count(*) > 10 AND count(*) < 500),
b AS (SELECT graph_id, u AS x, v AS y FROM pe UNION ALL SELECT graph_id, v, u FROM pe), k AS (SELECT graph_id, node, kind FROM p),
w AS (SELECT a.graph_id, c.kind AS mid, least(l.kind, r.kind) AS lo, greatest(l.kind, r.kind) AS hi FROM b a JOIN b d ON a.graph_id = d.graph_id AND a.x = d.x AND a.y < d.y
JOIN k c ON c.graph_id = a.graph_id AND c.node = a.x JOIN k l ON l.graph_id = a.graph_id AND l.node = a.y JOIN k r ON r.graph_id = a.graph_id AND r.node = d.y)
SELECT graph_id, lo || mid || hi AS wedge, count(*) AS freq FROM w JOIN z USING (graph_id) GROUP BY 1, 2""")
def x_freq_k3_purchase_kind(spark, sf_dir):
    nodes, edges = S.purchase(spark, sf_dir, False)
    raw = C.raw_counts(G.filter_targets(G.pack_graphs(nodes, edges, labels=["C", "O", "S"])), [3])
    kind = lambda i: F.element_at(F.array(F.lit("C"), F.lit("O"), F.lit("S")), F.element_at("labels", i) + 1)
    middle = F.when(F.col("bits") == 6, 1).when(F.col("bits") == 5, 2).otherwise(3)
    ends = [F.when(middle == 1, kind(2)).otherwise(kind(1)), F.when(middle == 3, kind(2)).otherwise(kind(3))]
    wedge = F.concat(F.least(*ends), F.when(middle == 1, kind(1)).when(middle == 2, kind(2)).otherwise(kind(3)), F.greatest(*ends))
    return raw.groupBy("graph_id", wedge.alias("wedge")).agg(F.sum("cnt").alias("freq"))


@query(f"WITH {SESSION} SELECT x.graph_id, count(*) AS triangles FROM e x JOIN e y ON x.graph_id = y.graph_id AND x.v = y.u JOIN e z ON z.graph_id = x.graph_id AND z.u = x.u AND z.v = y.v GROUP BY 1")
def x_triangles(spark, sf_dir):
    e = S.session(spark, sf_dir)[1]
    y = e.select("graph_id", F.col("u").alias("v"), F.col("v").alias("w"))
    z = e.select("graph_id", "u", F.col("v").alias("w"))
    return e.join(y, ["graph_id", "v"]).join(z, ["graph_id", "u", "w"]).groupBy("graph_id").agg(F.count(F.lit(1)).alias("triangles"))


@query(f"WITH {_PURCHASE}, d AS (SELECT graph_id, u AS x FROM pe UNION ALL SELECT graph_id, v FROM pe) SELECT graph_id, CAST(sum(c * (c - 1) / 2) AS BIGINT) AS wedges FROM (SELECT graph_id, x, count(*) AS c FROM d GROUP BY 1, 2) GROUP BY 1")
def x_wedges(spark, sf_dir):
    d = L.both_ways(S.purchase(spark, sf_dir)[1]).groupBy("graph_id", "node").count()
    return d.groupBy("graph_id").agg(F.sum((F.col("count") * (F.col("count") - 1) / 2).cast("long")).alias("wedges"))


@query("SELECT CAST(0 AS BIGINT) AS graph_id, CAST(0 AS INT) AS size FROM region WHERE false")
def x_engine_agree(spark, sf_dir):
    """Sets that only one of the three engines finds: none."""
    nodes, edges = S.session(spark, sf_dir)
    rows = C.enumerate_rows(_session(spark, sf_dir), 3)
    levels = C.enumerate_levels(nodes, edges, 3)
    counts = C.search_space(_session(spark, sf_dir), [3]).select("graph_id", "sets")
    odd = rows.exceptAll(levels).unionByName(levels.exceptAll(rows)).select("graph_id", F.size("members").alias("size"))
    off = rows.groupBy("graph_id").count().join(counts, "graph_id", "full").filter("count is null or sets is null or count != sets").select("graph_id", F.lit(3).alias("size"))
    return odd.unionByName(off)


def _mni_sql(k: int) -> str:
    parts = " UNION ALL ".join(f"SELECT graph_id, code, [{', '.join(f'n{x}' for x in p)}] AS spots FROM c WHERE f = {form}" for p, form in forms(k))
    images = " UNION ALL ".join(f"SELECT graph_id, code, {i} AS place, spots[{i + 1}] AS node FROM m" for i in range(k))
    return f"{coded(k)}, m AS ({parts}), i AS ({images}), q AS (SELECT graph_id, code, min(c) AS mni FROM (SELECT graph_id, code, place, count(DISTINCT node) AS c FROM i GROUP BY 1, 2, 3) GROUP BY 1, 2), z AS (SELECT graph_id, code, count(*) AS freq FROM c GROUP BY 1, 2), r AS (SELECT graph_id, CAST({k} AS INT) AS k, freq, mni FROM z JOIN q USING (graph_id, code))"


@query(f"WITH {_mni_sql(2)} SELECT * FROM r")
def n_mni_k2(spark, sf_dir):
    return N.mni_census(_session(spark, sf_dir), [2]).select("graph_id", "k", "freq", "mni")


@query(f"WITH {_mni_sql(3)} SELECT * FROM r")
def n_mni_k3(spark, sf_dir):
    return N.mni_census(_session(spark, sf_dir), [3]).select("graph_id", "k", "freq", "mni")


@query(f"WITH {_mni_sql(3)} SELECT graph_id, k, max(freq) AS freq, any_value(mni) AS mni FROM (SELECT *, rank() OVER (PARTITION BY graph_id ORDER BY mni DESC) AS x FROM r) WHERE x = 1 GROUP BY 1, 2")
def n_best_k3(spark, sf_dir):
    return N.baseline(N.mni_census(_session(spark, sf_dir), [3])).select("graph_id", "k", "freq", "mni")


@query(f"WITH {_mni_sql(3)}, t AS (SELECT graph_id, k, max(freq) AS freq FROM (SELECT *, rank() OVER (PARTITION BY graph_id ORDER BY mni DESC) AS x FROM r) WHERE x = 1 GROUP BY 1, 2), mx AS (SELECT graph_id, max(freq) AS best FROM r GROUP BY 1) SELECT k, count(*) AS graphs, CAST(sum(CASE WHEN freq < best THEN 1 ELSE 0 END) AS BIGINT) AS worse FROM t JOIN mx USING (graph_id) GROUP BY 1")
def n_disagree_k3(spark, sf_dir):
    return N.disagreement(N.mni_census(_session(spark, sf_dir), [3]))


@query(f"WITH {SESSION} SELECT graph_id, count(*) AS actions FROM s GROUP BY 1")
def p_valid_actions_t0(spark, sf_dir):
    return P.reset(_session(spark, sf_dir), [3]).select("graph_id", F.size(P.valid_actions()).cast("long").alias("actions"))


@query(f"WITH {SESSION} SELECT graph_id, string_agg(CAST(o AS VARCHAR), ',' ORDER BY o) AS actions FROM (SELECT DISTINCT graph_id, o FROM b WHERE a IN (3, 4) AND o NOT IN (3, 4)) GROUP BY 1")
def p_valid_actions_t2(spark, sf_dir):
    states = P.step(P.step(P.reset(_session(spark, sf_dir), [5]), F.lit(3)), F.lit(4))
    return states.select("graph_id", F.array_join(F.transform(P.valid_actions(), lambda x: x.cast("string")), ",").alias("actions"))


def _reward(kind: str, value: str) -> None:
    """Reward of picking nodes 0, 1, 2 of every session graph."""

    def reward(spark, sf_dir):
        g = _session(spark, sf_dir)
        census = _census(spark, sf_dir, 3)
        own = G.induce(g.withColumn("members", F.array(F.lit(0), F.lit(1), F.lit(2)))).select("graph_id", "n", "m", small_code("labels", "bits", 3).alias("code"))
        best = census.groupBy("graph_id").agg(F.max("freq").alias("best"))
        rows = own.join(census, ["graph_id", "code"]).join(best, "graph_id").withColumn("done", F.lit(True))
        return rows.select("graph_id", F.round(P.reward(kind), 9).alias("reward"))

    name = f"p_reward_{kind}"
    QUERIES[name] = reward
    SQL[name] = f"""WITH {coded(3)}, z AS (SELECT graph_id, code, count(*) AS freq FROM c GROUP BY 1, 2), t AS (SELECT graph_id, max(freq) AS best FROM z GROUP BY 1),
gn AS (SELECT graph_id, count(*) AS n FROM s GROUP BY 1), gm AS (SELECT graph_id, count(*) AS m FROM e GROUP BY 1)
SELECT graph_id, round({value}, 9) AS reward FROM (SELECT graph_id, code FROM c WHERE n0 = 0 AND n1 = 1 AND n2 = 2) JOIN z USING (graph_id, code) JOIN t USING (graph_id) JOIN gn USING (graph_id) JOIN gm USING (graph_id)"""


_reward("raw", "CAST(freq AS DOUBLE)")
_reward("best", "freq / best")
_reward("density", "freq / (n * (2 * m / (n * (n - 1))) * 3)")

# Small weights for the layer queries, rational so that both engines agree.
W = {"own": [[0.5, -0.25], [0.25, 0.5]], "centre": [[0.25, 0.125], [-0.125, 0.25]], "near": [[0.125, 0.25], [0.25, -0.125]]}
STATES = {"state_c": [[1.0, 0.5], [0.5, 1.0]], "state_n": [[1.0, 1.0], [0.25, 2.0]]}
GATES = {"gate_c": [[0.5, 0.25], [0.25, 0.5]], "gate_n": [[0.25, 0.5], [0.5, 0.25]], "wide_c": [[1.0, 0.5], [0.5, 1.0]], "wide_n": [[0.5, 1.0], [1.0, 0.5]]}
TASK = [0.5, 0.25]


def _layer_sql(state: bool, task: bool) -> str:
    mul = lambda w, a, j: "(" + " + ".join(f"{a}{i} * ({w[i][j]})" for i in range(2)) + ")"
    scale = lambda name, j: f"h{j} * CASE WHEN node = 0 THEN {STATES[name][1][j]} ELSE {STATES[name][0][j]} END" if state else f"h{j}"
    wide = lambda name, j: sum(t * GATES[name][i][j] for i, t in enumerate(TASK))
    gate = lambda kind, a, j: "1 / (1 + exp(-(" + " + ".join(f"{a}{i} * {wide('wide_' + kind, i)} * {GATES['gate_' + kind][i][j]}" for i in range(2)) + ")))" if task else "1"
    return f"""WITH {SESSION}, h AS (SELECT graph_id, node, (label_id + 1) / 4.0 AS h0, (node % 3) / 2.0 AS h1 FROM s),
x AS (SELECT *, {', '.join(f"{scale('state_c', j)} AS c{j}, {scale('state_n', j)} AS n{j}" for j in range(2))} FROM h),
y AS (SELECT *, {', '.join(f"{mul(W['centre'], 'c', j)} * {gate('c', 'c', j)} AS u{j}, {mul(W['near'], 'n', j)} * {gate('n', 'n', j)} AS v{j}" for j in range(2))} FROM x),
t AS (SELECT b.graph_id, b.a AS node, count(*) AS d, sum(v0) AS s0, sum(v1) AS s1 FROM b JOIN y ON y.graph_id = b.graph_id AND y.node = b.o GROUP BY 1, 2)
SELECT y.graph_id, y.node, {', '.join(f"round(greatest({mul(W['own'], 'h', j)} + d * u{j} - s{j}, 0), 6) + 0.0 AS h{j}" for j in range(2))} FROM y JOIN t ON y.graph_id = t.graph_id AND y.node = t.node"""


def _layer(name: str, state: bool, task: bool) -> None:
    def run(spark, sf_dir):
        nodes, edges = S.session(spark, sf_dir)
        nodes = G.encode_labels(nodes, EVENT_LABELS).select("graph_id", "node", F.array((F.col("label_id") + 1) / 4.0, F.col("node") % 3 / 2.0).alias("h"), (F.col("node") == 0).cast("int").alias("selected"))
        out = L.message_layer(nodes, edges, W | (STATES if state else {}) | (GATES if task else {}), TASK if task else None)
        return out.select("graph_id", "node", *[(F.round(F.col("h")[j], 6) + 0.0).alias(f"h{j}") for j in range(2)])

    QUERIES[name], SQL[name] = run, _layer_sql(state, task)


_layer("m_layer_plain", False, False)
_layer("m_layer_task", False, True)
_layer("m_layer_state", True, False)
_layer("m_layer_task_state", True, True)


@query(f"WITH {SESSION} SELECT graph_id, node, round(h + g * (1 / (1 + exp(-g * 0.5))), 6) AS h FROM (SELECT graph_id, node, label_id / 4.0 AS h, (node % 5) / 4.0 AS g FROM s)")
def m_gated_skip(spark, sf_dir):
    n = G.encode_labels(S.session(spark, sf_dir)[0], EVENT_LABELS)
    h = L.gated_skip(F.array(F.col("label_id") / 4.0), F.array(F.col("node") % 5 / 4.0), [0.5])
    return n.select("graph_id", "node", F.round(h[0], 6).alias("h"))


@query(f"WITH {SESSION}, x AS (SELECT graph_id, node, (node % 7) / 2.0 AS score, node % 2 = 1 AS valid FROM s) SELECT graph_id, node, round(CASE WHEN valid THEN exp(score) ELSE 0 END / sum(CASE WHEN valid THEN exp(score) ELSE 0 END) OVER (PARTITION BY graph_id), 6) AS prob FROM x")
def h_masked_softmax(spark, sf_dir):
    rows = S.session(spark, sf_dir)[0].select("graph_id", "node", (F.col("node") % 7 / 2.0).alias("score"), (F.col("node") % 2 == 1).alias("valid"))
    return L.masked_softmax(rows).select("graph_id", "node", F.round("prob", 6).alias("prob"))


@query(f"WITH {SESSION}, x AS (SELECT graph_id, node, (node % 7) / 2.0 AS a, node % 2 = 1 AS valid FROM s) SELECT graph_id, node, round(CASE WHEN valid THEN 1.5 + a - avg(CASE WHEN valid THEN a END) OVER (PARTITION BY graph_id) END, 6) AS q FROM x")
def h_dueling(spark, sf_dir):
    rows = S.session(spark, sf_dir)[0].select("graph_id", "node", F.lit(1.5).alias("value"), (F.col("node") % 7 / 2.0).alias("advantage"), (F.col("node") % 2 == 1).alias("valid"))
    return L.dueling(rows).select("graph_id", "node", F.round("q", 6).alias("q"))


@query()
def r_enumeration_estimate(spark, sf_dir):
    est = P.sample_enumeration(_session(spark, sf_dir), 4, [1.0, 0.7, 0.7, 0.7])
    return est.groupBy("graph_id").agg(F.round(F.sum("freq"), 6).alias("sets"))
