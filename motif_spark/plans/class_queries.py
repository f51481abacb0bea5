"""Queries of census, support, matching, sampling and accuracy at sizes 2 to 9, with SQL that knows only session graphs.

In a session graph a node is joined to the next two, so a connected set is a first node and gaps of one or
two, and its edges are those between consecutive picks plus a chord over each two gaps of one. Such a set can be
read from either end, the inner nodes of a lone four-node run may change places, and so may the two free nodes of
a triangle at an end; nothing else maps it onto itself or another. The least label word over these readings
names the class, which the engine's codes know nothing of.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import chain, combinations, permutations, product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import census as C
from ..operators import graphs as G
from ..operators import match as M
from ..operators import measures as A
from ..operators import mni as N
from ..operators import process as P
from ..operators.canonical import automorphisms
from ..sources import suites as S
from .graph_queries import EVENT_LABELS, SESSION

QUERIES, SQL = {}, {}
FOLDED = ["browse", "convert", "error"]
_FOLDED_WORD = "CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 0 WHEN 'error' THEN 2 ELSE 1 END"


def query(sql: str | None = None, name: str | None = None):
    def keep(f: Callable[[SparkSession, str], DataFrame]):
        at = name or f.__name__
        QUERIES[at] = f
        if sql:
            SQL[at] = sql
        return f

    return keep


def session(spark: SparkSession, sf_dir: str, fold: bool = False) -> DataFrame:
    return G.pack_graphs(*S.session(spark, sf_dir, fold), labels=FOLDED if fold else EVENT_LABELS)


def csv(column: str) -> F.Column:
    return F.array_join(F.transform(column, lambda x: x.cast("string")), ",").alias(column)


# --- the SQL side ---------------------------------------------------------------------------------------------


def readings(k: int) -> list[tuple[int, str, int, list[int]]]:
    """(pattern of gaps, chords, span, offsets in reading order) for every reading that its chords allow."""
    out = []
    for p, gaps in enumerate(product((1, 2), repeat=k - 1)):
        offsets = [sum(gaps[:i]) for i in range(k)]
        chords = [int(a == b == 1) for a, b in zip(gaps, gaps[1:])]
        runs, at = [], 0
        while at < len(chords):
            end = at
            while end < len(chords) and chords[end]:
                end += 1
            if end > at:
                runs.append((at, end - at))
            at = end + 1
        swaps = [(a + 1, a + 2) for a, m in runs if m == 2]
        swaps += [(0, 1) for a, m in runs if m == 1 and a == 0 and k > 3]
        swaps += [(k - 2, k - 1) for a, m in runs if m == 1 and a == k - 3 and k > 3]
        chosen = chain.from_iterable(combinations(swaps, r) for r in range(len(swaps) + 1))
        orders = set()
        for some in chosen:
            order = list(range(k))
            for a, b in some:
                order[a], order[b] = order[b], order[a]
            orders.add((tuple(order), tuple(chords)))
            orders.add((tuple(order[::-1]), tuple(chords[::-1])))
        if k == 3 and chords == [1]:
            orders = {(x, (1,)) for x in permutations(range(3))}
        least = min(shape for _, shape in orders)
        out += [(p, "c" + "".join(map(str, least)), offsets[-1], [offsets[i] for i in order]) for order, shape in sorted(orders) if shape == least]
    return out


def classes(sizes: list[int], where: str = "true", fold: bool = False) -> str:
    """CTEs: z (readings that give a set its name), sets (graph_id, k, kind, members, n_aut), classes (freq, n_aut, sample)."""
    label = _FOLDED_WORD if fold else "list_position(" + str(EVENT_LABELS) + ", event_type) - 1"
    parts = [f"""wd AS (SELECT graph_id, count(*) AS n, string_agg(CAST(l AS VARCHAR), '' ORDER BY ts, event_id) AS word FROM (
  SELECT user_id * 10 + CASE WHEN day(ts) <= 15 THEN 0 ELSE 1 END AS graph_id, {label} AS l, ts, event_id FROM events) WHERE {where} GROUP BY 1)"""]
    for k in sizes:
        table = ", ".join(f"({p}, '{shape}', {span}, {offsets})" for p, shape, span, offsets in readings(k))
        word = " || ".join(f"substr(word, beg + o[{i + 1}] + 1, 1)" for i in range(k))
        parts.append(f"""x{k} AS (SELECT graph_id, {k} AS k, beg, p, shape, o, {word} AS word FROM (SELECT graph_id, n, word, unnest(range(n)) AS beg FROM wd) JOIN (VALUES {table}) AS r(p, shape, span, o) ON beg + span < n)""")
    union = " UNION ALL ".join(f"SELECT * FROM x{k}" for k in sizes)
    parts.append(f"z AS (SELECT *, shape || word AS kind FROM (SELECT *, min(word) OVER (PARTITION BY graph_id, k, beg, p) AS least FROM ({union})) WHERE word = least)")
    parts.append("sets AS (SELECT graph_id, k, kind, beg, p, count(*) AS n_aut, list_transform(list_sort(any_value(o)), lambda d: beg + d) AS members FROM z GROUP BY graph_id, k, kind, beg, p)")
    parts.append("classes AS (SELECT graph_id, CAST(k AS INT) AS k, kind, count(*) AS freq, any_value(n_aut) AS n_aut, min(members) AS sample FROM sets GROUP BY graph_id, k, kind)")
    return ", ".join(parts)


def supports(sizes: list[int], where: str = "true", fold: bool = False) -> str:
    """classes() and the CTE mni: graph_id, k, kind, freq, mni."""
    return f"""{classes(sizes, where, fold)}, im AS (SELECT graph_id, k, kind, place, count(DISTINCT node) AS image FROM (SELECT graph_id, k, kind, unnest(range(len(o))) AS place, unnest(list_transform(o, lambda d: beg + d)) AS node FROM z) GROUP BY 1, 2, 3, 4),
mni AS (SELECT c.graph_id, c.k, c.kind, c.freq, c.sample, min(image) AS mni FROM classes c JOIN im ON im.graph_id = c.graph_id AND im.k = c.k AND im.kind = c.kind GROUP BY 1, 2, 3, 4, 5),
top AS (SELECT graph_id, k, max(freq) AS freq, any_value(mni) AS mni FROM (SELECT *, rank() OVER (PARTITION BY graph_id, k ORDER BY mni DESC) AS r FROM mni) WHERE r = 1 GROUP BY 1, 2),
best AS (SELECT graph_id, k, max(freq) AS best FROM mni GROUP BY 1, 2)"""


def chance_sql(*key: str) -> str:
    return "CAST('0x' || substr(md5(" + " || ':' || ".join(f"CAST({k} AS VARCHAR)" for k in key) + "), 1, 13) AS BIGINT) / 4503599627370496.0"


def rollouts(sizes: list[int], samples: int = 100, seeds: int = 5) -> str:
    """CTEs over wd: walk and rolled (graph_id, k, seed, sample, picked). The statement must be WITH RECURSIVE."""
    return f"""walk AS (SELECT graph_id, n, k, seed, sample, 0 AS t, CAST([] AS BIGINT[]) AS picked FROM wd, (VALUES {', '.join(f'({k})' for k in sizes)}) AS kk(k), range({seeds}) AS a(seed), range({samples}) AS b(sample)
UNION ALL SELECT graph_id, n, k, seed, sample, t + 1, list_append(picked, opts[CAST(floor(u * len(opts)) AS INT) + 1]) FROM (
  SELECT *, {chance_sql('graph_id', 'k', 'seed', 'sample', 't')} AS u, CASE WHEN t = 0 THEN range(n) ELSE list_sort(list_distinct(list_filter(flatten(list_transform(picked, lambda x: [x - 2, x - 1, x + 1, x + 2])), lambda y: y >= 0 AND y < n AND NOT list_contains(picked, y)))) END AS opts FROM walk WHERE t < k)),
rolled AS (SELECT graph_id, k, seed, sample, picked FROM walk WHERE t = k)"""


TEST = chance_sql("graph_id", "1") + " >= 0.8"

# --- exact census ---------------------------------------------------------------------------------------------


def _census(k: int) -> None:
    @query(f"WITH {classes([k])} SELECT graph_id, k, freq, n_aut, array_to_string(sample, ',') AS sample FROM classes", f"x_freq_k{k}_session")
    def freq(spark, sf_dir):
        """Every class with its least member set, frequency and automorphisms."""
        return C.exact_census(session(spark, sf_dir), [k]).select("graph_id", "k", "freq", "n_aut", csv("sample"))


def _best(k: int) -> None:
    @query(f"WITH {classes([k])} SELECT graph_id, k, freq, array_to_string(sample, ',') AS sample FROM classes QUALIFY row_number() OVER (PARTITION BY graph_id ORDER BY freq DESC, sample) = 1", f"x_best_k{k}_session")
    def best(spark, sf_dir):
        return C.best_census(session(spark, sf_dir), [k], then="sample").select("graph_id", "k", "freq", csv("sample"))


for _k in (5, 6, 7):
    _census(_k)
for _k in (5, 6, 7, 8, 9):
    _best(_k)


@query(f"""WITH {classes(list(range(1, 10)))}, t AS (SELECT *, max(freq) OVER (PARTITION BY graph_id, k) AS best FROM classes)
SELECT graph_id, k, count(*) AS classes, CAST(sum(freq) AS BIGINT) AS sets, any_value(best) AS best, CAST(sum(CASE WHEN freq = best THEN 1 ELSE 0 END) AS BIGINT) AS ties FROM t GROUP BY 1, 2""")
def x_census_k1_9_session(spark, sf_dir):
    """All sizes from one to nine in one run: classes, sets, the best frequency and how many classes have it. What is saved is
    how many classes of a graph and size have each frequency, as there are about as many classes as connected sets."""
    census = C.exact_census(session(spark, sf_dir), list(range(1, 10))).select("graph_id", "k", "freq")
    alike = G.saved(census.groupBy("graph_id", "k", "freq").agg(F.count(F.lit(1)).alias("alike")))
    best = alike.groupBy("graph_id", "k").agg(F.sum("alike").alias("classes"), F.sum(F.col("alike") * F.col("freq")).alias("sets"), F.max("freq").alias("best"))
    ties = alike.join(G.shuffled(best), ["graph_id", "k"]).filter("freq = best").groupBy("graph_id", "k").agg(F.sum("alike").alias("ties"))
    return best.join(G.shuffled(ties), ["graph_id", "k"])


def _two_stage(k: int) -> None:
    @query(f"WITH {classes([k])} SELECT graph_id, k, freq FROM classes", f"x_two_stage_k{k}")
    def two_stage(spark, sf_dir):
        """The two-stage baseline: a miner with threshold one lists classes, the matcher counts each."""
        return C.two_stage(session(spark, sf_dir), k).select("graph_id", "k", "freq")


_two_stage(3)
_two_stage(5)


def _engine(name: str, k: int, run: Callable[[SparkSession, str], DataFrame]) -> None:
    query(f"WITH {classes([k])} SELECT graph_id, array_to_string(members, ',') AS members FROM sets", name)(lambda s, d: run(s, d).select("graph_id", csv("members")))


_engine("x_rows_k4", 4, lambda s, d: C.enumerate_rows(session(s, d), 4))
_engine("x_levels_k4", 4, lambda s, d: C.enumerate_levels(*S.session(s, d), 4))

# --- image support --------------------------------------------------------------------------------------------


def _support(k: int) -> None:
    @query(f"WITH {supports([k])} SELECT graph_id, k, freq, mni FROM mni", f"n_mni_k{k}")
    def mni(spark, sf_dir):
        return N.mni_census(session(spark, sf_dir), [k]).select("graph_id", "k", "freq", "mni")


for _k in (4, 5, 6):
    _support(_k)


@query(f"WITH {supports([4])} SELECT graph_id, k, freq, mni FROM mni")
def n_merged_k4(spark, sf_dir):
    """Images gathered root by root and merged by Spark, as for graphs of many units."""
    return N.mni_census(session(spark, sf_dir), [4], whole_units=0).select("graph_id", "k", "freq", "mni")


@query(f"WITH {supports([5, 6, 7, 8, 9])} SELECT graph_id, k, freq, mni FROM top")
def n_best_k5_9(spark, sf_dir):
    return N.best_support(session(spark, sf_dir), [5, 6, 7, 8, 9]).select("graph_id", "k", "freq", "mni")


@query(f"WITH {supports([3, 4, 5])} SELECT graph_id, k, freq, mni FROM top")
def n_descent_k5(spark, sf_dir):
    return N.baseline(N.descent(session(spark, sf_dir), [3, 4, 5])).select("graph_id", "k", "freq", "mni")


@query(f"WITH {supports([3, 4])} SELECT graph_id, k, freq, mni FROM (SELECT *, rank() OVER (PARTITION BY graph_id, k ORDER BY mni DESC) AS r FROM mni) WHERE r = 1")
def n_max_k4(spark, sf_dir):
    """All classes of highest support."""
    return N.max_mni(N.mni_census(session(spark, sf_dir), [3, 4])).select("graph_id", "k", "freq", "mni")


@query(f"WITH {supports([1, 2, 3, 4])} SELECT graph_id, k, freq, mni FROM mni WHERE mni >= 3")
def n_mine_t3(spark, sf_dir):
    """The level-wise miner with a threshold of three."""
    return N.mine(session(spark, sf_dir), 4, 3).select("graph_id", "k", "freq", "mni")


@query(f"""WITH {SESSION}, lab AS (SELECT graph_id, node, label_id AS l FROM s), p AS (
  SELECT graph_id, 1 AS k, 'n' || l AS kind, [node] AS m, [node] AS spots FROM lab
  UNION ALL SELECT b.graph_id, 2, 'e' || x.l || y.l, list_sort([a, o]), [a, o] FROM b JOIN lab x ON x.graph_id = b.graph_id AND x.node = a JOIN lab y ON y.graph_id = b.graph_id AND y.node = o WHERE x.l <= y.l
  UNION ALL SELECT b.graph_id, 3, 'p' || x.l || y.l || z.l, list_sort([b.a, b.o, c.o]), [b.a, b.o, c.o] FROM b JOIN b c ON c.graph_id = b.graph_id AND c.a = b.o AND c.o <> b.a JOIN lab x ON x.graph_id = b.graph_id AND x.node = b.a JOIN lab y ON y.graph_id = b.graph_id AND y.node = b.o JOIN lab z ON z.graph_id = b.graph_id AND z.node = c.o WHERE x.l <= z.l
  UNION ALL SELECT b.graph_id, 3, 't' || x.l || y.l || z.l, list_sort([b.a, b.o, c.o]), [b.a, b.o, c.o] FROM b JOIN b c ON c.graph_id = b.graph_id AND c.a = b.o JOIN b d ON d.graph_id = b.graph_id AND d.a = c.o AND d.o = b.a JOIN lab x ON x.graph_id = b.graph_id AND x.node = b.a JOIN lab y ON y.graph_id = b.graph_id AND y.node = b.o JOIN lab z ON z.graph_id = b.graph_id AND z.node = c.o WHERE x.l <= y.l AND y.l <= z.l),
f AS (SELECT graph_id, k, kind, count(DISTINCT m) AS freq FROM p GROUP BY 1, 2, 3),
i AS (SELECT graph_id, k, kind, place, count(DISTINCT node) AS c FROM (SELECT graph_id, k, kind, unnest(range(k)) AS place, unnest(spots) AS node FROM p) GROUP BY 1, 2, 3, 4)
SELECT f.graph_id, CAST(f.k AS INT) AS k, freq, min(c) AS mni FROM f JOIN i ON i.graph_id = f.graph_id AND i.k = f.k AND i.kind = f.kind GROUP BY f.graph_id, f.k, f.kind, freq""")
def n_plain_k3(spark, sf_dir):
    """Support of subgraphs that need not be induced."""
    return N.mine(session(spark, sf_dir), 3, 1, induced=False).select("graph_id", "k", "freq", "mni")


@query(f"WITH {supports([5, 6, 7])} SELECT top.k, count(*) AS graphs, CAST(sum(CASE WHEN freq < best THEN 1 ELSE 0 END) AS BIGINT) AS worse FROM top JOIN best ON best.graph_id = top.graph_id AND best.k = top.k GROUP BY 1")
def n_disagree_k5_7(spark, sf_dir):
    return N.disagreement(N.mni_census(session(spark, sf_dir), [5, 6, 7]))


# --- matching -------------------------------------------------------------------------------------------------

#: A click between two views that are no neighbours: labels of the places, then the bits of pairs (1,2) (1,3) (2,3).
WEDGE = "4.0.4:5"
_WEDGE = f"""{SESSION}, m AS (SELECT x.graph_id, x.o AS p, x.a AS c, y.o AS q FROM b x JOIN b y ON y.graph_id = x.graph_id AND y.a = x.a AND y.o <> x.o
JOIN s c ON c.graph_id = x.graph_id AND c.node = x.a AND c.label = 'click' JOIN s p ON p.graph_id = x.graph_id AND p.node = x.o AND p.label = 'view'
JOIN s q ON q.graph_id = x.graph_id AND q.node = y.o AND q.label = 'view' WHERE abs(x.o - y.o) > 2)"""


@query(f"WITH {_WEDGE} SELECT graph_id, concat_ws(',', p, c, q) AS mapping FROM m")
def f_match_wedge(spark, sf_dir):
    """Every isomorphism of a pattern onto induced subgraphs."""
    return M.match_pattern(session(spark, sf_dir), WEDGE).select("graph_id", csv("mapping"))


@query(f"WITH {_WEDGE} SELECT graph_id, count(*) AS freq FROM m WHERE p < q GROUP BY 1")
def f_frequency_wedge(spark, sf_dir):
    """Different node sets of a pattern, one mapping each."""
    return M.frequency(session(spark, sf_dir), WEDGE)


@query(f"WITH {classes([3, 4])} SELECT graph_id, k, freq * n_aut AS mappings FROM classes")
def f_mapping_count(spark, sf_dir):
    return M.mapping_count(C.exact_census(session(spark, sf_dir), [3, 4])).select("graph_id", "k", "mappings")


@query(f"WITH {classes([4])} SELECT graph_id, k, freq FROM classes")
def f_frequency_many_k4(spark, sf_dir):
    """Every class of every graph counted by matching."""
    graphs = G.saved(session(spark, sf_dir))
    return M.frequency_many(graphs, C.exact_census(graphs, [4]).select("graph_id", "k", "code")).select("graph_id", "k", "freq")


@query(f"WITH {classes([3, 4])} SELECT graph_id, k, freq FROM classes")
def f_frequencies_k4(spark, sf_dir):
    """The same with the choice between matching and a census left to the engine."""
    graphs = G.saved(session(spark, sf_dir))
    return M.frequencies(graphs, C.exact_census(graphs, [3, 4]).select("graph_id", "k", "code")).select("graph_id", "k", "freq")


@query(f"""WITH {classes([4])}, r AS (SELECT graph_id, k, kind, beg, p, unnest(range(4)) AS place, unnest(o) AS d FROM z),
o AS (SELECT graph_id, kind, beg, p, d, min(place) AS least FROM r GROUP BY 1, 2, 3, 4, 5),
q AS (SELECT graph_id, kind, beg, p, count(DISTINCT least) AS orbits FROM o GROUP BY 1, 2, 3, 4)
SELECT c.graph_id, c.freq, c.n_aut, any_value(orbits) AS orbits FROM classes c JOIN q ON q.graph_id = c.graph_id AND q.kind = c.kind GROUP BY c.graph_id, c.kind, c.freq, c.n_aut""")
def f_orbits_k4(spark, sf_dir):
    """Automorphisms and orbits of every class."""
    census = G.saved(C.exact_census(session(spark, sf_dir), [4]).select("graph_id", "code", "freq"))
    table = automorphisms(census.select("code"))
    return census.join(G.shuffled(table), "code").select("graph_id", "freq", "n_aut", F.size(F.array_distinct("orbits")).cast("long").alias("orbits"))


@query(f"""WITH {classes([3])} SELECT s.graph_id, array_to_string(members, ',') AS members, freq FROM sets s JOIN classes c ON c.graph_id = s.graph_id AND c.kind = s.kind WHERE members = [0, 1, 2] OR members = [1, 2, 4]""")
def f_lookup(spark, sf_dir):
    """Frequencies of given node sets from a saved census, as rewards look them up."""
    graphs = G.saved(session(spark, sf_dir))
    sets = graphs.filter("n > 4").select("graph_id", F.explode(F.expr("array(array(0, 1, 2), array(1, 2, 4))")).alias("members"))
    coded = C.code_sets(sets, graphs).withColumn("k", F.lit(3))
    return M.frequency_lookup(coded, C.exact_census(graphs, [3])).select("graph_id", csv("members"), "freq")


# --- random sampler -------------------------------------------------------------------------------------------


@query(f"WITH RECURSIVE {classes([3])}, {rollouts([3, 5])} SELECT graph_id, CAST(k AS INT) AS k, CAST(seed AS INT) AS seed, CAST(sample AS INT) AS sample, array_to_string(picked, ',') AS members FROM rolled")
def r_rollouts(spark, sf_dir):
    return P.random_rollouts(session(spark, sf_dir), [3, 5]).select("graph_id", "k", "seed", "sample", csv("members"))


def _sampled(sizes: list[int], where: str = "true", fold: bool = False, support: bool = False) -> str:
    """CTE hit: graph_id, k, seed, the highest frequency among the sampled classes, and the best of all."""
    return f"""{(supports if support else classes)(sizes, where, fold)}, {rollouts(sizes)},
hit AS (SELECT graph_id, k, seed, max(freq) AS freq FROM (SELECT DISTINCT r.graph_id, r.k, r.seed, c.freq FROM rolled r JOIN sets s ON s.graph_id = r.graph_id AND s.k = r.k AND s.members = list_sort(r.picked) JOIN classes c ON c.graph_id = s.graph_id AND c.k = s.k AND c.kind = s.kind) GROUP BY 1, 2, 3),
most AS (SELECT graph_id, k, max(freq) AS best FROM classes GROUP BY 1, 2)"""


@query(f"WITH RECURSIVE {_sampled([3, 5])} SELECT graph_id, CAST(k AS INT) AS k, CAST(seed AS INT) AS seed, freq FROM hit")
def r_best(spark, sf_dir):
    """The best of 100 samples, each class counted by the engine's choice of matching or census."""
    graphs = G.saved(session(spark, sf_dir))
    return P.random_baseline(graphs, P.random_rollouts(graphs, [3, 5])).select("graph_id", "k", "seed", "freq")


_SEEDS = "SELECT k, avg(ratio) AS ratio, stddev_samp(ratio) AS deviation, count(*) AS seeds FROM (SELECT k, seed, avg(freq / best) AS ratio FROM hit JOIN most USING (graph_id, k) GROUP BY 1, 2) GROUP BY 1"


@query(f"WITH RECURSIVE {_sampled([3, 5], fold=True)} SELECT CAST(k AS INT) AS k, round(ratio, 9) AS ratio, round(deviation, 9) AS deviation, seeds FROM ({_SEEDS})")
def w2_random_ratio(spark, sf_dir):
    """Random sampler on folded session graphs: its ratio falls with the size."""
    graphs = G.saved(session(spark, sf_dir, True))
    census = G.saved(C.exact_census(graphs, [3, 5]))
    found = P.random_baseline(graphs, P.random_rollouts(graphs, [3, 5]), census)
    return A.average_over_seeds(A.approx_ratio(found, census)).select("k", F.round("ratio", 9).alias("ratio"), F.round("deviation", 9).alias("deviation"), "seeds")


@query(f"""WITH RECURSIVE {classes([4])}, {rollouts([4], 20, 2)}, paid AS (SELECT r.graph_id, r.k, r.seed, r.sample, r.picked, c.freq / max(c.freq) OVER (PARTITION BY c.graph_id) AS ratio FROM classes c JOIN sets s ON s.graph_id = c.graph_id AND s.kind = c.kind LEFT JOIN rolled r ON r.graph_id = s.graph_id AND list_sort(r.picked) = s.members)
SELECT graph_id, CAST(k AS INT) AS k, CAST(seed AS INT) AS seed, CAST(sample AS INT) AS sample, CAST(step AS INT) AS step, array_to_string(picked[1 : step], ',') AS selected, CAST(picked[step + 1] AS INT) AS action, round(CASE WHEN step = 3 THEN ratio ELSE 0 END, 9) AS reward, step = 3 AS done FROM paid, range(4) AS t(step) WHERE picked IS NOT NULL""")
def t_transitions(spark, sf_dir):
    """The replay table of 20 rollouts of two seeds: states, actions, rewards from a census, ends."""
    graphs = G.saved(session(spark, sf_dir))
    census = G.saved(C.exact_census(graphs, [4]))
    rows = P.transitions(P.random_rollouts(graphs, [4], 20, 2), census, graphs)
    return rows.select("graph_id", "k", "seed", "sample", "step", csv("selected"), "action", F.round("reward", 9).alias("reward"), "done")


@query(f"WITH {classes([2, 3, 4])} SELECT graph_id, CAST(sum(freq) AS DOUBLE) AS sets, count(*) AS classes FROM classes WHERE k = 4 GROUP BY 1")
def r_enumeration_all(spark, sf_dir):
    """Sampled enumeration that keeps every branch: the estimates are the counts."""
    est = P.sample_enumeration(session(spark, sf_dir), 4, [1.0] * 4)
    return est.groupBy("graph_id").agg(F.sum("freq").alias("sets"), F.count(F.lit(1)).alias("classes"))


@query(f"WITH {classes([3, 4, 5])} SELECT k, round(100.0 * count(DISTINCT graph_id) / sum(freq), 9) AS fraction FROM classes GROUP BY 1")
def r_sample_fraction(spark, sf_dir):
    """Share of all connected sets that 100 samples for each graph are."""
    graphs = session(spark, sf_dir)
    space = C.search_space(graphs, [3, 4, 5])
    return space.groupBy("k").agg(F.round(F.lit(100.0) * F.count(F.lit(1)) / F.sum("sets"), 9).alias("fraction"))


# --- accuracy -------------------------------------------------------------------------------------------------


def _accuracy_sql(fold: bool) -> str:
    suite = "session3" if fold else "session"
    return f"""WITH RECURSIVE {_sampled([5, 6, 7, 8, 9], TEST, fold, True)}
SELECT '{suite}' AS suite, 'exact' AS method, CAST(k AS INT) AS k, 1.0::DOUBLE AS ratio, count(*) AS graphs FROM best GROUP BY k
UNION ALL SELECT '{suite}', 'mni', CAST(top.k AS INT), round(avg(freq / best), 9), count(*) FROM top JOIN best ON best.graph_id = top.graph_id AND best.k = top.k GROUP BY top.k
UNION ALL SELECT '{suite}', 'random', CAST(k AS INT), round(avg(ratio), 9), max(graphs) FROM (SELECT k, seed, avg(freq / best) AS ratio, count(*) AS graphs FROM hit JOIN most USING (graph_id, k) GROUP BY 1, 2) GROUP BY k"""


def _accuracy(fold: bool) -> None:
    @query(_accuracy_sql(fold), f"w2_accuracy_session{'3' if fold else ''}")
    def accuracy(spark, sf_dir):
        """Mean ratio of the exact census, the support miner and the random sampler (100 samples, 5 seeds) on the
        test graphs of the 80/20 split, sizes 5 to 9."""
        sizes, suite = [5, 6, 7, 8, 9], "session3" if fold else "session"
        test = G.saved(G.split_targets(session(spark, sf_dir, fold), 0.8).filter("split = 'test'"))
        census = G.saved(C.best_census(test, sizes))
        found = {"exact": census, "mni": N.best_support(test, sizes)}
        rows = [A.avg_ratio(A.approx_ratio(x, census)).select(F.lit(name).alias("method"), "k", "ratio", "graphs") for name, x in found.items()]
        random = A.approx_ratio(P.random_best(test, sizes), census)
        each = random.groupBy("seed", "k").agg(F.avg("ratio").alias("ratio"), F.count(F.lit(1)).alias("graphs"))
        rows.append(each.groupBy("k").agg(F.avg("ratio").alias("ratio"), F.max("graphs").alias("graphs")).select(F.lit("random").alias("method"), "k", "ratio", "graphs"))
        whole = rows[0].unionByName(rows[1]).unionByName(rows[2])
        return whole.select(F.lit(suite).alias("suite"), "method", "k", F.round("ratio", 9).alias("ratio"), "graphs")


_accuracy(False)
_accuracy(True)


@query(f"WITH {supports([2, 3, 4, 5])}, a AS (SELECT top.k, avg(freq / best) AS ratio FROM top JOIN best ON best.graph_id = top.graph_id AND best.k = top.k GROUP BY 1) SELECT round(stddev_samp(ratio), 9) AS deviation, round(max(ratio) - min(ratio), 9) AS spread FROM a")
def a_stability(spark, sf_dir):
    """Spread over sizes of the support miner's mean ratio."""
    census = G.saved(N.mni_census(session(spark, sf_dir), [2, 3, 4, 5]))
    got = A.stability(A.avg_ratio(A.approx_ratio(N.baseline(census), census)))
    return got.select(F.round("deviation", 9).alias("deviation"), F.round("spread", 9).alias("spread"))
