"""SQL functions: codes, isomorphism, induced bits, vector sums, and table functions."""

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udtf(returnType="k int, members array<int>, code string")
class EnumerateSubgraphs:
    """Connected induced subgraphs of a packed graph given as (label_ids, nbrs, k_max)."""

    def eval(self, label_ids, nbrs, k_max):
        from motif_spark.operators.census import code_of, enumerate_sets, masks

        for s in enumerate_sets(masks(nbrs), k_max):
            yield len(s), sorted(s), code_of(list(s), label_ids, nbrs)


@F.udtf(returnType="graph_id bigint, k int, sets bigint")
class CountSubgraphs:
    """Connected sets by size of the packed rows of a table argument, partition by partition."""

    def __init__(self):
        self.counts = {}

    def eval(self, row, k_max):
        from motif_spark.operators.census import enumerate_sets, masks

        for s in enumerate_sets(masks(row["nbrs"]), k_max):
            key = (row["graph_id"], len(s))
            self.counts[key] = self.counts.get(key, 0) + 1

    def terminate(self):
        for (graph, k), sets in self.counts.items():
            yield graph, k, sets


@F.udtf(returnType="node int, parent int, tag string")
class HtmlTree:
    """Elements of a page with their parents."""

    def eval(self, html):
        from motif_spark.sources.suites import html_tree

        yield from html_tree(html)


def mine_udtf(policy):
    """A table function (label_ids, nbrs, k) -> members by greedy search with a trained policy."""

    @F.udtf(returnType="members array<int>")
    class Mine:
        def eval(self, label_ids, nbrs, k):
            from motif_spark.operators.learning import rollout

            yield (sorted(rollout(policy.actor, policy.config, [(list(label_ids), [list(x) for x in nbrs])], [k])[0]),)

    return Mine


#: A SQL function, so it stays in the plan: pairs of members in the order given, first pair highest.
INDUCED_BITS = """
CREATE OR REPLACE TEMPORARY FUNCTION induced_bits(nbrs ARRAY<ARRAY<INT>>, members ARRAY<INT>) RETURNS BIGINT RETURN
aggregate(
  flatten(transform(sequence(1, greatest(size(members) - 1, 1)), i -> transform(slice(members, i + 1, size(members)), y -> array_contains(element_at(nbrs, element_at(members, i) + 1), y)))),
  0L, (a, b) -> a * 2 + CAST(b AS BIGINT))
"""


def register_all(spark: SparkSession, policy=None) -> None:
    """motif_code(labels, bits), motif_isomorphic(a, b), induced_bits(nbrs, members), vec_sum(array), enumerate_subgraphs,
    count_subgraphs, html_tree, mine."""

    @F.pandas_udf(T.StringType())
    def motif_code(labels: pd.Series, bits: pd.Series) -> pd.Series:
        from motif_spark.operators.canonical import canonical_of

        return pd.Series([canonical_of(tuple(int(v) for v in x), int(b))[0] for x, b in zip(labels, bits)])

    @F.pandas_udf(T.BooleanType())
    def motif_isomorphic(a: pd.Series, b: pd.Series) -> pd.Series:
        from motif_spark.operators.canonical import is_isomorphic

        return pd.Series([is_isomorphic(x, y) for x, y in zip(a, b)])

    @F.pandas_udf("array<double>")
    def vec_sum(v: pd.Series) -> list:
        return np.sum(np.stack(v.to_list()), 0).tolist()

    for name, f in (("motif_code", motif_code), ("motif_isomorphic", motif_isomorphic), ("vec_sum", vec_sum)):
        spark.udf.register(name, f)
    spark.sql(INDUCED_BITS)
    spark.udtf.register("enumerate_subgraphs", EnumerateSubgraphs)
    spark.udtf.register("count_subgraphs", CountSubgraphs)
    spark.udtf.register("html_tree", HtmlTree)
    if policy is not None:
        spark.udtf.register("mine", mine_udtf(policy))


def vec_sum_native(df, by: list[str], vector: str):
    """Sum of arrays by place, in DataFrame functions."""
    places = df.select(*by, F.posexplode(vector).alias("at", "x")).groupBy(*by, "at").agg(F.sum("x").alias("x"))
    return places.groupBy(*by).agg(F.transform(F.sort_array(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias(vector))
