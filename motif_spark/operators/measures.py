"""Accuracy and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graphs import shuffled


def approx_ratio(found: DataFrame, truth: DataFrame) -> DataFrame:
    """Adds ratio, the found frequency over the best; a graph and size without an answer has ratio 0."""
    best = truth.groupBy("graph_id", "k").agg(F.max("freq").alias("best"))
    got = found.select("graph_id", "k", *[c for c in found.columns if c not in ("graph_id", "k", "best")])
    return best.join(shuffled(got), ["graph_id", "k"], "left").withColumn("ratio", F.coalesce(F.col("freq") / F.col("best"), F.lit(0.0)))


def avg_ratio(ratios: DataFrame, *by: str) -> DataFrame:
    """Mean ratio, share of exact hits and number of rows for each size."""
    return ratios.groupBy(*by, "k").agg(F.avg("ratio").alias("ratio"), F.avg((F.col("ratio") >= 1).cast("double")).alias("hit_rate"), F.count(F.lit(1)).alias("graphs"))


def average_over_seeds(ratios: DataFrame) -> DataFrame:
    """Mean and deviation over seeds of the mean ratio of each seed."""
    each = ratios.groupBy("seed", "k").agg(F.avg("ratio").alias("ratio"))
    return each.groupBy("k").agg(F.avg("ratio").alias("ratio"), F.stddev("ratio").alias("deviation"), F.count(F.lit(1)).alias("seeds"))


def stability(averages: DataFrame) -> DataFrame:
    """Spread of the mean ratio over sizes."""
    return averages.agg(F.stddev("ratio").alias("deviation"), (F.max("ratio") - F.min("ratio")).alias("spread"))


def timed(df: DataFrame) -> tuple[float, int]:
    """Seconds to compute all rows, and how many there are."""
    began = time.perf_counter()
    rows = df.count()
    return time.perf_counter() - began, rows


def speedup(exact_seconds: float, method_seconds: float) -> float:
    return exact_seconds / method_seconds


def sample_fraction(samples: int, space: DataFrame) -> float:
    """Subgraphs sampled over all there are."""
    return samples / space.agg(F.sum("sets")).first()[0]


def cost_model(n: int, m: int, d: int, k: int, layers: int = 1) -> dict[str, float]:
    """Operations of the encoder, the head, one step and a whole search, up to constants."""
    encoder, head = layers * (n * d * d + m * d), n * n * d + n * d * d
    return {"encoder": encoder, "head": head, "step": encoder + head, "search": k * (encoder + head)}


def slope(xs: list[float], ys: list[float]) -> float:
    """Least-squares slope, for the growth of time with k."""
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys)) / sum((x - mx) ** 2 for x in xs)


def growth(rows: DataFrame, by: str, x: str, y: str) -> DataFrame:
    """slope of the line through y against x, and bend: the share of y's variance that is beside the line."""
    fit = rows.groupBy(by).agg(F.regr_slope(y, x).alias("slope"), F.regr_r2(y, x).alias("r2"))
    return fit.select(by, "slope", (1 - F.col("r2")).alias("bend"))
