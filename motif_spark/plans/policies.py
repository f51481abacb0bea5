"""Trained policies: how they are made from a suite's training graphs, and the ones that come with the package."""

from __future__ import annotations

import os
from dataclasses import asdict

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import census as C
from ..operators import graphs as G
from ..operators import learning as L
from ..operators import network as net
from ..operators import training as T
from ..sources import suites as S

MODELS = os.path.join(os.path.dirname(os.path.dirname(os.path.abspath(__file__))), "models")
#: The network of the shipped policies.
CONFIG = net.Config(labels=3, width=32, heads=2, layers=3, k_max=9, residual=True)


def school(spark: SparkSession, sf_dir: str, suite: str, sizes: list[int], valid: float = 0.1, most: int | None = None, splits: tuple[str, ...] = ("train", "valid", "test")) -> dict[str, DataFrame]:
    """Lessons of the training, validation and test graphs of a suite; rewards come from each split's own census.

    most: training takes at most so many graphs, the first by a hash of the id; other splits are whole.
    """
    graphs = G.saved(G.split_targets(S.packed(spark, sf_dir, suite), 0.8, valid))
    parts = spark.sparkContext.defaultParallelism
    out = {}
    for split in splits:
        own = graphs.filter(f"split = '{split}'")
        if split == "train" and most:
            own = G.saved(own.orderBy(F.xxhash64("graph_id"), "graph_id").limit(most))
        out[split] = T.lessons(own, C.exact_census(own, sizes), parts)
    return out


def save(policy: L.Policy, name: str) -> str:
    """Weights, network and curve in one file of the package."""
    os.makedirs(MODELS, exist_ok=True)
    path = os.path.join(MODELS, f"{name}.npz")
    np.savez_compressed(path, **{f"w:{k}": x.astype(np.float16) for k, x in policy.actor.items()}, config=np.array(str(asdict(policy.config))), curve=np.array(str(policy.curve)))
    return path


def load(name: str) -> L.Policy:
    import ast

    with np.load(os.path.join(MODELS, f"{name}.npz")) as f:
        config = net.Config(**ast.literal_eval(str(f["config"])))
        actor = {k[2:]: f[k].astype(np.float32) for k in f.files if k.startswith("w:")}
        return L.Policy(config, actor, ast.literal_eval(str(f["curve"])))
