"""The methods' scalar and table functions, for use from SQL."""

from __future__ import annotations

import hashlib
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from localcoef.functions.concentration import bernstein_halfwidth, plugin_loop
from localcoef.operators.tuning import minimax_split


def bernstein_batch(v: pd.Series, r: pd.Series, s: pd.Series, k: pd.Series, eta: pd.Series) -> pd.Series:
    log = np.log(4 * k / eta)
    return np.sqrt(2 * v.clip(lower=0) * log / s) + 7 * r * log / (3 * (s - 1))


class DrawEdges:
    """(ix, u01): the first n uniform numbers of a seed's main stream, as ``sampling.uniform`` gives them."""

    def eval(self, n: int, seed: int):
        for ix in range(n):
            yield ix, int(hashlib.md5(f"{seed}:main:{ix}".encode()).hexdigest()[:13], 16) / 2**52


class EnumeratePairs:
    """(a, b): the pairs of a short list, in order."""

    def eval(self, items: list[int]):
        yield from combinations(sorted(set(items or ())), 2)


def register_all(spark: SparkSession) -> list[str]:
    """Registers all functions for SQL and returns their names."""
    spark.udf.register("bernstein_halfwidth", F.pandas_udf(bernstein_batch, "double"))
    spark.udf.register("minimax_split", F.udf(lambda rows: float(minimax_split([tuple(r) for r in rows or ()])[0]), "double"))
    spark.udf.register("plugin_bernstein", F.pandas_udf(_plugin_aggregate, "double"))
    spark.udtf.register("draw_edges", F.udtf(DrawEdges, returnType="ix long, u01 double"))
    spark.udtf.register("enumerate_pairs", F.udtf(EnumeratePairs, returnType="a long, b long"))
    return ["bernstein_halfwidth", "minimax_split", "plugin_bernstein", "draw_edges", "enumerate_pairs"]


def _plugin_aggregate(x: pd.Series, r: pd.Series, eta: pd.Series) -> float:
    return plugin_loop(x.tolist(), float(r.iloc[0]), float(eta.iloc[0]))[1]


__all__ = ["bernstein_halfwidth", "register_all"]
