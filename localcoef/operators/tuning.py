"""Choice of the split weight: the variance of every bucket as a quadratic of it, and its minimax."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.model import Graph, bucket_sizes
from localcoef.operators.estimators import bag_triangles, bucket_weights, edge_shares, edge_values


def edge_lines(g: Graph, bag: DataFrame, buckets: DataFrame, w: DataFrame, m: int, few: bool = False) -> DataFrame:
    """(u, v, bucket, b, s): a distinct edge's value for a bucket is b + s * q at split weight q."""
    found = bag_triangles(g, bag, few)
    scales = bucket_weights(buckets, w)
    ends = edge_values(edge_shares(found, 0.5), scales, m).select("u", "v", "bucket", F.lit(0.0).alias("b"), F.col("x").alias("e"))
    corners = edge_values(edge_shares(found, 0.0), scales, m).select("u", "v", "bucket", F.col("x").alias("b"), F.lit(0.0).alias("e"))
    both = corners.unionByName(ends).groupBy("u", "v", "bucket").agg(F.sum("b").alias("b"), F.sum("e").alias("e"))
    return both.select("u", "v", "bucket", "b", (2 * (F.col("e") - F.col("b"))).alias("s"))


def line_sums(drawn: DataFrame, *keys: str) -> DataFrame:
    """Sums of the values b + s * q of draws, enough for their mean and variance at any split weight."""
    return drawn.groupBy(*keys, "bucket").agg(*[F.sum(x).alias(n) for n, x in (("b", F.col("b")), ("s", F.col("s")), ("bb", F.col("b") * F.col("b")), ("bs", F.col("b") * F.col("s")), ("ss", F.col("s") * F.col("s")))])


def split_quadratics(g: Graph, bag: DataFrame, buckets: DataFrame, w: DataFrame, m: int, c: int, few: bool = False) -> DataFrame:
    """(bucket, qa, qb, qc): the unbiased variance of a draw's value is qa + qb * x + qc * x^2 at split weight x.

    A draw's value is linear in the split weight, so five sums of its values at 0 and its slopes are enough; draws that
    do not touch a bucket count as zeros.
    """
    sums = line_sums(bag.join(edge_lines(g, bag, buckets, w, m, few), ["u", "v"]))
    full = bucket_sizes(buckets).select("bucket").join(sums, "bucket", "left").fillna(0.0)
    return full.select("bucket", *_quadratic(c))


def _quadratic(c: int) -> list:
    """The three coefficients from sums of c draws."""
    cov = lambda xy, x, y: (F.col(xy) - F.col(x) * F.col(y) / c) / (c - 1)
    return [cov("bb", "b", "b").alias("qa"), (2 * cov("bs", "b", "s")).alias("qb"), cov("ss", "s", "s").alias("qc")]


def tuned_from_sums(rows: Sequence, c: int) -> float:
    """The tuned split weight from rows of ``line_sums`` of c pilot draws; a bucket without a row varies nowhere."""
    if c < 2:
        return 1 / 3
    cov = lambda r, xy, x, y: (r[xy] - r[x] * r[y] / c) / (c - 1)
    return minimax_split([(0.0, 0.0, 0.0), *((cov(r, "bb", "b", "b"), 2 * cov(r, "bs", "b", "s"), max(cov(r, "ss", "s", "s"), 0.0)) for r in rows)])[0]


def minimax_split(rows: Sequence[tuple[float, float, float]], limit: int = 200) -> tuple[float, float]:
    """The x in [0, 1/2] that minimises the largest of the quadratics a + b x + c x^2 with c >= 0, and that value.

    The largest is convex; its minimum is at an end, at a vertex or where two of them cross. Beyond ``limit`` rows a
    section search is used. Ties go to the smaller x.
    """
    rows = [r for r in dict.fromkeys(rows)] or [(0.0, 0.0, 0.0)]
    top = lambda x: max(a + b * x + c * x * x for a, b, c in rows)
    if len(rows) > limit:
        low, high, golden = 0.0, 0.5, (5**0.5 - 1) / 2
        for _ in range(80):
            left, right = high - golden * (high - low), low + golden * (high - low)
            low, high = (low, right) if top(left) <= top(right) else (left, high)
        spots = [0.0, 0.5, (low + high) / 2]
    else:
        spots = [0.0, 0.5]
        for i, (a, b, c) in enumerate(rows):
            if c > 0:
                spots.append(-b / (2 * c))
            for a2, b2, c2 in rows[:i]:
                da, db, dc = a - a2, b - b2, c - c2
                if abs(dc) > 1e-300:
                    disc = db * db - 4 * da * dc
                    if disc >= 0:
                        spots += [(-db + disc**0.5) / (2 * dc), (-db - disc**0.5) / (2 * dc)]
                elif abs(db) > 1e-300:
                    spots.append(-da / db)
    spots = sorted(x for x in spots if 0 <= x <= 0.5)
    best = min(top(x) for x in spots)
    x = next(x for x in spots if top(x) <= best * (1 + 1e-12) + 1e-300)
    return x, top(x)


def variance_by_split(quadratics: DataFrame, grid: Sequence[float]) -> DataFrame:
    """(q, bucket, variance) over a grid."""
    points = F.explode(F.array(*[F.lit(float(x)) for x in grid]))
    return quadratics.withColumn("q", points).select("q", "bucket", (F.col("qa") + F.col("qb") * F.col("q") + F.col("qc") * F.col("q") * F.col("q")).alias("variance"))


def tune_split(g: Graph, bag: DataFrame, buckets: DataFrame, w: DataFrame, m: int, c: int, few: bool = False) -> float:
    """The tuned split weight from a pilot bag of c draws; one row for each bucket comes to the driver."""
    if c < 2:
        return 1 / 3
    rows = [(r["qa"], r["qb"], max(r["qc"], 0.0)) for r in split_quadratics(g, bag, buckets, w, m, c, few).collect()]
    return minimax_split(rows)[0]
