"""Bounds that are read off the graph and its partition: neighbour buckets, dimension, and ranges of values."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcoef.model import Graph, bucket_sizes
from localcoef.operators.estimators import check_split
from localcoef.operators.exact import degrees


def bucket_spread(g: Graph, buckets: DataFrame, closed: bool = True) -> DataFrame:
    """(id, chi): how many buckets a node's neighbours lie in, with its own if ``closed``."""
    there = g.adjacency.join(buckets.select(F.col("id").alias("dst"), "bucket"), "dst").select(F.col("src").alias("id"), "bucket")
    if closed:
        there = there.unionByName(buckets.select("id", "bucket"))
    found = there.distinct().groupBy("id").agg(F.count("*").alias("chi"))
    return g.nodes.join(found, "id", "left").select("id", F.coalesce("chi", F.lit(0)).alias("chi"))


def spread_sup(g: Graph, buckets: DataFrame, closed: bool = True) -> DataFrame:
    """(chi): the largest spread of an edge, each taken at its end of lower degree, the smaller one on equal degrees."""
    at = degrees(g).join(bucket_spread(g, buckets, closed), "id")
    ends = g.edges.join(at.select(F.col("id").alias("u"), F.col("deg").alias("du"), F.col("chi").alias("cu")), "u").join(at.select(F.col("id").alias("v"), F.col("deg").alias("dv"), F.col("chi").alias("cv")), "v")
    chi = F.when(F.col("du") < F.col("dv"), F.col("cu")).when(F.col("dv") < F.col("du"), F.col("cv")).otherwise(F.least("cu", "cv"))
    return ends.agg(F.coalesce(F.max(chi), F.lit(1)).cast("long").alias("chi"))


def dimension_bound(chi: int, q: float | None = None) -> int:
    """floor(log2 chi) + 1; with q = 1/2 an edge touches the buckets of its two ends only."""
    if q == 0.5:
        chi = min(chi, 2)
    return int(math.floor(math.log2(max(1, chi)))) + 1


def range_bounds(g: Graph, buckets: DataFrame, w: DataFrame, m: int, q: float, tight: bool = False) -> DataFrame:
    """(bucket, r): at least the value of every edge.

    An edge has no more triangles than its smaller degree less one, and its common neighbours are neighbours of its end
    of lower degree other than the far end. So an edge is bounded by that many shares at its ends and the sum of the
    inverse wedges of that end's neighbours in the bucket; with ``tight`` by the smaller of both ends' sums. All is in
    long rows (node, bucket), so a hub is no wide row.
    """
    check_split(q)
    weighted = w.where("w > 0").join(buckets.select("id", "bucket"), "id").select("id", "bucket", (1 / F.col("w")).alias("iw"))
    largest = _tight_largest(g, weighted, q) if tight and q < 0.5 else _largest(g, buckets, weighted, q)
    return bucket_sizes(buckets).join(largest, "bucket", "left").select("bucket", (F.coalesce("x", F.lit(0.0)) * m / F.col("size")).alias("r"))


def _largest(g: Graph, buckets: DataFrame, weighted: DataFrame, q: float) -> DataFrame:
    """(bucket, x) without a row for each edge and bucket.

    At a node z, the low end of some edges, an edge's bound in a bucket depends on its far end only if that lies in the
    bucket, and then it is convex in the far end's inverse wedges. So their least and largest, and whether a far end
    lies elsewhere, give the largest bound of z in the bucket.
    """
    node = degrees(g).join(buckets.select("id", "bucket"), "id", "left").join(weighted.select("id", "iw"), "id", "left").select("id", "deg", "bucket", F.coalesce("iw", F.lit(0.0)).alias("iw"))
    far = node.select(F.col("id").alias("dst"), F.col("deg").alias("far_deg"), "bucket", "iw")
    near = degrees(g).select(F.col("id").alias("src"), "deg")
    low = (F.col("deg") < F.col("far_deg")) | ((F.col("deg") == F.col("far_deg")) & (F.col("src") < F.col("dst")))
    around = g.adjacency.join(far, "dst").join(near, "src").select("src", "bucket", "iw", low.alias("low"), F.lit(None).cast("double").alias("own"), F.lit(None).cast("long").alias("t"))
    self = node.select(F.col("id").alias("src"), "bucket", F.lit(0.0).alias("iw"), F.lit(False).alias("low"), F.col("iw").alias("own"), (F.col("deg") - 1).alias("t"))
    lows = F.when(F.col("low"), F.col("iw"))
    cells = around.unionByName(self).groupBy("src", "bucket").agg(
        F.sum("iw").alias("around"), F.count_if("low").alias("n"), F.min(lows).alias("least"), F.max(lows).alias("most"), F.coalesce(F.max("own"), F.lit(0.0)).alias("own"), F.max("t").alias("t")
    )
    of_node = Window.partitionBy("src")
    cells = cells.withColumn("t", F.max("t").over(of_node)).withColumn("all", F.sum("n").over(of_node)).where("t > 0 and bucket is not null")
    bound = lambda there: F.greatest(F.col("around") - there, F.lit(0.0)) * (1 - 2 * q) + (F.col("own") + there) * F.col("t") * q
    x = F.greatest(F.when(F.col("n") > 0, F.greatest(bound(F.col("least")), bound(F.col("most")))), F.when(F.col("n") < F.col("all"), bound(F.lit(0.0))))
    return cells.groupBy("bucket").agg(F.max(x).alias("x"))


def _tight_largest(g: Graph, weighted: DataFrame, q: float) -> DataFrame:
    """(bucket, x) from a row for each edge and each bucket around both of its ends."""
    deg = degrees(g)
    around = g.adjacency.join(weighted.select(F.col("id").alias("dst"), "bucket", "iw"), "dst").groupBy(F.col("src").alias("z"), "bucket").agg(F.sum("iw").alias("around"))
    d = lambda end: deg.select(F.col("id").alias(end), F.col("deg").alias(f"d{end}"))
    edges = g.edges.join(d("u"), "u").join(d("v"), "v")
    small = F.col("du") <= F.col("dv")
    edges = edges.select("u", "v", F.when(small, F.col("u")).otherwise(F.col("v")).alias("z"), F.when(small, F.col("v")).otherwise(F.col("u")).alias("o"), (F.least("du", "dv") - 1).alias("t"))
    # what the two ends get themselves
    ends = edges.where("t > 0").select("u", "v", F.explode(F.array("u", "v")).alias("id"), "t").join(weighted, "id").select("u", "v", "bucket", (F.col("iw") * F.col("t") * q).alias("x"))
    other = _side(edges, around, weighted, "o", "z").withColumnRenamed("s", "s2")
    corner = _side(edges, around, weighted, "z", "o").join(other, ["u", "v", "bucket"]).select("u", "v", "bucket", (F.least("s", "s2") * (1 - 2 * q)).alias("x"))
    return ends.unionByName(corner).groupBy("u", "v", "bucket").agg(F.sum("x").alias("x")).groupBy("bucket").agg(F.max("x").alias("x"))


def _side(edges: DataFrame, around: DataFrame, weighted: DataFrame, end: str, far: str) -> DataFrame:
    """(u, v, bucket, s): the inverse wedges around one end of each edge, without the far end."""
    sums = edges.where("t > 0").join(around.withColumnRenamed("z", end), end).select("u", "v", "bucket", F.col("around").alias("s"))
    less = edges.where("t > 0").join(weighted.withColumnRenamed("id", far), far).select("u", "v", "bucket", (-F.col("iw")).alias("s"))
    return sums.unionByName(less).groupBy("u", "v", "bucket").agg(F.greatest(F.sum("s"), F.lit(0.0)).alias("s"))
