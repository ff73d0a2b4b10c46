"""Edge-split estimators: each drawn edge shares out the triangles on it among its ends and their common neighbours."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from localcoef.model import Graph, bucket_sizes
from localcoef.operators.exact import degrees, triangles


def bag_triangles(g: Graph, bag: DataFrame, few: bool = False) -> DataFrame:
    """(u, v, w) for the distinct edges of a bag and their common neighbours w.

    The neighbours come from the endpoint of lower degree and are kept if they are joined to the other one. With
    ``few``, for a bag of bounded size, its endpoints are broadcast: the edges are only scanned, and what is shuffled
    is the neighbourhood of the drawn edges.
    """
    drawn = bag.select("u", "v").distinct()
    if few:
        return _few_triangles(g, drawn)
    deg = degrees(g)
    ends = drawn.join(deg.select(F.col("id").alias("u"), F.col("deg").alias("du")), "u").join(deg.select(F.col("id").alias("v"), F.col("deg").alias("dv")), "v")
    small = F.col("du") <= F.col("dv")
    ends = ends.select("u", "v", F.when(small, F.col("u")).otherwise(F.col("v")).alias("src"), F.when(small, F.col("v")).otherwise(F.col("u")).alias("far"))
    near = ends.join(g.adjacency, "src").where("dst <> far").select("u", "v", F.col("dst").alias("w"), F.least("far", "dst").alias("x"), F.greatest("far", "dst").alias("y"))
    closing = g.edges.select(F.col("u").alias("x"), F.col("v").alias("y"))
    return near.join(closing, ["x", "y"], "left_semi").select("u", "v", "w")


def all_triangles(g: Graph) -> DataFrame:
    """(u, v, w) as of a bag of all edges, from each triangle listed once."""
    sides = [F.struct(*[F.col(x).alias(n) for x, n in zip(corners, "uvw", strict=True)]) for corners in ("abc", "acb", "bca")]
    return triangles(g).select(F.inline(F.array(*sides)))


def _few_triangles(g: Graph, drawn: DataFrame) -> DataFrame:
    touched = drawn.select(F.explode(F.array("u", "v")).alias("src")).distinct()
    around = g.adjacency.join(F.broadcast(touched), "src", "left_semi")
    deg = around.groupBy("src").agg(F.count("*").alias("deg"))
    ends = drawn.join(deg.select(F.col("src").alias("u"), F.col("deg").alias("du")), "u").join(deg.select(F.col("src").alias("v"), F.col("deg").alias("dv")), "v")
    small = F.col("du") <= F.col("dv")
    ends = ends.select("u", "v", F.when(small, F.col("u")).otherwise(F.col("v")).alias("src"), F.when(small, F.col("v")).otherwise(F.col("u")).alias("far"))
    near = g.adjacency.join(F.broadcast(ends), "src").where("dst <> far").select("u", "v", F.col("far").alias("x"), F.col("dst").alias("w"))
    closing = around.select(F.col("src").alias("x"), F.col("dst").alias("w"))
    return near.join(closing, ["x", "w"], "left_semi").select("u", "v", "w")


def check_split(q: float) -> None:
    if not 0 <= q <= 0.5:
        raise ValueError("the split weight lies between 0 and 1/2")


def edge_shares(found: DataFrame, q: float, weight: Column | None = None) -> DataFrame:
    """(u, v, node, a): what each distinct edge of (u, v, w) gives to its ends and to the opposite corners."""
    check_split(q)
    weight = F.lit(1.0) if weight is None else weight
    ends = found.groupBy("u", "v").agg(F.sum(weight * q).alias("a")).select("u", "v", F.explode(F.array("u", "v")).alias("node"), "a")
    if q == 0.5:
        return ends
    corners = found.select("u", "v", F.col("w").alias("node"), (weight * (1 - 2 * q)).alias("a"))
    return corners if q == 0 else ends.unionByName(corners)


def edge_credits(g: Graph, bag: DataFrame, q: float) -> DataFrame:
    """(ix, node, a) for every draw; an edge drawn more than once is worked out once."""
    return bag.join(edge_shares(bag_triangles(g, bag), q), ["u", "v"]).select("ix", "node", "a")


def estimate_node_triangles(g: Graph, bag: DataFrame, s: int, m: int, q: float) -> DataFrame:
    """(id, t_hat): unbiased for every node's number of triangles; nodes that no draw touches are left out, as zeros."""
    return edge_credits(g, bag, q).groupBy(F.col("node").alias("id")).agg((F.sum("a") * m / s).alias("t_hat"))


def bucket_weights(buckets: DataFrame, w: DataFrame) -> DataFrame:
    """(node, bucket, scale): one over the bucket's size and the node's wedges; nodes without wedges have no row."""
    sizes = bucket_sizes(buckets)
    return buckets.select("id", "bucket").join(w.where("w > 0"), "id").join(sizes, "bucket").select(F.col("id").alias("node"), "bucket", (1 / (F.col("w") * F.col("size"))).alias("scale"))


def edge_values(shares: DataFrame, scales: DataFrame, m: int) -> DataFrame:
    """(u, v, bucket, x): the value of each distinct edge for the buckets it touches; all others are zero."""
    return shares.join(scales, "node").groupBy("u", "v", "bucket").agg((F.sum(F.col("a") * F.col("scale")) * m).alias("x"))


def edge_bucket_values(g: Graph, bag: DataFrame, buckets: DataFrame, w: DataFrame, m: int, q: float, few: bool = False) -> DataFrame:
    """(ix, bucket, x)."""
    values = edge_values(edge_shares(bag_triangles(g, bag, few), q), bucket_weights(buckets, w), m)
    return bag.join(values, ["u", "v"]).select("ix", "bucket", "x")


def moments(values: DataFrame) -> DataFrame:
    """(bucket, sx, sxx); zeros are implied, so divide by the number of draws."""
    return values.groupBy("bucket").agg(F.sum("x").alias("sx"), F.sum(F.col("x") * F.col("x")).alias("sxx"))


def bucket_means(values: DataFrame, buckets: DataFrame, s: int) -> DataFrame:
    """(bucket, size, f): buckets that no draw touches have 0."""
    return bucket_sizes(buckets).join(moments(values), "bucket", "left").select("bucket", "size", (F.coalesce("sx", F.lit(0.0)) / s).alias("f"))


def all_edge_values(g: Graph, buckets: DataFrame, w: DataFrame, m: int, q: float) -> DataFrame:
    """(u, v, bucket, x) of every edge, for exact expectations, variances and ranges."""
    return edge_values(edge_shares(all_triangles(g), q), bucket_weights(buckets, w), m)


def exact_edge_moments(g: Graph, buckets: DataFrame, w: DataFrame, m: int, q: float) -> DataFrame:
    """(bucket, mean, variance, largest) of a single draw's value over all edges."""
    found = all_edge_values(g, buckets, w, m, q).groupBy("bucket").agg(F.sum("x").alias("sx"), F.sum(F.col("x") * F.col("x")).alias("sxx"), F.max("x").alias("largest"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    mean = zero("sx") / m
    return bucket_sizes(buckets).join(found, "bucket", "left").select("bucket", mean.alias("mean"), (zero("sxx") / m - mean * mean).alias("variance"), zero("largest").alias("largest"))


def importance_means(g: Graph, bag: DataFrame, buckets: DataFrame, w: DataFrame, s: int, q: float) -> DataFrame:
    """(bucket, size, f) from a bag with probabilities: (ix, u, v, p)."""
    values = edge_values(edge_shares(bag_triangles(g, bag), q), bucket_weights(buckets, w), 1)
    drawn = bag.join(values, ["u", "v"]).select("bucket", (F.col("x") / F.col("p")).alias("x"))
    return bucket_means(drawn, buckets, s)


def min_degree_weights(g: Graph) -> DataFrame:
    """(u, v, weight): the smaller degree less one, which is positive wherever there is a triangle."""
    deg = degrees(g)
    both = g.edges.join(deg.select(F.col("id").alias("u"), F.col("deg").alias("du")), "u").join(deg.select(F.col("id").alias("v"), F.col("deg").alias("dv")), "v")
    return both.select("u", "v", (F.least("du", "dv") - 1).alias("weight"))
