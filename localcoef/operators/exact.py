"""Exact degrees, wedges, triangles, local coefficients and bucket averages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from localcoef.model import Graph, check_coefficient
from localcoef.operators import bits
from localcoef.operators.packed import counted_triangles, headed_wedges, indexed, listed_triangles


def degrees(g: Graph) -> DataFrame:
    """(id, deg), isolated nodes with 0."""
    if g.packed is not None:
        return g.packed.deg
    ends = g.edges.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count("*").alias("deg"))
    return g.nodes.join(ends, "id", "left").select("id", F.coalesce("deg", F.lit(0)).cast("long").alias("deg"))


def listed_edges(g: Graph) -> DataFrame:
    """(u, v) of a graph of groups from bits or packed lists, so that no pair is shuffled."""
    made = g.bits() if g.bits is not None and g.packed is None else None
    out = bits.edges(made) if made is not None and made.classed is not None else None
    return indexed(g).edges if out is None else out


def wedges_centered(g: Graph) -> DataFrame:
    return degrees(g).select("id", F.expr("deg * (deg - 1) div 2").alias("wc"))


def wedges_headed(g: Graph) -> DataFrame:
    g = indexed(g)
    return g.nodes.join(headed_wedges(g.packed), "id", "left").select("id", F.coalesce("wh", F.lit(0)).cast("long").alias("wh"))


def denominators(g: Graph, coefficient: str) -> DataFrame:
    """(id, w): centred wedges, or half the headed ones."""
    check_coefficient(coefficient)
    if coefficient == "clustering":
        return wedges_centered(g).select("id", F.col("wc").cast("double").alias("w"))
    return wedges_headed(g).select("id", (F.col("wh") / 2).alias("w"))


def wedge_total(g: Graph) -> DataFrame:
    """The number of wedges of the graph, in a type that holds hubs of any size."""
    d = F.col("deg").cast("decimal(19,0)")
    return degrees(g).agg(F.coalesce(F.sum(d * (d - 1) / 2), F.lit(0)).cast("decimal(38,0)").alias("wedges"))


def oriented(g: Graph) -> DataFrame:
    """Each edge from its endpoint of lower (degree, id) to the other; out-degrees are then at most about sqrt(2 m)."""
    deg = degrees(g)
    both = g.edges.join(deg.withColumnRenamed("id", "u").withColumnRenamed("deg", "du"), "u").join(deg.withColumnRenamed("id", "v").withColumnRenamed("deg", "dv"), "v")
    up = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    return both.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("src"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("dst"))


def triangles(g: Graph) -> DataFrame:
    """(a, b, c) with a < b < c, each triangle once."""
    return listed_triangles(indexed(g).packed)


def triangle_count(g: Graph) -> DataFrame:
    """(n): the number of triangles, from those of each node, so that none is a row."""
    return counted_triangles(indexed(g).packed).agg(F.expr("coalesce(sum(t), 0) div 3").alias("n"))


def edge_triangles(g: Graph) -> DataFrame:
    """(u, v, n): triangles of every edge, also of those without."""
    sides = triangles(g).select(F.inline(F.array(*[F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in ("ab", "ac", "bc")])))
    return g.edges.join(sides.groupBy("u", "v").agg(F.count("*").alias("n")), ["u", "v"], "left").select("u", "v", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def corner_counts(found: DataFrame, name: str = "t") -> DataFrame:
    return found.select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count("*").alias(name))


def node_triangles(g: Graph) -> DataFrame:
    g = indexed(g)
    return g.nodes.join(counted_triangles(g.packed), "id", "left").select("id", F.coalesce("t", F.lit(0)).cast("long").alias("t"))


def ratio(t: Column, w: Column) -> Column:
    """A node without wedges has coefficient 0."""
    return F.when(w > 0, t / w).otherwise(F.lit(0.0))


def local_coefficients(g: Graph, coefficient: str) -> DataFrame:
    """(id, psi)."""
    g = indexed(g)
    return node_triangles(g).join(denominators(g, coefficient), "id").select("id", ratio(F.col("t"), F.col("w")).alias("psi"))


def local_coefficients_bruteforce(g: Graph, coefficient: str) -> DataFrame:
    """For tests: closed pairs of neighbours over all pairs, or closed two-step walks over all."""
    check_coefficient(coefficient)
    adj = g.adjacency
    if coefficient == "clustering":
        pairs = adj.select(F.col("src").alias("id"), F.col("dst").alias("x")).join(adj.select(F.col("src").alias("id"), F.col("dst").alias("y")), "id").where("x < y")
        ends = ("x", "y")
    else:
        pairs = adj.select(F.col("src").alias("id"), F.col("dst").alias("x")).join(adj.select(F.col("src").alias("x"), F.col("dst").alias("y")), "x").where("id <> y")
        ends = ("id", "y")
    closed = adj.select(F.col("src").alias(ends[0]), F.col("dst").alias(ends[1]), F.lit(1).alias("hit"))
    found = pairs.join(closed, list(ends), "left").groupBy("id").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("psi"))
    return g.nodes.join(found, "id", "left").select("id", F.coalesce("psi", F.lit(0.0)).alias("psi"))


def node_profile(g: Graph) -> DataFrame:
    """(id, deg, t, wc, wh, alpha, phi) of every node."""
    g = indexed(g)
    all_of = node_triangles(g).join(degrees(g), "id").join(wedges_headed(g), "id").withColumn("wc", F.expr("deg * (deg - 1) div 2"))
    return all_of.select("id", "deg", "t", "wc", "wh", ratio(F.col("t"), F.col("wc")).alias("alpha"), ratio(2 * F.col("t"), F.col("wh")).alias("phi"))


def exact_bucket_means(g: Graph, buckets: DataFrame, coefficient: str) -> DataFrame:
    """(bucket, size, psi)."""
    return local_coefficients(g, coefficient).join(buckets, "id").groupBy("bucket").agg(F.count("*").alias("size"), F.avg("psi").alias("psi"))


def subset_mean(g: Graph, chosen: DataFrame, coefficient: str) -> DataFrame:
    """The average over the nodes whose id is in ``chosen``."""
    return local_coefficients(g, coefficient).join(chosen.select("id"), "id", "left_semi").agg(F.count("*").alias("size"), F.coalesce(F.avg("psi"), F.lit(0.0)).alias("psi"))


def graph_profile(g: Graph) -> DataFrame:
    """(n, m, dmax, alpha, phi): the statistics of a graph in one row."""
    made = g.bits() if g.bits is not None and g.packed is None else None
    if made is None:
        nodes = node_profile(g).agg(F.count("*").alias("n"), (F.sum("deg") / 2).cast("long").alias("m"), F.max("deg").alias("dmax"), F.avg("alpha").alias("alpha"), F.avg("phi").alias("phi"))
    else:
        mean = lambda x: F.sum(F.col("size") * x) / F.sum("size")
        nodes = bits.profile(made).agg(F.sum("size").alias("n"), (F.sum(F.col("size") * F.col("deg")) / 2).cast("long").alias("m"), F.max("deg").alias("dmax"), mean(ratio(F.col("t"), F.col("wc"))).alias("alpha"), mean(ratio(2 * F.col("t"), F.col("wh"))).alias("phi"))
    return nodes.select(F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("m", F.lit(0)).cast("long").alias("m"), F.coalesce("dmax", F.lit(0)).cast("long").alias("dmax"), F.coalesce("alpha", F.lit(0.0)).alias("alpha"), F.coalesce("phi", F.lit(0.0)).alias("phi"))


def weighted_clustering(g: Graph, weights: DataFrame) -> DataFrame:
    """(id, psi): clustering with edge weights (u, v, weight), each closed pair counted by the mean of its two edges' weights."""
    w = weights.select("u", "v", "weight")
    both = w.unionByName(w.select(F.col("v").alias("u"), F.col("u").alias("v"), "weight"))
    strength = both.groupBy("u").agg(F.sum("weight").alias("s"), F.count("*").alias("d")).withColumnRenamed("u", "id")
    corners = triangles(g).select(F.inline(F.array(*[F.struct(F.col(i).alias("id"), F.col(x).alias("x"), F.col(y).alias("y")) for i, x, y in ("abc", "bac", "cab")])))
    at = lambda name, out: both.select(F.col("u").alias("id"), F.col("v").alias(name), F.col("weight").alias(out))
    closed = corners.join(at("x", "wx"), ["id", "x"]).join(at("y", "wy"), ["id", "y"]).groupBy("id").agg(F.sum(F.col("wx") + F.col("wy")).alias("c"))
    full = g.nodes.join(strength, "id", "left").join(closed, "id", "left")
    return full.select("id", F.when(F.col("d") > 1, F.coalesce("c", F.lit(0.0)) / (F.col("s") * (F.col("d") - 1))).otherwise(F.lit(0.0)).alias("psi"))
