"""Exact treatment of nodes of low degree, and the graph that is left for sampling."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcoef.model import Graph, bucket_sizes
from localcoef.operators.exact import corner_counts, degrees, oriented


def degree_budget(g: Graph) -> DataFrame:
    """(deg, nodes, work): running work deg^2 * nodes over the degree histogram."""
    histogram = degrees(g).groupBy("deg").agg(F.count("*").alias("nodes"))
    work = F.sum(F.col("deg") * F.col("deg") * F.col("nodes")).over(Window.orderBy("deg"))
    return histogram.withColumn("work", work)


def low_degree_threshold(g: Graph, work_factor: float) -> DataFrame:
    """(beta): the largest degree up to which the work is at most ``work_factor`` times the number of nodes."""
    rows = degree_budget(g)
    total = F.sum("nodes").over(Window.partitionBy())
    return rows.withColumn("n", total).agg(F.coalesce(F.max(F.when(F.col("work") <= F.col("n") * work_factor, F.col("deg"))), F.lit(0)).cast("long").alias("beta"))


def low_degree_triangles(g: Graph, beta: int, inclusive: bool = True) -> DataFrame:
    """(a, b, c): triangles with a corner of low degree, each once, at its lowest corner, which is low itself."""
    low = degrees(g).where(F.col("deg") <= beta if inclusive else F.col("deg") < beta).select(F.col("id").alias("src"))
    out = oriented(g).join(low, "src", "left_semi")
    pairs = out.withColumnRenamed("dst", "x").join(out.withColumnRenamed("dst", "y"), "src").where("x < y")
    closed = pairs.join(g.edges, (F.col("x") == F.col("u")) & (F.col("y") == F.col("v")), "left_semi")
    corners = F.sort_array(F.array("src", "x", "y"))
    return closed.select(*[corners[i].alias(c) for i, c in enumerate("abc")])


def residual_edges(g: Graph, beta: int, inclusive: bool = True) -> DataFrame:
    """Edges between nodes above the threshold."""
    low = degrees(g).where(F.col("deg") <= beta if inclusive else F.col("deg") < beta).select("id")
    return g.edges.join(low.withColumnRenamed("id", "u"), "u", "left_anti").join(low.withColumnRenamed("id", "v"), "v", "left_anti").select("u", "v")


@dataclass(frozen=True)
class Filtered:
    """What is left to sample, and what is known exactly: (bucket, known)."""

    rest: Graph
    known: DataFrame
    beta: int


def apply_filter(g: Graph, buckets: DataFrame, w: DataFrame, beta: int, inclusive: bool = True) -> Filtered:
    """Degrees, wedges and bucket sizes stay those of the whole graph, so the exact part only shifts the centres."""
    counts = corner_counts(low_degree_triangles(g, beta, inclusive), "n")
    parts = counts.join(w.where("w > 0"), "id").join(buckets.select("id", "bucket"), "id").groupBy("bucket").agg(F.sum(F.col("n") / F.col("w")).alias("part"))
    known = bucket_sizes(buckets).join(parts, "bucket", "left").select("bucket", (F.coalesce("part", F.lit(0.0)) / F.col("size")).alias("known"))
    return Filtered(Graph(g.nodes, residual_edges(g, beta, inclusive)), known, beta)
