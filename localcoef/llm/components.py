"""Connected components of a link table, by alternating star contractions on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.llm.store import discard, written


def _least(sym: DataFrame) -> DataFrame:
    """Each edge (u, v) with ``m``, the least neighbour of u; both sides are shuffled anew, so a hub can be split."""
    least = sym.groupBy("u").agg(F.min("v").alias("m")).withColumn("x", F.hash("u"))
    return sym.withColumn("x", F.hash("u")).join(least, ["u", "x"]).select("u", "v", "m")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _least(both).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    met = _least(edges)
    return met.select("u", F.col("m").alias("v")).unionByName(met.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))).distinct()


def components(links: DataFrame) -> DataFrame:
    """From links (u, v) between different ids: (id, component) of every linked id, the component by its least id.

    The links shrink to stars around the least ids; each round is written to the shared folder and compared to the
    one before by a count and a sum of hashes.
    """
    spark = links.sparkSession
    edges = written(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), "links")
    seen = None
    while True:
        mark = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            return edges.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(
                edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct()
            )
        seen = mark
        last = edges
        edges = written(_small_star(_large_star(edges)), "links")
        discard(spark, last)
