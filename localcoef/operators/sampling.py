"""Seeded bags of edges and nodes. The hash draws are md5-based, so another engine can repeat them."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Bags up to this number of draws are broadcast; more are shuffled.
BROADCAST_DRAWS = 2_000_000


def uniform(seed: int, stream: str, *keys: Column) -> Column:
    """A number in [0, 1) of 52 bits, from the hash of seed, stream and keys."""
    return uniform_of(F.lit(seed), stream, *keys)


def uniform_of(seed: Column, stream: str, *keys: Column) -> Column:
    """As ``uniform``, with a seed of each row."""
    text = F.concat_ws(":", seed.cast("string"), F.lit(stream), *[k.cast("string") for k in keys])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long") / F.lit(float(1 << 52))


#: Shards that edges are numbered in, each sorted by a task of its own.
SHARDS = 4096


def number_edges(edges: DataFrame, shards: int = SHARDS) -> DataFrame:
    """(eid, u, v) with ids from 0 without gaps, by shards and a table of their sizes, one row each; no global sort."""
    keyed = edges.select("u", "v", F.pmod(F.col("u") * 31 + F.col("v"), F.lit(shards)).cast("int").alias("shard"))
    sizes = keyed.groupBy("shard").agg(F.count("*").alias("n"))
    ahead = F.sum("n").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("shard", F.coalesce(ahead, F.lit(0)).alias("before"))
    placed = keyed.withColumn("r", F.row_number().over(Window.partitionBy("shard").orderBy("u", "v")))
    return placed.join(F.broadcast(offsets), "shard").select((F.col("before") + F.col("r") - 1).cast("long").alias("eid"), "u", "v")


def draw_indexed(numbered: DataFrame, m: int, s: int, seed: int, stream: str = "main", start: int = 0) -> DataFrame:
    """(ix, u, v): s independent uniform draws with replacement. A draw depends on seed, stream and ix alone, so a longer bag extends a shorter one."""
    if m <= 0 or s <= 0:
        return numbered.select(F.lit(0).cast("long").alias("ix"), "u", "v").limit(0)
    draws = numbered.sparkSession.range(start, start + s).select(F.col("id").alias("ix"))
    draws = draws.withColumn("eid", F.least(F.floor(uniform(seed, stream, F.col("ix")) * m).cast("long"), F.lit(m - 1)))
    return numbered.join(F.broadcast(draws) if s <= BROADCAST_DRAWS else draws, "eid").select("ix", "u", "v")


def draw_poisson(edges: DataFrame, m: int, s: int, seed: int) -> DataFrame:
    """(u, v, copies): one pass, no ids and no shuffle; every edge is drawn a Poisson number of times with mean s / m.

    Given their total the draws are a uniform bag with replacement; the total itself is random, about s.
    """
    rate = s / m
    x, copies, mass, total = uniform(seed, "poisson", F.col("u"), F.col("v")), F.lit(0), math.exp(-rate), math.exp(-rate)
    steps = []
    for k in range(1, max(8, int(rate + 10 * math.sqrt(rate) + 8))):
        steps.append(F.when(x >= total, 1).otherwise(0))
        mass *= rate / k
        total += mass
    copies = sum(steps, F.lit(0))
    return edges.select("u", "v", copies.alias("copies")).where("copies > 0")


def draw_weighted(weighted: DataFrame, s: int, seed: int, stream: str = "weighted", shards: int = 64) -> DataFrame:
    """(ix, u, v, p): draws with probability in proportion to ``weight`` > 0, by inverse sums in two levels.

    The driver holds one sum for each shard; a draw picks its shard there, and then joins the row of that shard whose
    interval of running sums holds it.
    """
    keyed = weighted.where("weight > 0").select("u", "v", "weight", F.pmod(F.col("u") * 31 + F.col("v"), F.lit(shards)).cast("int").alias("shard"))
    sums = sorted((r["shard"], float(r["w"])) for r in keyed.groupBy("shard").agg(F.sum("weight").alias("w")).collect())
    whole = sum(w for _, w in sums)
    if not sums or s <= 0:
        return keyed.select(F.lit(0).cast("long").alias("ix"), "u", "v", F.lit(0.0).alias("p")).limit(0)
    high = F.sum(F.col("weight").cast("double")).over(Window.partitionBy("shard").orderBy("u", "v"))
    rows = keyed.withColumn("high", high).withColumn("low", F.col("high") - F.col("weight"))
    at = uniform(seed, stream, F.col("id")) * whole
    shard, rest, before = F.lit(sums[-1][0]), at - (whole - sums[-1][1]), whole - sums[-1][1]
    for k, w in reversed(sums[:-1]):
        before -= w
        shard, rest = F.when(at < before + w, F.lit(k)).otherwise(shard), F.when(at < before + w, at - before).otherwise(rest)
    draws = weighted.sparkSession.range(s).select(F.col("id").alias("ix"), shard.alias("shard"), rest.alias("rest"))
    # the running sums are cut into cells of equal width, so that the interval test is an equi-join on few cells
    cell = whole / (len(sums) * 256)
    rows = rows.withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") / cell), F.floor(F.col("high") / cell))))
    draws = draws.withColumn("cell", F.floor(F.col("rest") / cell))
    met = rows.join(F.broadcast(draws) if s <= BROADCAST_DRAWS else draws, ["shard", "cell"]).where("rest >= low and rest < high")
    return met.select("ix", "u", "v", (F.col("weight") / whole).alias("p"))


def draw_nodes(buckets: DataFrame, draws: DataFrame, seed: int, stream: str = "nodes") -> DataFrame:
    """(bucket, ix, id): uniform nodes of each bucket with replacement; ``draws`` has (bucket, s), a row for each bucket."""
    ranked = buckets.select("bucket", "id", F.pmod(F.col("id"), F.lit(64)).cast("int").alias("part"))
    # ranks by part of a bucket, then an offset for each part: a large bucket is not sorted in one task
    parts = ranked.groupBy("bucket", "part").agg(F.count("*").alias("n"))
    ahead = F.sum("n").over(Window.partitionBy("bucket").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    parts = parts.select("bucket", "part", F.coalesce(ahead, F.lit(0)).alias("before"), F.sum("n").over(Window.partitionBy("bucket")).alias("size"))
    place = ranked.withColumn("r", F.row_number().over(Window.partitionBy("bucket", "part").orderBy("id"))).join(parts, ["bucket", "part"])
    place = place.select("bucket", "id", (F.col("before") + F.col("r") - 1).alias("rank"))
    sizes = parts.select("bucket", "size").distinct()
    wish = draws.join(sizes, "bucket").select("bucket", "size", F.explode(F.sequence(F.lit(0).cast("long"), F.col("s").cast("long") - 1)).alias("ix"))
    wish = wish.select("bucket", "ix", F.least(F.floor(uniform(seed, stream, F.col("bucket"), F.col("ix")) * F.col("size")).cast("long"), F.col("size") - 1).alias("rank"))
    return place.join(wish, ["bucket", "rank"]).select("bucket", "ix", "id")
