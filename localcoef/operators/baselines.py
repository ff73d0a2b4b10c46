"""Competitors: wedge sampling for both coefficients, and stand-ins for the other families, whose details are not given."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from localcoef.functions.concentration import hoeffding_size
from localcoef.model import Graph, bucket_sizes, check_coefficient
from localcoef.operators.estimators import edge_credits
from localcoef.operators.exact import degrees, denominators, edge_triangles, ratio, wedges_headed
from localcoef.operators.sampling import draw_nodes, number_edges, uniform

PARTS = 64


def ranked_adjacency(g: Graph) -> DataFrame:
    """(src, dst, rank): the place of a neighbour from 0, in an order by part; a hub's neighbours are ranked in parts."""
    adj = g.adjacency.withColumn("part", F.pmod("dst", F.lit(PARTS)).cast("int"))
    parts = adj.groupBy("src", "part").agg(F.count("*").alias("n"))
    ahead = F.sum("n").over(Window.partitionBy("src").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    parts = parts.select("src", "part", F.coalesce(ahead, F.lit(0)).alias("before"))
    inner = F.row_number().over(Window.partitionBy("src", "part").orderBy("dst"))
    return adj.withColumn("r", inner).join(parts, ["src", "part"]).select("src", "dst", (F.col("before") + F.col("r") - 1).alias("rank"))


def _pick(seed: int, stream: str, size) -> F.Column:
    return F.least(F.floor(uniform(seed, stream, F.col("bucket"), F.col("ix")) * size).cast("long"), size.cast("long") - 1)


def _closed_share(drawn: DataFrame, hits: DataFrame, buckets: DataFrame) -> DataFrame:
    """(bucket, size, draws, f) from all draws and those whose wedge is closed."""
    found = hits.groupBy("bucket").agg(F.count("*").alias("hits"))
    counts = drawn.groupBy("bucket").agg(F.count("*").alias("draws"))
    return bucket_sizes(buckets).join(counts, "bucket", "left").join(found, "bucket", "left").select("bucket", "size", F.coalesce("draws", F.lit(0)).alias("draws"), (F.coalesce("hits", F.lit(0)) / F.coalesce("draws", F.lit(1))).alias("f"))


def wedge_center(g: Graph, buckets: DataFrame, draws: DataFrame, seed: int = 0) -> DataFrame:
    """Clustering: a random node of the bucket and a random pair of its neighbours; nodes of degree below 2 count as open."""
    drawn = draw_nodes(buckets, draws, seed, "center").join(degrees(g), "id")
    pairs = drawn.where("deg > 1").withColumn("r1", _pick(seed, "first", F.col("deg"))).withColumn("r2", _pick(seed, "second", F.col("deg") - 1))
    pairs = pairs.withColumn("r2", F.col("r2") + (F.col("r2") >= F.col("r1")).cast("int"))
    ranks = ranked_adjacency(g)
    side = lambda r, x: ranks.select(F.col("src").alias("id"), F.col("rank").alias(r), F.col("dst").alias(x))
    ends = pairs.join(side("r1", "x"), ["id", "r1"]).join(side("r2", "y"), ["id", "r2"])
    closed = ends.select("bucket", "ix", F.least("x", "y").alias("u"), F.greatest("x", "y").alias("v")).join(g.edges, ["u", "v"], "left_semi")
    return _closed_share(drawn, closed, buckets)


def wedge_headed(g: Graph, buckets: DataFrame, draws: DataFrame, seed: int = 0) -> DataFrame:
    """Closure: a random node, a neighbour in proportion to its degree less one, and another neighbour of that one."""
    deg, ranks = degrees(g), ranked_adjacency(g)
    drawn = draw_nodes(buckets, draws, seed, "head").join(wedges_headed(g), "id")
    first = drawn.where("wh > 0").withColumn("at", _pick(seed, "hop", F.col("wh")))
    heavy = ranks.join(deg.select(F.col("id").alias("dst"), (F.col("deg") - 1).alias("more")), "dst").withColumn("part", F.pmod("dst", F.lit(PARTS)).cast("int"))
    parts = heavy.groupBy("src", "part").agg(F.sum("more").alias("n"))
    ahead = F.sum("n").over(Window.partitionBy("src").orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    parts = parts.select("src", "part", "n", F.coalesce(ahead, F.lit(0)).alias("before"))
    # a draw meets the parts of its node, and in its part the last step that begins at or before it
    held = first.join(parts.withColumnRenamed("src", "id"), "id").where("at >= before and at < before + n").select("id", "part", (F.col("at") - F.col("before")).alias("pos"), "bucket", "ix")
    began = F.sum("more").over(Window.partitionBy("src", "part").orderBy("dst")) - F.col("more")
    steps = heavy.where("more > 0").select(F.col("src").alias("id"), "part", began.alias("pos"), F.struct(F.col("dst").alias("mid"), "more").alias("step"))
    latest = F.last("step", True).over(Window.partitionBy("id", "part").orderBy("pos", F.col("ix").isNotNull()))
    hop = steps.unionByName(held, True).withColumn("step", latest).where("ix is not null").select("id", "bucket", "ix", "step.mid", "step.more")
    # the other neighbour of the middle: any but the head, by rank
    own = ranks.select(F.col("src").alias("mid"), F.col("dst").alias("id"), F.col("rank").alias("own"))
    hop = hop.join(own, ["mid", "id"]).withColumn("r", _pick(seed, "other", F.col("more")))
    hop = hop.withColumn("r", F.col("r") + (F.col("r") >= F.col("own")).cast("int"))
    ends = hop.join(ranks.select(F.col("src").alias("mid"), F.col("rank").alias("r"), F.col("dst").alias("y")), ["mid", "r"])
    closed = ends.select("bucket", "ix", F.least("id", "y").alias("u"), F.greatest("id", "y").alias("v")).join(g.edges, ["u", "v"], "left_semi")
    return _closed_share(drawn, closed, buckets)


def wedge_baseline(g: Graph, buckets: DataFrame, coefficient: str, eps: DataFrame, k: int, eta: float, seed: int = 0, most: int = 10_000_000) -> DataFrame:
    """Wedge sampling at given half-widths (bucket, eps); ``most`` keeps an unattainable request from running on."""
    check_coefficient(coefficient)
    rows = [(r["bucket"], min(most, hoeffding_size(max(r["eps"], 1e-6), k, eta))) for r in eps.collect()]
    draws = g.nodes.sparkSession.createDataFrame(rows, "bucket int, s long")
    return (wedge_center if coefficient == "clustering" else wedge_headed)(g, buckets, draws, seed)


def node_edge_baseline(g: Graph, buckets: DataFrame, bag: DataFrame, s: int, m: int, q: float = 1 / 3) -> DataFrame:
    """Stand-in: symmetric per-node edge sampling for clustering, averaged by bucket afterwards."""
    t = edge_credits(g, bag, q).groupBy(F.col("node").alias("id")).agg((F.sum("a") * m / s).alias("t"))
    return _node_means(g, buckets, t)


def _node_means(g: Graph, buckets: DataFrame, t: DataFrame) -> DataFrame:
    w = denominators(g, "clustering")
    psi = w.join(t, "id", "left").select("id", ratio(F.coalesce("t", F.lit(0.0)), F.col("w")).alias("psi"))
    return psi.join(buckets.select("id", "bucket"), "id").groupBy("bucket").agg(F.count("*").alias("size"), F.avg("psi").alias("f"))


#: The modulus of the portable hash orders.
PRIME = 2_147_483_647


def hash_order(i: int) -> tuple[int, int]:
    """Multiplier and shift of the i-th order."""
    return (1_103_515_245 * (i + 1) + 12_345) % PRIME, (69_069 * (i + 7) + 1) % PRIME


def sketch_baseline(g: Graph, buckets: DataFrame, hashes: int = 16) -> DataFrame:
    """Stand-in: min-wise signatures of neighbourhoods give each edge's common neighbours, in passes over all edges."""
    minima = [F.min((F.col("dst") * a + b) % PRIME).alias(f"h{i}") for i in range(hashes) for a, b in [hash_order(i)]]
    sig = g.adjacency.groupBy("src").agg(F.count("*").alias("d"), *minima)
    side = lambda end: sig.select(F.col("src").alias(end), F.struct("d", *[f"h{i}" for i in range(hashes)]).alias(f"s{end}"))
    both = g.edges.join(side("u"), "u").join(side("v"), "v")
    agree = sum(((F.col(f"su.h{i}") == F.col(f"sv.h{i}")).cast("int") for i in range(hashes)), F.lit(0)) / hashes
    shared = agree / (1 + agree) * (F.col("su.d") + F.col("sv.d"))
    t = both.select(F.explode(F.array("u", "v")).alias("id"), (shared / 2).alias("x")).groupBy("id").agg(F.sum("x").alias("t"))
    return _node_means(g, buckets, t)


def retained_edge_baseline(g: Graph, buckets: DataFrame, rate: float = 0.25, seed: int = 0) -> DataFrame:
    """Stand-in: edges arrive in order of their numbers and are kept by hash; an arriving edge that closes two kept earlier ones counts 1 / rate^2. Their common corner is looked for from the end with fewer kept edges."""
    arriving = number_edges(g.edges)
    kept = arriving.where(uniform(seed, "keep", F.col("u"), F.col("v")) < rate)
    both = kept.select("eid", F.col("u").alias("a"), F.col("v").alias("b")).unionByName(kept.select("eid", F.col("v").alias("a"), F.col("u").alias("b")))
    deg = both.groupBy("a").agg(F.count("*").alias("n"))
    d = lambda end: deg.select(F.col("a").alias(end), F.col("n").alias(f"n{end}"))
    small = F.col("nu") <= F.col("nv")
    ends = arriving.join(d("u"), "u").join(d("v"), "v").select("eid", "u", "v", F.when(small, F.col("u")).otherwise(F.col("v")).alias("z"), F.when(small, F.col("v")).otherwise(F.col("u")).alias("o"))
    one = both.select(F.col("a").alias("z"), F.col("b").alias("w"), F.col("eid").alias("e1"))
    two = both.select(F.col("a").alias("o"), F.col("b").alias("w"), F.col("eid").alias("e2"))
    closed = ends.join(one, "z").where("e1 < eid").join(two, ["o", "w"]).where("e2 < eid").select("u", "v", "w")
    t = closed.select(F.explode(F.array("u", "v", "w")).alias("id")).groupBy("id").agg((F.count("*") / (rate * rate)).alias("t"))
    return _node_means(g, buckets, t)


def exact_baseline(g: Graph, buckets: DataFrame) -> DataFrame:
    t = edge_triangles(g).select(F.explode(F.array("u", "v")).alias("id"), "n").groupBy("id").agg((F.sum("n") / 2).alias("t"))
    return _node_means(g, buckets, t)


#: What the compared methods cover and cost.
CAPABILITIES = [
    ("adaptive", True, True, True, "R ln(k/eta)/eps to R^2 (zeta + ln(1/eta))/eps^2", "dmax"),
    ("wedge_center", True, False, False, "k ln(k/eta)/eps^2", "1"),
    ("wedge_headed", False, True, False, "k ln(k/eta)/eps^2", "dmax"),
    ("node_edge", True, False, False, "m^2 (ln dmax + ln(1/eta))/eps^2", "dmax"),
    ("sketch", True, False, False, "ln(n/eta)/eps^2", "m ln(1/eps)"),
    ("retained_edge", True, False, False, "r", "m"),
]


def capability_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CAPABILITIES, "method string, clustering boolean, closure boolean, adaptive boolean, draws string, per_draw string")
