"""Node partitions: every function gives (id, bucket, label) with buckets numbered from 0 without gaps."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from localcoef.model import Graph
from localcoef.operators.exact import degrees


def numbered(labelled: DataFrame) -> DataFrame:
    """From (id, label): buckets by order of label. Up to 100,000 labels are sorted in one task and broadcast; more are numbered by ranges."""
    labels = labelled.select(F.col("label").alias("named")).distinct()
    few = _few(labels)
    labels = labels.withColumn("bucket", (F.row_number().over(Window.orderBy("named")) - 1).cast("int")) if few else _numbered_by_ranges(labels)
    return labelled.join(F.broadcast(labels) if few else labels, F.col("label").eqNullSafe(F.col("named"))).select("id", "bucket", F.col("label").cast("string").alias("label"))


def _numbered_by_ranges(labels: DataFrame) -> DataFrame:
    """(named, bucket) from (named): ranges of labels, written so that they stay as they are, each numbered on from the sizes of those before."""
    from localcoef.plans.store import written

    ranges = written(labels.repartitionByRange("named").withColumn("range", F.spark_partition_id()), "labels")
    ahead = F.sum("n").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1))
    offsets = ranges.groupBy("range").agg(F.count("*").alias("n")).select("range", F.coalesce(ahead, F.lit(0)).alias("before"))
    place = F.row_number().over(Window.partitionBy("range").orderBy("named")) - 1
    return ranges.withColumn("place", place).join(F.broadcast(offsets), "range").select("named", (F.col("before") + F.col("place")).cast("int").alias("bucket"))


def _few(labels: DataFrame, bound: int = 100_000) -> bool:
    return labels.limit(bound + 1).count() <= bound


def single_bucket(g: Graph) -> DataFrame:
    return g.nodes.select("id", F.lit(0).alias("bucket"), F.lit("all").alias("label"))


def singleton_buckets(g: Graph) -> DataFrame:
    """Every node alone. Numbers are dense ranks of the ids, by shards of ids and their sizes."""
    return dense_numbers(g.nodes, "id", "bucket").select("id", F.col("bucket").cast("int"), F.col("id").cast("string").alias("label"))


def dense_numbers(rows: DataFrame, by: str, name: str, shards: int = 64) -> DataFrame:
    """Numbers from 0 in an order by shard of ``by``; no sort of the whole: the driver holds one count for each shard."""
    keyed = rows.withColumn("shard", F.pmod(F.col(by), F.lit(shards)).cast("int"))
    counts = {r["shard"]: r["n"] for r in keyed.groupBy("shard").agg(F.count("*").alias("n")).collect()}
    before, offsets = 0, []
    for s in range(shards):
        offsets.append(before)
        before += counts.get(s, 0)
    offset = F.element_at(F.array(*[F.lit(o) for o in offsets]), F.col("shard") + 1)
    return keyed.withColumn(name, (offset + F.row_number().over(Window.partitionBy("shard").orderBy(by)) - 1).cast("long")).drop("shard")


def metadata_buckets(g: Graph, rows: DataFrame, id_col: str, label_col: str) -> DataFrame:
    """By a label of the nodes; nodes without one are in the bucket ``none``."""
    known = rows.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("string").alias("label"))
    return numbered(g.nodes.join(known, "id", "left").select("id", F.coalesce("label", F.lit("none")).alias("label")))


def majority_buckets(g: Graph, activity: DataFrame, id_col: str, class_col: str) -> DataFrame:
    """By the class that occurs most often with a node; ties go to the first class by name."""
    counts = activity.where(F.col(class_col).isNotNull()).groupBy(F.col(id_col).cast("long").alias("id"), F.col(class_col).cast("string").alias("label")).agg(F.count("*").alias("n"))
    top = counts.groupBy("id").agg(F.min(F.struct(-F.col("n"), "label"))["label"].alias("label"))
    return metadata_buckets(g, top, "id", "label")


def degree_buckets(g: Graph, k: int = 25, mode: str = "depth") -> DataFrame:
    """Nodes of similar degree: about k groups of equal size, equal degrees together; or k ranges of equal width.

    Sizes are read off the degree histogram, so no sort of the nodes is needed.
    """
    return grouped_values(degrees(g).withColumnRenamed("deg", "value"), k, mode)


def grouped_values(values: DataFrame, k: int, mode: str = "depth") -> DataFrame:
    """(id, value) into about k buckets of similar value."""
    histogram = values.groupBy("value").agg(F.count("*").alias("n"))
    if mode == "depth":
        before = F.sum("n").over(Window.orderBy("value").rowsBetween(Window.unboundedPreceding, -1))
        total = F.sum("n").over(Window.partitionBy())
        group = F.floor(k * F.coalesce(before, F.lit(0)) / total)
    elif mode == "width":
        high = F.max("value").over(Window.partitionBy())
        low = F.min("value").over(Window.partitionBy())
        group = F.least(F.lit(k - 1), F.floor(k * (F.col("value") - low) / (high - low + 1)))
    else:
        raise ValueError(f"unknown mode {mode!r}")
    groups = histogram.withColumn("g", group.cast("long")).select("value", F.col("g"))
    labelled = values.join(groups, "value").select("id", F.lpad(F.col("g").cast("string"), 6, "0").alias("label"))
    return numbered(labelled)


def log_degree_buckets(g: Graph, base: float | None = None) -> DataFrame:
    """floor(log(1 + (d - 2) / log 2)) + 2; degrees 0 and 1 have the first bucket."""
    import math

    scale = 1.0 if base is None else math.log(base)
    group = F.when(F.col("deg") <= 1, F.lit(1)).otherwise(F.floor(F.ln(1 + (F.col("deg") - 2) / F.lit(math.log(2) / scale)) / scale).cast("int") + 2)
    return numbered(degrees(g).select("id", F.lpad(group.cast("string"), 4, "0").alias("label")))


def random_buckets(g: Graph, k: int = 30, seed: int = 0) -> DataFrame:
    """By a hash of the id that DuckDB computes alike."""
    code = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("long")
    return numbered(g.nodes.select("id", F.lpad((code % k).cast("string"), 6, "0").alias("label")))


def core_numbers(g: Graph, rounds: int | None = None) -> DataFrame:
    """(id, core): the largest h such that the node is in a subgraph of least degree h, by repeated h-indices.

    A node's neighbours' values are counted from above by a window over (node, value); every round is written to the
    shared folder; a node's value only falls, and the rounds end when none does. More than ``rounds``, if given, are an error.
    """
    from localcoef.plans.store import written

    adj = written(g.adjacency, "adjacency")
    now = written(degrees(g).withColumnRenamed("deg", "core"), "cores")
    for n in count():
        if n == rounds:
            raise RuntimeError(f"core numbers have not settled in {rounds} rounds")
        seen = adj.join(now.withColumnRenamed("id", "dst"), "dst").groupBy("src", "core").agg(F.count("*").alias("n"))
        above = F.sum("n").over(Window.partitionBy("src").orderBy(F.desc("core")))
        index = seen.withColumn("h", F.least("core", above)).groupBy("src").agg(F.max("h").alias("h"))
        new = written(now.join(index.withColumnRenamed("src", "id"), "id", "left").select("id", F.least("core", F.coalesce("h", F.lit(0))).alias("core"), (F.col("core") > F.coalesce("h", F.lit(0))).alias("fell")), "cores")
        fell = new.where("fell").limit(1).count()
        now = new.select("id", "core")
        if not fell:
            break
    return now


def core_buckets(g: Graph, k: int = 30, mode: str = "depth") -> DataFrame:
    return grouped_values(core_numbers(g).withColumnRenamed("core", "value"), k, mode)


def cluster_buckets(g: Graph, k: int = 10, rounds: int = 8, slack: float = 1.3) -> DataFrame:
    """A stand-in for an external partitioner: label propagation from k seeds by hash, with a cap on a label's size.

    In each round a node takes its neighbours' most frequent label if that label is under its cap.
    """
    from localcoef.plans.store import written

    adj = written(g.adjacency, "adjacency")
    total = g.nodes.count()
    now = written(random_buckets(g, k, 1).select("id", "bucket"), "labels")
    for _ in range(rounds):
        votes = adj.join(now.withColumnRenamed("id", "dst"), "dst").groupBy("src", "bucket").agg(F.count("*").alias("n"))
        wish = votes.groupBy(F.col("src").alias("id")).agg(F.min(F.struct(-F.col("n"), "bucket"))["bucket"].alias("want"))
        sizes = now.groupBy("bucket").agg(F.count("*").alias("size"))
        room = F.broadcast(sizes.select(F.col("bucket").alias("want"), (F.col("size") < slack * total / k).alias("open")))
        now = written(now.join(wish, "id", "left").join(room, "want", "left").select("id", F.when(F.col("open"), F.col("want")).otherwise(F.col("bucket")).alias("bucket")), "labels")
    return numbered(now.select("id", F.lpad(F.col("bucket").cast("string"), 6, "0").alias("label")))
