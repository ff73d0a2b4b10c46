"""Edge streams from event files: windows, joins, duplicates, retained-edge estimates and incremental refresh."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from uuid import uuid4

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from localcoef.model import Graph, bucket_sizes, canonical
from localcoef.operators.estimators import bag_triangles, bucket_means, bucket_weights, edge_shares, edge_values
from localcoef.operators.exact import listed_edges
from localcoef.operators.sampling import draw_poisson
from localcoef.plans.estimate import fixed_size_estimate
from localcoef.plans.store import drop_on_exit, shared_path, written
from localcoef.sources.graphs import in_slots, shared_group_graph


def event_stream(spark: SparkSession, sf_dir: str, files: int = 1, delay: str = "1 hour") -> DataFrame:
    """The events as a stream with a watermark; the pattern takes a single Parquet file or a folder of them."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    events = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{sf_dir}/events.parquet*")
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def window_counts(events: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(start, event_type, n) in tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n) of sessions without a longer pause."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def co_activity_join(events: DataFrame, minutes: int = 10) -> DataFrame:
    """(ts, u, v): users with an event in the same slot, by a stream-stream join with an interval bound, for streams without an end.

    One row for each pair of events; those later than the watermark are left out, so files must come in order of time.
    """
    slot = F.floor(F.unix_timestamp("ts") / (60 * minutes))
    a = events.select(F.col("ts").alias("ta"), F.col("user_id").alias("u"), slot.alias("sa"))
    b = events.select(F.col("ts").alias("tb"), F.col("user_id").alias("v"), slot.alias("sb"))
    bound = F.expr(f"tb BETWEEN ta - INTERVAL {minutes} MINUTES AND ta + INTERVAL {minutes} MINUTES")
    return a.join(b, (F.col("sa") == F.col("sb")) & bound & (F.col("u") < F.col("v"))).select(F.greatest("ta", "tb").alias("ts"), "u", "v")


def co_activity(events: DataFrame, minutes: int = 10) -> DataFrame:
    """(u, v): users with an event in the same slot of a bounded stream, each pair once.

    The stream puts the slots of its users into files, without a state, so that no event is too late; pairs are made of the
    whole slots when it has ended, and none is a row of a state or a shuffle.
    """
    return listed_edges(shared_group_graph(run_to_files(in_slots(events, minutes)), "slot", "user_id"))


def distinct_events(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def with_buckets(edges: DataFrame, buckets: DataFrame) -> DataFrame:
    """Stream edges with the buckets of their ends, from a static table."""
    at = lambda x: buckets.select(F.col("id").alias(x), F.col("bucket").alias(f"b{x}"))
    return edges.join(at("u"), "u").join(at("v"), "v")


def run_to_memory(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a bounded stream to its end and gives what it put out."""
    name = f"out_{uuid4().hex}"
    q = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", shared_path(stream.sparkSession, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def run_to_files(stream: DataFrame) -> DataFrame:
    """Runs a bounded stream of appended rows to its end and gives what it put out, from files in the shared folder; no row goes to the driver."""
    spark, path = stream.sparkSession, shared_path(stream.sparkSession, "put")
    q = stream.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", shared_path(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    drop_on_exit(spark, path)
    return spark.read.schema(stream.schema).parquet(path)


class RetainedTriangles(StatefulProcessor):
    """For each triple of colours, keeps arriving edges by hash and counts how often an arriving edge closes two kept ones.

    A triangle is counted in the triple of its corners' colours alone, so all triples together count each once. The kept
    neighbours of a node are held by their colour.
    """

    def __init__(self, rate: float, seed: int):
        self.rate, self.seed = rate, seed

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getMapState("kept", "node long, colour int", "near array<long>")
        self.found = handle.getValueState("found", "n double")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        total = self.found.get()[0] if self.found.exists() else 0.0
        near = lambda x, c: set(self.kept.getValue((x, c))[0]) if self.kept.containsKey((x, c)) else set()
        for frame in rows:
            for u, v, cu, cv in frame.sort_values(["ts", "u", "v"])[["u", "v", "cu", "cv"]].itertuples(index=False):
                u, v, cu, cv = int(u), int(v), int(cu), int(cv)
                of_u, of_v = near(u, cv), near(v, cu)
                if v in of_u:
                    continue
                third = [int(c) for c in key]
                third.remove(cu)
                third.remove(cv)
                total += len(near(u, third[0]) & near(v, third[0])) / self.rate**2
                if int(hashlib.md5(f"{self.seed}:{u}:{v}".encode()).hexdigest()[:8], 16) / 2**32 < self.rate:
                    self.kept.updateValue((u, cv), (sorted(of_u | {v}),))
                    self.kept.updateValue((v, cu), (sorted(near(v, cu) | {u}),))
        self.found.update((total,))
        yield pd.DataFrame({"a": [int(key[0])], "b": [int(key[1])], "c": [int(key[2])], "triangles": [total]})

    def close(self) -> None:
        pass


def retained_triangles(edges: DataFrame, rate: float = 1.0, colours: int = 4, seed: int = 0) -> DataFrame:
    """(a, b, c, triangles) of the triangles whose corners have these colours, updated batch by batch; the sum over all
    triples is the whole count. Each edge goes to as many triples as there are colours."""
    colour = lambda c: F.pmod(F.xxhash64(c), F.lit(colours)).cast("int")
    met = edges.withColumns({"cu": colour("u"), "cv": colour("v")}).withColumn("cw", F.explode(F.sequence(F.lit(0), F.lit(colours - 1))))
    triple = F.array_sort(F.array("cu", "cv", "cw"))
    met = met.withColumns({n: triple[i] for i, n in enumerate("abc")})
    return met.groupBy("a", "b", "c").transformWithStateInPandas(RetainedTriangles(rate, seed), "a int, b int, c int, triangles double", "update", "none")


def refresh(edges: DataFrame, buckets: DataFrame, coefficient: str, path: str, done: Callable[[DataFrame, int], None], fraction: float = 0.2, seed: int = 0):
    """A sink for foreachBatch: adds a batch's new edges to a table and estimates again from all of it."""

    def batch(df: DataFrame, number: int) -> None:
        spark = df.sparkSession
        canonical(df).write.mode("append").parquet(path)
        g = Graph.of(spark.read.parquet(path).distinct(), buckets)
        done(fixed_size_estimate(g, buckets, coefficient, fraction=fraction, q=1 / 3, seed=seed), number)

    return edges.writeStream.foreachBatch(batch)


def streamed_estimate(edges: DataFrame, buckets: DataFrame, coefficient: str, fraction: float = 0.2, seed: int = 0) -> DataFrame:
    """Runs ``refresh`` over a bounded edge stream to its end and gives the last estimate."""
    spark, last = buckets.sparkSession, []
    q = refresh(edges, buckets, coefficient, shared_path(spark, "edges"), lambda df, _: last.append(written(df, "refreshed")), fraction, seed)
    q.option("checkpointLocation", shared_path(spark, "stream")).trigger(availableNow=True).start().awaitTermination()
    return last[-1]


def streamed_passes(edges: Callable[[], DataFrame], buckets: DataFrame, coefficient: str, s: int, q: float = 1 / 3, seed: int = 0) -> DataFrame:
    """(bucket, size, f) from passes over an edge stream that is read anew each time and never held whole: degrees, then
    a one-pass bag, then the edges around the drawn ones, each run to its end."""
    spark = buckets.sparkSession
    both = edges().select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count("*").alias("deg"))
    deg = written(buckets.select("id").join(run_to_memory(both, "complete"), "id", "left").fillna(0), "deg")
    m = (deg.agg(F.sum("deg").alias("n")).first()["n"] or 0) // 2
    if not m:
        return bucket_sizes(buckets).withColumn("f", F.lit(0.0))
    bag = written(run_to_memory(draw_poisson(edges(), m, s, seed)), "bag")
    n = bag.agg(F.coalesce(F.sum("copies"), F.lit(0)).alias("n")).first()["n"]
    touched = bag.select(F.explode(F.array("u", "v")).alias("id")).distinct()
    ends = edges().select("u", "v", F.inline(F.array(F.struct(F.col("u").alias("id")), F.struct(F.col("v").alias("id")))))
    around = written(run_to_memory(ends.join(touched, "id", "left_semi").select("u", "v")).distinct(), "around")
    if coefficient == "closure":  # the headed wedges need the degrees at the other ends, one more pass
        at = lambda x, y: F.struct(F.col(x).alias("id"), F.col(y).alias("other"))
        far = edges().select(F.inline(F.array(at("u", "v"), at("v", "u")))).join(deg.select(F.col("id").alias("other"), F.col("deg").alias("d")), "other")
        sums = run_to_memory(far.groupBy("id").agg(F.sum(F.col("d") - 1).alias("wh")), "complete")
        w = deg.join(sums, "id", "left").select("id", (F.coalesce("wh", F.lit(0)) / 2).alias("w"))
    else:
        w = deg.select("id", (F.col("deg") * (F.col("deg") - 1) / 2).alias("w"))
    values = edge_values(edge_shares(bag_triangles(Graph.of(around, buckets), bag), q), bucket_weights(buckets, written(w, "wedges")), m)
    weighted = bag.join(values, ["u", "v"]).select("bucket", (F.col("x") * F.col("copies")).alias("x"))
    return bucket_means(weighted, buckets, max(1, n))
