"""Graphs built from the given tables, from edge lists, and by hand."""

from __future__ import annotations

import math
from collections.abc import Iterator
from typing import TYPE_CHECKING

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcoef.model import Graph, canonical
from localcoef.operators import bits

if TYPE_CHECKING:
    import pyarrow as pa


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_list(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> Graph:
    """An edge list of two columns in any of Spark's file formats; text files hold two numbers to a line."""
    if fmt == "text":
        parts = F.split(F.trim("value"), r"[\s,]+")
        rows = spark.read.text(path).where(~F.col("value").startswith("#")).select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    else:
        raw = spark.read.format(fmt).options(**options).load(path)
        rows = raw.toDF("u", "v", *raw.columns[2:]).select(F.col("u").cast("long"), F.col("v").cast("long"))
    return Graph.of(canonical(rows))


def of_pairs(spark: SparkSession, pairs: list[tuple[int, int]], nodes: list[int] | None = None) -> Graph:
    edges = canonical(spark.createDataFrame(pairs, "u long, v long"))
    return Graph.of(edges, spark.createDataFrame([(i,) for i in nodes], "id long") if nodes is not None else None)


def shared_group_graph(rows: DataFrame, group: str, member: str) -> Graph:
    """Two members are joined if they share a group. Groups are small by nature (lines of an order), which bounds the pairs.

    Rows are dealt out by group once, for the distinct members and for the join; packed lists are made of the rows themselves.
    """
    every = rows.select(F.col(group).alias("g"), F.col(member).cast("long").alias("i")).where("g is not null and i is not null")
    rows = every.repartition("g").distinct()
    a, b = rows.withColumnRenamed("i", "u"), rows.withColumnRenamed("i", "v")
    pairs = a.join(b, "g").where("u < v").select("u", "v")
    groups = every if dict(every.dtypes)["g"] in ("bigint", "int", "smallint", "tinyint") else None
    return Graph.of(pairs.distinct(), pairs=pairs, groups=groups, bits=groups and (lambda: bits.of_groups(groups)))


def copart(spark: SparkSession, sf_dir: str) -> Graph:
    """Parts that share an order."""
    return shared_group_graph(read(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey")


def year_lines(spark: SparkSession, sf_dir: str, first: int, last: int | None = None) -> DataFrame:
    """Lines of the orders from one year up to another; the dates are a range, so the scan skips what lies outside."""
    low, high = (F.lit(f"{y}-01-01 00:00:00").cast("timestamp") for y in (first, (last or first) + 1))
    orders = read(spark, sf_dir, "orders").where((F.col("o_orderdate") >= low) & (F.col("o_orderdate") < high)).select("o_orderkey")
    return read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")


def copart_year(spark: SparkSession, sf_dir: str, first: int = 1996, last: int | None = None) -> Graph:
    """Parts that share an order of a year, or of several."""
    return shared_group_graph(year_lines(spark, sf_dir, first, last), "l_orderkey", "l_partkey")


def tripartite(spark: SparkSession, sf_dir: str) -> Graph:
    """Each line joins its customer, part and supplier; ids are 3 * key + {0, 1, 2}."""
    lines, orders = read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders")
    c, p, s = F.col("o_custkey") * 3, F.col("l_partkey") * 3 + 1, F.col("l_suppkey") * 3 + 2
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.inline(F.array(*[F.struct(a.alias("u"), b.alias("v")) for a, b in ((c, p), (p, s), (c, s))])))
    return Graph.of(canonical(rows))


def active_together(spark: SparkSession, sf_dir: str, minutes: int = 10) -> Graph:
    """Users with an event in the same slot of so many minutes."""
    return shared_group_graph(in_slots(read(spark, sf_dir, "events"), minutes), "slot", "user_id")


def in_slots(events: DataFrame, minutes: int = 10) -> DataFrame:
    """(slot, user_id) of events."""
    return events.select(F.floor(F.unix_timestamp("ts") / (60 * minutes)).alias("slot"), "user_id")


def within_interval(spark: SparkSession, sf_dir: str, seconds: int = 60) -> Graph:
    """Users with events at most so many seconds apart: a range join by slots of that length and their neighbours."""
    at = read(spark, sf_dir, "events").select(F.unix_timestamp("ts").alias("t"), "user_id").withColumn("slot", F.floor(F.col("t") / seconds))
    left = at.select(F.col("t").alias("ta"), F.col("user_id").alias("u"), F.explode(F.array(F.col("slot") - 1, F.col("slot"), F.col("slot") + 1)).alias("slot"))
    right = at.select(F.col("t").alias("tb"), F.col("user_id").alias("v"), "slot")
    return Graph.of(canonical(left.join(right, "slot").where((F.abs(F.col("ta") - F.col("tb")) <= seconds) & (F.col("u") < F.col("v")))))


def similar_vectors(spark: SparkSession, sf_dir: str, threshold: float = 0.2, planes: int = 0, tables: int = 16) -> Graph:
    """Vectors whose cosine exceeds a threshold.

    Without planes the vectors are compared block by block, exactly, in blocks of about 10,000. With planes, only vectors that fall on the same
    side of that many random planes in one of ``tables`` tables are compared, which scales and may miss edges.
    """
    rows = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, y: s + y * y))
    rows = rows.withColumn("norm", norm).where("norm > 0")
    cosine = F.aggregate(F.zip_with("a.x", "b.x", lambda p, q: p * q), F.lit(0.0), lambda s, y: s + y) / (F.col("a.norm") * F.col("b.norm"))
    if planes:
        import numpy as np

        size = len(rows.select("x").first()["x"])
        normal = np.random.default_rng(5).standard_normal((tables, planes, size))
        sign = lambda t, p: F.when(F.aggregate(F.zip_with("x", F.array(*[F.lit(float(c)) for c in normal[t, p]]), lambda y, w: y * w), F.lit(0.0), lambda s, y: s + y) > 0, 1 << p).otherwise(0)
        keys = [F.struct(F.lit(t).alias("t"), sum((sign(t, p) for p in range(planes)), F.lit(0)).alias("k")) for t in range(tables)]
        keyed = rows.withColumn("key", F.explode(F.array(*keys)))
        joined = keyed.alias("a").join(keyed.alias("b"), (F.col("a.key") == F.col("b.key")) & (F.col("a.id") < F.col("b.id")))
    else:
        blocks = max(4, math.ceil(rows.count() / 10_000))
        own, all_of = F.pmod(F.col("id"), F.lit(blocks)).cast("int"), F.sequence(F.lit(0), F.lit(blocks - 1))
        dealt = rows.select("id", "x", own.alias("own"), F.explode(all_of).alias("other"))
        cell = F.least("own", "other") * blocks + F.greatest("own", "other")
        dealt = dealt.select(cell.alias("cell"), (F.col("own") > F.col("other")).cast("int").alias("side"), F.col("id").cast("long").alias("id"), "x")
        pairs = dealt.repartitionById(blocks * blocks, "cell").sortWithinPartitions("cell", "side").mapInArrow(_above(threshold, blocks), "u long, v long")
        return Graph.of(pairs.distinct(), pairs=pairs, bits=lambda: bits.of_vectors(rows.select("id", "x"), threshold))
    return Graph.of(joined.where(cosine > threshold).select(F.col("a.id").alias("u"), F.col("b.id").alias("v")).distinct())


def _above(threshold: float, blocks: int, slab: int = 256):
    """Pairs of two blocks of vectors, (cell, side, id, x) in order of cell and side, with a larger cosine."""
    import numpy as np
    import pyarrow as pa

    def pairs(cell: int, held: dict[int, list]) -> Iterator[pa.RecordBatch]:
        same = cell // blocks == cell % blocks
        for dim in {x.shape[1] for _, x in held[0]}:  # vectors of other lengths have no cosine
            (ids, a), (others, b) = (tuple(np.concatenate([y[i] for y in held[side] if y[1].shape[1] == dim] or [np.empty((0, dim)[: i + 1])]) for i in (0, 1)) for side in (0, 0 if same else 1))
            norms = [np.sqrt(np.cumsum(x * x, axis=1)[:, -1]) for x in (a, b)]
            for at in range(0, len(a) if len(b) else 0, slab):
                scale = norms[0][at : at + slab, None] * norms[1][None, :]
                cosine = a[at : at + slab] @ b.T / scale
                i, j = np.nonzero(np.abs(cosine - threshold) < 1e-9)  # summed in order where the last bits decide
                cosine[i, j] = np.cumsum(a[at + i] * b[j], axis=1)[:, -1] / scale[i, j] if len(i) else 0
                i, j = np.nonzero(~(cosine <= threshold))  # not a number counts as larger, as in SQL
                p, q = ids[at + i].astype(np.int64), others[j].astype(np.int64)
                keep = p < q if same else p != q
                p, q = p[keep], q[keep]
                for k in range(0, len(p), 100_000):
                    yield pa.RecordBatch.from_arrays([pa.array(f(p[k : k + 100_000], q[k : k + 100_000])) for f in (np.minimum, np.maximum)], names=["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, {0: [], 1: []}
        for batch in batches:
            cells, sides = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
            ids, x = batch.column(2).to_numpy(zero_copy_only=False), batch.column(3)
            sizes, values = np.diff(x.offsets.to_numpy()), x.flatten().to_numpy(zero_copy_only=False)
            cut = np.flatnonzero(np.diff(cells) | np.diff(sides) | np.diff(sizes)) + 1
            ends = np.r_[0, np.cumsum(sizes)]
            for a, b in zip(np.r_[0, cut], np.r_[cut, len(cells)], strict=True):
                if cells[a] != now:
                    if now is not None:
                        yield from pairs(now, held)
                    now, held = int(cells[a]), {0: [], 1: []}
                held[int(sides[a])].append((ids[a:b].copy(), values[ends[a] : ends[b]].reshape(b - a, sizes[a]).copy()))
        if now is not None:
            yield from pairs(now, held)

    return run


def _page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    links = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))))
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]*)", 1).alias("host"), links.alias("link"))


def text_id(text) -> F.Column:
    """A 48-bit number of a text that DuckDB computes alike."""
    return F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long")


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Pages, their hosts and their link targets, pairwise joined; ids are 3 * number + {0, 1, 2}."""
    rows = _page_links(spark, sf_dir)
    page, host, link = F.col("page_id") * 3, text_id("host") * 3 + 1, text_id("link") * 3 + 2
    return Graph.of(canonical(rows.select(F.inline(F.array(*[F.struct(a.alias("u"), b.alias("v")) for a, b in ((page, host), (host, link), (page, link))])))))


def pages_sharing_links(spark: SparkSession, sf_dir: str, at_most: int = 20) -> Graph:
    """Pages that share a link which few pages have."""
    rows = _page_links(spark, sf_dir).select("page_id", "link")
    rare = rows.groupBy("link").agg(F.count("*").alias("n")).where(F.col("n") <= at_most).select("link")
    return shared_group_graph(rows.join(rare, "link"), "link", "page_id")


def similar_documents(spark: SparkSession, sf_dir: str, shingle: int = 3, bands: int = 16, rows_in_band: int = 2) -> Graph:
    """Documents that share a band of min-hashes of their word shingles; a band's hub is its least document, so a large band is a star of edges."""
    words = F.filter(F.split("text", r"[\x20\x09-\x0D]+"), lambda x: x != "")
    grams = F.transform(F.sequence(F.lit(0), F.size("w") - shingle), lambda i: F.xxhash64(F.array_join(F.slice("w", i + 1, F.lit(shingle)), " ")))
    base = read(spark, sf_dir, "documents").select("doc_id", words.alias("w")).where(F.size("w") >= shingle).select("doc_id", grams.alias("g"))
    keys = [F.struct(F.lit(b).alias("b"), F.xxhash64(*[F.array_min(F.transform("g", lambda x, s=b * rows_in_band + r: F.xxhash64(x, F.lit(s)))) for r in range(rows_in_band)]).alias("k")) for b in range(bands)]
    keyed = base.select("doc_id", F.explode(F.array(*keys)).alias("key"))
    hubs = keyed.groupBy("key").agg(F.min("doc_id").alias("u"), F.count("*").alias("n")).where("n > 1").withColumn("x", F.hash("key"))
    return Graph.of(canonical(keyed.withColumn("x", F.hash("key")).join(hubs, ["key", "x"]).select("u", F.col("doc_id").alias("v"))))


def conversations_sharing_words(spark: SparkSession, sf_dir: str, low: int = 2, high: int = 4) -> Graph:
    """Conversations that share a word which few conversations have."""
    words = read(spark, sf_dir, "conversations").select("conv_id", F.explode(F.split(F.lower("text"), r"[\x20\x09-\x0D]+")).alias("word")).where("word <> ''").distinct()
    rare = words.groupBy("word").agg(F.count("*").alias("n")).where(F.col("n").between(low, high)).select("word")
    return shared_group_graph(words.join(rare, "word"), "word", "conv_id")


def suppliers_sharing_orders(spark: SparkSession, sf_dir: str) -> Graph:
    return shared_group_graph(read(spark, sf_dir, "lineitem"), "l_orderkey", "l_suppkey")


#: The hand graph of the worked examples; nodes a..f are 0..5.
TOY_EDGES, TOY_NODES, TOY_BUCKETS = [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3), (3, 4)], [0, 1, 2, 3, 4, 5], [(0, 0), (1, 0), (2, 1), (3, 1), (4, 2), (5, 2)]


def toy(spark: SparkSession) -> Graph:
    return of_pairs(spark, TOY_EDGES, TOY_NODES)


def star(spark: SparkSession, n: int = 10, chord: bool = True) -> Graph:
    """A hub 0 with leaves 1..n-1, and one edge between two leaves."""
    return of_pairs(spark, [(0, i) for i in range(1, n)] + ([(1, 2)] if chord else []))


GRAPHS = {
    "cp": copart, "cpy": copart_year, "tr": tripartite, "ev": active_together, "em": similar_vectors, "pg": page_links,
    "dc": similar_documents, "cv": conversations_sharing_words, "ge": suppliers_sharing_orders,
}
