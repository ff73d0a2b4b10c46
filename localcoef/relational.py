"""The surrounding relational operators as queries: scans, joins, aggregates, windows, sets, scalars, SQL, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from localcoef.functions.udfs import register_all
from localcoef.operators import exact
from localcoef.oracles import graph, with_buckets
from localcoef.plans import experiments as X
from localcoef.plans.store import shared_path, written
from localcoef.queries import cpy, query, r6
from localcoef.sources import partitions as P
from localcoef.sources.edge_source import register
from localcoef.sources.graphs import read, read_edge_list, within_interval
from localcoef.streaming import edges as S

CPY = graph("cpy")


def _edges_file(s: SparkSession, d: str, fmt: str, **options) -> str:
    path = shared_path(s, "edges")
    cpy(s, d).edges.write.format(fmt).options(**options).save(path)
    return path


for _fmt, _opt in (("parquet", {}), ("csv", {}), ("json", {}), ("orc", {})):
    query(f"op_scan_{_fmt}", CPY + " SELECT u, v FROM edges")(lambda s, d, f=_fmt, o=_opt: read_edge_list(s, _edges_file(s, d, f, **o), f, **o).edges)


@query("op_scan_text", CPY + " SELECT u, v FROM edges")
def _text(s: SparkSession, d: str) -> DataFrame:
    path = shared_path(s, "text")
    cpy(s, d).edges.select(F.concat_ws(" ", "u", "v")).write.text(path)
    return read_edge_list(s, path, "text").edges


@query("op_scan_data_source", CPY + " SELECT u, v FROM edges")
def _source(s: SparkSession, d: str) -> DataFrame:
    register(s)
    path = shared_path(s, "source")
    cpy(s, d).edges.select(F.concat_ws(" ", "u", "v")).write.text(path)
    return s.read.format("edge_list").load(f"{path.removeprefix('file:')}/*.txt").distinct()


@query("op_sink_partitioned", CPY + " SELECT u % 4 AS part, count(*) AS n FROM edges GROUP BY part")
def _partitioned(s: SparkSession, d: str) -> DataFrame:
    path = shared_path(s, "partitioned")
    cpy(s, d).edges.withColumn("part", F.col("u") % 4).write.partitionBy("part").parquet(path)
    return s.read.parquet(path).groupBy(F.col("part").cast("long").alias("part")).agg(F.count("*").alias("n"))


query("op_join_semi", CPY + " SELECT u, v FROM edges WHERE u IN (SELECT p_partkey FROM part WHERE p_size < 10)")(lambda s, d: cpy(s, d).edges.join(read(s, d, "part").where("p_size < 10"), F.col("u") == F.col("p_partkey"), "left_semi"))
query("op_join_anti", CPY + " SELECT p_partkey AS id FROM part WHERE p_partkey NOT IN (SELECT id FROM nodes)")(lambda s, d: read(s, d, "part").select(F.col("p_partkey").alias("id")).join(cpy(s, d).nodes, "id", "left_anti"))
query("op_join_left", CPY + " SELECT p_partkey AS id, coalesce(d, 0) AS deg FROM part LEFT JOIN deg ON id = p_partkey")(lambda s, d: read(s, d, "part").select(F.col("p_partkey").alias("id")).join(exact.degrees(cpy(s, d)), "id", "left").select("id", F.coalesce("deg", F.lit(0)).alias("deg")))
query("op_join_full", "SELECT coalesce(a.c, b.s) AS n, a.c IS NOT NULL AS has_c, b.s IS NOT NULL AS has_s FROM (SELECT DISTINCT c_nationkey AS c FROM customer) a FULL JOIN (SELECT DISTINCT s_nationkey AS s FROM supplier) b ON a.c = b.s")(
    lambda s, d: (c := read(s, d, "customer").select(F.col("c_nationkey").alias("c")).distinct()).join(x := read(s, d, "supplier").select(F.col("s_nationkey").alias("s")).distinct(), F.col("c") == F.col("s"), "full").select(F.coalesce("c", "s").alias("n"), F.col("c").isNotNull().alias("has_c"), F.col("s").isNotNull().alias("has_s"))
)
query("op_join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY r_name")(
    lambda s, d: read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))
)
query("op_join_range", "WITH e AS (SELECT floor(epoch(ts))::BIGINT AS t, user_id FROM events) SELECT DISTINCT a.user_id AS u, b.user_id AS v FROM e a JOIN e b ON abs(a.t - b.t) <= 60 AND a.user_id < b.user_id")(lambda s, d: within_interval(s, d, 60).edges)


@query("op_join_asof", "SELECT o_orderkey, o_custkey, (SELECT max(p.o_orderdate) FROM orders p WHERE p.o_custkey = o.o_custkey AND p.o_orderdate < o.o_orderdate) AS before FROM orders o")
def _asof(s: SparkSession, d: str) -> DataFrame:
    """The customer's latest earlier order date, by one ordered window and no self join."""
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_orderdate").cast("timestamp").cast("long")).rangeBetween(Window.unboundedPreceding, -1)
    return read(s, d, "orders").select("o_orderkey", "o_custkey", F.max("o_orderdate").over(w).alias("before"))


REPORT = "SELECT {c}, count(*) AS n, round(avg(l_quantity), 6) AS q FROM lineitem GROUP BY {g}"
query("op_rollup", REPORT.format(c="l_returnflag, l_linestatus", g="ROLLUP (l_returnflag, l_linestatus)"))(lambda s, d: r6(read(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.avg("l_quantity").alias("q"))))
query("op_cube", REPORT.format(c="l_returnflag, l_linestatus", g="CUBE (l_returnflag, l_linestatus)"))(lambda s, d: r6(read(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.avg("l_quantity").alias("q"))))
query("op_grouping_sets", REPORT.format(c="l_returnflag, l_linestatus", g="GROUPING SETS ((l_returnflag), (l_linestatus))"))(
    lambda s, d: r6(read(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.avg("l_quantity").alias("q")))
)
query("op_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'O') AS \"O\", count(*) FILTER (l_linestatus = 'F') AS \"F\" FROM lineitem GROUP BY l_returnflag")(
    lambda s, d: read(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["O", "F"]).agg(F.count(F.lit(1))).fillna(0)
)
query("op_unpivot", "SELECT l_orderkey, name, sum(x)::DOUBLE AS total FROM (SELECT l_orderkey, 'q' AS name, l_quantity AS x FROM lineitem UNION ALL SELECT l_orderkey, 'd', l_discount * 100 FROM lineitem) GROUP BY l_orderkey, name".replace("sum(x)::DOUBLE", "round(sum(x), 6)"))(
    lambda s, d: r6(read(s, d, "lineitem").select("l_orderkey", F.col("l_quantity").alias("q"), (F.col("l_discount") * 100).alias("d")).unpivot("l_orderkey", ["q", "d"], "name", "x").groupBy("l_orderkey", "name").agg(F.sum("x").alias("total")))
)
query("op_aggregates", "SELECT p_brand, count(DISTINCT p_type) AS types, min_by(p_name, p_partkey) AS first_name, max_by(p_name, p_partkey) AS last_name, round(var_samp(p_retailprice), 4) AS v, round(stddev_pop(p_size), 4) AS sd, bool_and(p_size > 0) AS sized, count(*) FILTER (p_size > 25) AS large FROM part GROUP BY p_brand")(
    lambda s, d: read(s, d, "part").groupBy("p_brand").agg(F.countDistinct("p_type").alias("types"), F.min_by("p_name", "p_partkey").alias("first_name"), F.max_by("p_name", "p_partkey").alias("last_name"), F.round(F.var_samp("p_retailprice"), 4).alias("v"), F.round(F.stddev_pop("p_size"), 4).alias("sd"), F.bool_and(F.col("p_size") > 0).alias("sized"), F.count_if(F.col("p_size") > 25).alias("large"))
)
query("op_percentiles", CPY + " SELECT quantile_cont(d, 0.5)::DOUBLE AS mid, quantile_cont(d, 0.9)::DOUBLE AS high FROM deg")(lambda s, d: exact.degrees(cpy(s, d)).agg(F.percentile("deg", 0.5).alias("mid"), F.percentile("deg", 0.9).alias("high")))
query("op_sketches")(lambda s, d: read(s, d, "lineitem").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"), F.approx_count_distinct("l_suppkey").alias("suppliers")))
query("op_window_ranks", CPY + " SELECT id, rank() OVER (ORDER BY d DESC) AS r, dense_rank() OVER (ORDER BY d DESC) AS dr, round(percent_rank() OVER (ORDER BY d), 6) AS pr, round(cume_dist() OVER (ORDER BY d), 6) AS cd FROM deg")(lambda s, d: _ranks(exact.degrees(cpy(s, d))))


def _ranks(deg: DataFrame) -> DataFrame:
    """Global ranks from the degree histogram, which is small, and not from a sort of all nodes in one task."""
    hist = deg.groupBy("deg").agg(F.count("*").alias("c"))
    down, up, all_of = Window.orderBy(F.desc("deg")), Window.orderBy("deg"), Window.partitionBy()
    n, before = F.sum("c").over(all_of), F.sum("c").over(up) - F.col("c")
    rows = hist.select("deg", (F.sum("c").over(down) - F.col("c") + 1).cast("int").alias("r"), F.row_number().over(down).alias("dr"), F.round(before / F.greatest(n - 1, F.lit(1)), 6).alias("pr"), F.round(F.sum("c").over(up) / n, 6).alias("cd"))
    return deg.join(F.broadcast(rows), "deg").select("id", "r", "dr", "pr", "cd")


query("op_window_frames", "SELECT o_orderkey, lag(o_totalprice) OVER w AS prev, lead(o_totalprice) OVER w AS next, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")(
    lambda s, d: read(s, d, "orders").select("o_orderkey", F.lag("o_totalprice").over(w := Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("prev"), F.lead("o_totalprice").over(w).alias("next"), F.round(F.avg("o_totalprice").over(w.rowsBetween(-2, 0)), 4).alias("moving"))
)
query("op_top_k", with_buckets("cpy", "type") + " SELECT bucket, id, d AS deg FROM (SELECT bucket, deg.id, d, row_number() OVER (PARTITION BY bucket ORDER BY d DESC, deg.id) AS r FROM deg JOIN buckets USING (id)) WHERE r <= 3")(
    lambda s, d: exact.degrees(g := cpy(s, d)).join(X.part_buckets(s, d, g, "type"), "id").withColumn("r", F.row_number().over(Window.partitionBy("bucket").orderBy(F.desc("deg"), "id"))).where("r <= 3").select("bucket", "id", "deg")
)
YEARS = ", ".join(f"e{y} AS (SELECT DISTINCT a.p AS u, b.p AS v FROM y{y} a JOIN y{y} b ON a.o = b.o AND a.p < b.p)" for y in (1996, 1997))
LINES = ", ".join(f"y{y} AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE year(o_orderdate) = {y})" for y in (1996, 1997))
DRIFT = f"WITH {LINES}, {YEARS} "
from localcoef.sources.graphs import copart_year  # noqa: E402

query("op_set_intersect", DRIFT + "SELECT u, v FROM e1996 INTERSECT SELECT u, v FROM e1997")(lambda s, d: copart_year(s, d, 1996).edges.intersect(copart_year(s, d, 1997).edges))
query("op_set_except", DRIFT + "SELECT u, v FROM e1996 EXCEPT SELECT u, v FROM e1997")(lambda s, d: copart_year(s, d, 1996).edges.exceptAll(copart_year(s, d, 1997).edges))
query("op_set_union", DRIFT + "SELECT u, v FROM e1996 UNION SELECT u, v FROM e1997")(lambda s, d: copart_year(s, d, 1996).edges.unionByName(copart_year(s, d, 1997).edges).distinct())
query("op_json", "SELECT event_type, sum((props->>'$.k')::INTEGER)::BIGINT AS k FROM events GROUP BY event_type")(lambda s, d: read(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("int")).alias("k")))
query("op_variant", "SELECT event_type, max((props->>'$.k')::BIGINT) AS k FROM events GROUP BY event_type")(lambda s, d: read(s, d, "events").groupBy("event_type").agg(F.max(F.variant_get(F.parse_json("props"), "$.k", "long")).alias("k")))
query("op_arrays_maps", "SELECT o_custkey, list_sort(list_distinct(list(o_orderpriority))) AS kinds, count(*) AS n FROM orders GROUP BY o_custkey")(lambda s, d: read(s, d, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_set("o_orderpriority")).alias("kinds"), F.count("*").alias("n")))


@query("op_sql_subqueries", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT avg(o_totalprice) FROM orders))")
def _subqueries(s: SparkSession, d: str) -> DataFrame:
    text = "WITH big AS (SELECT o_custkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders})) SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM big WHERE big.o_custkey = c.c_custkey)"
    return s.sql(text, orders=read(s, d, "orders"), customer=read(s, d, "customer"))


query("op_lateral", "SELECT n_name, x.c_custkey, x.c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) x")(
    lambda s, d: s.sql("SELECT n_name, x.c_custkey, x.c_acctbal FROM {n} n, LATERAL (SELECT c_custkey, c_acctbal FROM {c} WHERE c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) x", n=read(s, d, "nation"), c=read(s, d, "customer"))
)
query("op_recursive", "WITH RECURSIVE t(n, f) AS (SELECT 1, 1::BIGINT UNION ALL SELECT n + 1, f * (n + 1) FROM t WHERE n < 10) SELECT n, f FROM t")(lambda s, d: s.sql("WITH RECURSIVE t(n, f) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT n + 1, f * (n + 1) FROM t WHERE n < 10) SELECT n, f FROM t"))


@query("op_functions", "SELECT i::BIGINT AS ix, round(('0x' || substr(md5('7:main:' || i), 1, 13))::BIGINT / 4503599627370496::DOUBLE, 6) AS u01 FROM range(0, 20) t(i)")
def _functions(s: SparkSession, d: str) -> DataFrame:
    register_all(s)
    return r6(s.sql("SELECT ix, u01 FROM draw_edges(20, 7)"))


query("st_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: S.run_to_memory(S.window_counts(S.event_stream(s, d)), "complete"))
query("st_sessions", """WITH g AS (SELECT user_id, ts, (ts >= coalesce(lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE, TIMESTAMP '1970-01-01'))::INT AS fresh FROM events),
  h AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM h GROUP BY user_id, k""")(lambda s, d: S.sessions(read(s, d, "events")))  # fmt: skip
query("st_distinct", "SELECT count(DISTINCT event_id) AS n FROM events")(lambda s, d: S.run_to_memory(S.distinct_events(S.event_stream(s, d))).agg(F.count("*").alias("n")))
query("st_enriched")(lambda s, d: S.run_to_memory(S.with_buckets(S.event_stream(s, d).select(F.col("user_id").alias("u"), (F.col("user_id") + 1).alias("v")), P.numbered(read(s, d, "events").select(F.col("user_id").alias("id"), F.col("event_type").alias("label")).groupBy("id").agg(F.min("label").alias("label"))))))
query("st_sliding", """SELECT w AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS w FROM events) GROUP BY ALL""")(
    lambda s, d: S.run_to_memory(S.window_counts(S.event_stream(s, d), "1 hour", "30 minutes"), "complete")
)
query("st_co_activity", """SELECT DISTINCT a.user_id AS u, b.user_id AS v FROM events a JOIN events b ON floor(epoch(a.ts) / 600) = floor(epoch(b.ts) / 600) AND a.user_id < b.user_id""")(
    lambda s, d: S.co_activity(S.event_stream(s, d))
)


def _edge_files(s, d):
    """The edges of the year's graph as files that a stream reads, and its buckets."""
    g = cpy(s, d)
    edges = written(g.edges, "edges")
    return (lambda: s.readStream.schema(edges.schema).parquet(edges.inputFiles()[0].rsplit("/", 1)[0])), X.part_buckets(s, d, g, "type")


query("st_refresh")(lambda s, d: S.streamed_estimate((x := _edge_files(s, d))[0](), x[1], "clustering"))
query("st_passes")(lambda s, d: S.streamed_passes(*_edge_files(s, d), "clustering", 2000))
