"""Registered queries of the graph methods, each with its DuckDB equivalent where SQL can say it.

Floating-point results are rounded to six places on both sides, as sums differ in their last bits by order.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Sequence
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localcoef import oracles as O
from localcoef.functions import concentration as C
from localcoef.model import Graph
from localcoef.operators import baselines, bounds, estimators, exact, measures, prefilter, sampling, tuning
from localcoef.plans import experiments as X
from localcoef.plans.estimate import adaptive_estimate, fixed_size_estimate, multipass_stream_estimate, prepare
from localcoef.plans.store import written
from localcoef.ship import ship
from localcoef.sources import graphs as G
from localcoef.sources import partitions as P

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}
SEED, DRAWS, SPLIT = 7, 2000, 0.2


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            ship(spark)
            return f(spark, sf_dir)

        QUERIES[name] = run
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def r6(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


#: The graph that the operators' queries run on; see the end of this file.
GRAPH: ContextVar[str] = ContextVar("graph", default="cpy")


def cpy(spark: SparkSession, d: str) -> Graph:
    """The graph of the year 1996, or the one that a query is registered on besides."""
    return G.GRAPHS[GRAPH.get()](spark, d)


def part_buckets(spark: SparkSession, d: str, g: Graph, kind: str) -> DataFrame:
    """A partition by name; the hub graph's nodes are not parts alone, so there it is by degree."""
    return X.part_buckets(spark, d, g, "deg" if GRAPH.get() == "tr" else kind)


def numbered(g: Graph) -> tuple[DataFrame, int]:
    edges = sampling.number_edges(g.edges)
    return edges, g.edges.count()


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """The fixed-size estimator for clustering by part type."""
    ship(spark)
    g = cpy(spark, d)
    return fixed_size_estimate(g, part_buckets(spark, d, g, "type"), "clustering", fraction=0.2, seed=SEED)


# --- exact layer

CPY = O.graph("cpy")
query("x1_degree", CPY + " SELECT id, d AS deg FROM deg")(lambda s, d: exact.degrees(cpy(s, d)))
query("x2_wedges_centered", CPY + " SELECT id, d * (d - 1) // 2 AS wc FROM deg")(lambda s, d: exact.wedges_centered(cpy(s, d)))
query("x3_wedges_headed", CPY + " SELECT id, wh FROM head")(lambda s, d: exact.wedges_headed(cpy(s, d)))
for _c in ("clustering", "closure"):
    query(f"x4_denominators_{_c}", CPY + " " + O.W[_c])(lambda s, d, c=_c: exact.denominators(cpy(s, d), c))
query("x5_wedge_total", CPY + " SELECT sum(d * (d - 1) // 2)::BIGINT AS wedges FROM deg")(lambda s, d: exact.wedge_total(cpy(s, d)).select(F.col("wedges").cast("long")))
query("x6_edge_triangles", CPY + " SELECT e.u, e.v, count(b.dst) AS n FROM edges e LEFT JOIN adj a ON a.src = e.u LEFT JOIN adj b ON b.src = e.v AND b.dst = a.dst GROUP BY e.u, e.v")(lambda s, d: exact.edge_triangles(cpy(s, d)))
query("x7_triangles", CPY + " SELECT a, b, c FROM tri")(lambda s, d: exact.triangles(cpy(s, d)))
query("x7_triangle_count_cp", O.graph("cp") + " SELECT count(*) AS n FROM tri")(lambda s, d: exact.triangle_count(G.copart(s, d)))
query("x8_node_triangles", CPY + " SELECT id, t FROM prof")(lambda s, d: exact.node_triangles(cpy(s, d)))
for _c, _n in (("clustering", "alpha"), ("closure", "phi")):
    query(f"x{'9' if _n == 'alpha' else '10'}_local_{_c}", CPY + f" SELECT id, round({_n}, 6) AS psi FROM prof")(lambda s, d, c=_c: r6(exact.local_coefficients(cpy(s, d), c)))
    query(f"x14_bruteforce_{_c}", CPY + f" SELECT id, round({_n}, 6) AS psi FROM prof")(lambda s, d, c=_c: r6(exact.local_coefficients_bruteforce(cpy(s, d), c)))
    for _k in ("brand", "type", "segment", "deg", "log", "rnd"):
        query(f"x11_bucket_means_{_c}_{_k}", O.with_buckets("cpy", _k) + f" SELECT bucket, count(*) AS size, round(avg({_n}), 6) AS psi FROM prof JOIN buckets USING (id) GROUP BY bucket")(
            lambda s, d, c=_c, k=_k: r6(exact.exact_bucket_means(g := exact.indexed(cpy(s, d)), part_buckets(s, d, g, k), c))
        )
    query(f"x12_global_{_c}", O.with_buckets("cpy", "one") + f" SELECT bucket, count(*) AS size, round(avg({_n}), 6) AS psi FROM prof JOIN buckets USING (id) GROUP BY bucket")(
        lambda s, d, c=_c: r6(exact.exact_bucket_means(g := exact.indexed(cpy(s, d)), P.single_bucket(g), c))
    )
    query(f"x13_subset_{_c}", CPY + f" SELECT count(*) AS size, round(coalesce(avg({_n}), 0), 6) AS psi FROM prof JOIN part ON p_partkey = id WHERE p_size < 10")(
        lambda s, d, c=_c: r6(exact.subset_mean(cpy(s, d), G.read(s, d, "part").where("p_size < 10").select(F.col("p_partkey").alias("id")), c))
    )


@query("x15_weighted_clustering", CPY + """, wg AS (SELECT u, v, count(*)::DOUBLE AS weight FROM (SELECT a.p AS u, b.p AS v, a.o FROM gl a JOIN gl b ON a.o = b.o AND a.p < b.p) GROUP BY u, v),
  wa AS (SELECT u AS src, v AS dst, weight FROM wg UNION ALL SELECT v, u, weight FROM wg), st AS (SELECT src AS id, sum(weight) AS s FROM wa GROUP BY src),
  cl AS (SELECT id, sum(wx.weight + wy.weight) AS c FROM (SELECT a AS id, b AS x, c AS y FROM tri UNION ALL SELECT b, a, c FROM tri UNION ALL SELECT c, a, b FROM tri) t
    JOIN wa wx ON wx.src = id AND wx.dst = x JOIN wa wy ON wy.src = id AND wy.dst = y GROUP BY id)
  SELECT deg.id, round(CASE WHEN d > 1 THEN coalesce(c, 0) / (s * (d - 1)) ELSE 0 END, 6) AS psi FROM deg JOIN st USING (id) LEFT JOIN cl USING (id)""")  # fmt: skip
def _weighted(s: SparkSession, d: str) -> DataFrame:
    lines = G.year_lines(s, d, 1996) if GRAPH.get() == "cpy" else G.read(s, d, "lineitem")
    rows = lines.select(F.col("l_orderkey").alias("o"), F.col("l_partkey").alias("p")).distinct()
    pairs = rows.withColumnRenamed("p", "u").join(rows.withColumnRenamed("p", "v"), "o").where("u < v").groupBy("u", "v").agg(F.count("*").cast("double").alias("weight"))
    return r6(exact.weighted_clustering(cpy(s, d), pairs))


# --- sampling

BAG = CPY + O.NUMBER + O.bag(str(DRAWS), SEED)
query("s1_index_bag", BAG + " SELECT ix, u, v FROM bag")(lambda s, d: sampling.draw_indexed(*numbered(cpy(s, d)), DRAWS, SEED))
query("s2_number_edges", CPY + O.NUMBER + " SELECT eid, u, v FROM numbered")(lambda s, d: sampling.number_edges(cpy(s, d).edges))
query("s7_pilot_bag", CPY + O.NUMBER + O.bag("500", SEED, "pilot") + " SELECT ix, u, v FROM bag")(lambda s, d: sampling.draw_indexed(*numbered(cpy(s, d)), 500, SEED, "pilot"))
query("s3_poisson_bag", CPY + O.NUMBER + f""", dr AS (SELECT u, v, {O.hashed(SEED, "poisson", "u", "v")} AS x, 2000.0::DOUBLE / m AS r FROM edges, total)
  SELECT u, v, ((x >= exp(-r))::INT + (x >= exp(-r) * (1 + r))::INT + (x >= exp(-r) * (1 + r + r * r / 2))::INT + (x >= exp(-r) * (1 + r + r * r / 2 + r * r * r / 6))::INT
    + (x >= exp(-r) * (1 + r + r * r / 2 + r * r * r / 6 + r * r * r * r / 24))::INT)::INTEGER AS copies FROM dr WHERE x >= exp(-r)""")(
    lambda s, d: sampling.draw_poisson(g.edges, g.edges.count(), DRAWS, SEED) if (g := cpy(s, d)) else None
)
query("s4_fraction_sample")(lambda s, d: cpy(s, d).edges.sample(False, 0.1, SEED))
query("s5_weighted_bag")(lambda s, d: r6(sampling.draw_weighted(estimators.min_degree_weights(cpy(s, d)), 500, SEED)))


@query("s6_nodes_per_bucket", O.with_buckets("cpy", "type") + f""", ranked AS (SELECT bucket, id, row_number() OVER (PARTITION BY bucket ORDER BY id % 64, id) - 1 AS r FROM buckets),
  wish AS (SELECT bucket, i AS ix, least(floor({O.hashed(SEED, "nodes", "bucket", "i")} * size)::BIGINT, size - 1) AS r FROM sizes, range(0, 50) t(i))
  SELECT bucket, ix, id FROM wish JOIN ranked USING (bucket, r)""")  # fmt: skip
def _nodes(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    b = part_buckets(s, d, g, "type")
    return sampling.draw_nodes(b, b.select("bucket").distinct().withColumn("s", F.lit(50)), SEED)


# --- estimators

VALS = {c: O.with_buckets("cpy", "brand") + O.NUMBER + O.bag(str(DRAWS), SEED) + O.values("bag", "0.2", c) for c in O.W}
FULL = {c: O.with_buckets("cpy", "brand") + O.NUMBER + O.values("edges", "0.2", c) for c in O.W}


def _bag(s: SparkSession, d: str, kind: str = "brand", n: int = DRAWS):
    g = cpy(s, d)
    rows, m = numbered(g)
    return g, sampling.draw_indexed(rows, m, n, SEED), m, part_buckets(s, d, g, kind)


query("e1_edge_credits", VALS["clustering"] + " SELECT ix, node, round(a, 6) AS a FROM bag JOIN shares USING (u, v)")(lambda s, d: r6(estimators.edge_credits((x := _bag(s, d))[0], x[1], SPLIT)))
query("e2_node_triangle_estimate", VALS["clustering"] + f" SELECT node AS id, round(sum(a) * (SELECT m FROM total) / {DRAWS}, 6) AS t_hat FROM bag JOIN shares USING (u, v) GROUP BY node")(
    lambda s, d: r6(estimators.estimate_node_triangles((x := _bag(s, d))[0], x[1], DRAWS, x[2], SPLIT))
)
for _c in O.W:
    query(f"e3_edge_bucket_values_{_c}", VALS[_c] + " SELECT ix, bucket, round(x + 1e-9::DOUBLE, 6) AS x FROM bag JOIN vals USING (u, v)")(
        # many values are short binary fractions; the shift keeps them off the ties of rounding
        lambda s, d, c=_c: r6(estimators.edge_bucket_values((x := _bag(s, d))[0], x[1], x[3], exact.denominators(x[0], c), x[2], SPLIT).withColumn("x", F.col("x") + 1e-9))
    )
    query(f"e4_fixed_bag_means_{_c}", VALS[_c] + f" SELECT bucket, size, round(coalesce(sum(x), 0) / {DRAWS}, 6) AS f FROM sizes LEFT JOIN (SELECT bucket, x FROM bag JOIN vals USING (u, v)) USING (bucket) GROUP BY bucket, size")(
        lambda s, d, c=_c: r6(estimators.bucket_means(estimators.edge_bucket_values((x := _bag(s, d))[0], x[1], x[3], exact.denominators(x[0], c), x[2], SPLIT), x[3], DRAWS))
    )
    query(f"e7_expectation_{_c}", O.with_buckets("cpy", "brand") + f" SELECT bucket, round(avg({'alpha' if _c == 'clustering' else 'phi'}), 6) AS mean FROM prof JOIN buckets USING (id) GROUP BY bucket")(
        lambda s, d, c=_c: r6(estimators.exact_edge_moments(g := cpy(s, d), part_buckets(s, d, g, "brand"), exact.denominators(g, c), g.edges.count(), SPLIT).select("bucket", "mean"))
    )
    query(f"e8_variance_{_c}", FULL[_c] + """, mo AS (SELECT bucket, coalesce(sum(x), 0) / (SELECT m FROM total) AS mean, coalesce(sum(x * x), 0) / (SELECT m FROM total) AS two FROM sizes LEFT JOIN vals USING (bucket) GROUP BY bucket)
      SELECT bucket, round(two - mean * mean, 4) AS variance, round(((SELECT m FROM total) - 1) * mean * mean, 4) AS ceiling FROM mo""")(
        lambda s, d, c=_c: estimators.exact_edge_moments(g := cpy(s, d), part_buckets(s, d, g, "brand"), exact.denominators(g, c), m := g.edges.count(), SPLIT).select("bucket", F.round("variance", 4).alias("variance"), F.round(F.col("mean") * F.col("mean") * (m - 1), 4).alias("ceiling"))
    )
    query(f"b9_true_range_{_c}", FULL[_c] + " SELECT bucket, round(coalesce(max(x), 0), 6) AS r FROM sizes LEFT JOIN vals USING (bucket) GROUP BY bucket")(
        lambda s, d, c=_c: r6(estimators.exact_edge_moments(g := cpy(s, d), part_buckets(s, d, g, "brand"), exact.denominators(g, c), g.edges.count(), SPLIT).select("bucket", F.col("largest").alias("r")))
    )
    query(f"b6_range_bounds_{_c}", O.with_buckets("cpy", "brand") + f", total AS (SELECT count(*) AS m FROM edges), wt AS ({O.W[_c]})" + O.SIDE + " SELECT bucket, round(coalesce(max(x), 0) * (SELECT m FROM total) / any_value(size), 6) AS r FROM sizes LEFT JOIN rb USING (bucket) GROUP BY bucket")(
        lambda s, d, c=_c: r6(bounds.range_bounds(g := cpy(s, d), part_buckets(s, d, g, "brand"), exact.denominators(g, c), g.edges.count(), SPLIT))
    )
    query(f"q1_quadratics_{_c}", O.with_buckets("cpy", "brand") + O.NUMBER + O.bag("500", SEED, "pilot") + O.values("bag", "0", _c).replace("vals AS", "v0 AS") + O.values("bag", "0.5", _c).replace("wt AS", "wt2 AS").replace("et AS", "et2 AS").replace("shares AS", "sh2 AS").replace("FROM et ", "FROM et2 ").replace("JOIN wt ON wt.id", "JOIN wt2 wt ON wt.id").replace("FROM shares", "FROM sh2").replace("vals AS", "v5 AS") + """,
      dr AS (SELECT ix, b.bucket, coalesce(v0.x, 0) AS b, 2 * (coalesce(v5.x, 0) - coalesce(v0.x, 0)) AS s FROM (SELECT ix, u, v, bucket FROM bag, sizes) b LEFT JOIN v0 ON v0.u = b.u AND v0.v = b.v AND v0.bucket = b.bucket LEFT JOIN v5 ON v5.u = b.u AND v5.v = b.v AND v5.bucket = b.bucket)
      SELECT bucket, round(var_samp(b), 4) AS qa, round(2 * covar_samp(b, s), 4) AS qb, round(var_samp(s), 4) AS qc FROM dr GROUP BY bucket""")(
        lambda s, d, c=_c: tuning.split_quadratics(g := cpy(s, d), sampling.draw_indexed(*(x := numbered(g)), 500, SEED, "pilot"), part_buckets(s, d, g, "brand"), exact.denominators(g, c), x[1], 500).select("bucket", *[F.round(n, 4).alias(n) for n in ("qa", "qb", "qc")])
    )
    query(f"b7_tight_ranges_{_c}", O.with_buckets("cpy", "brand") + f", total AS (SELECT count(*) AS m FROM edges), wt AS ({O.W[_c]})" + O.TIGHT + " SELECT bucket, round(coalesce(max(x), 0) * (SELECT m FROM total) / any_value(size), 6) AS r FROM sizes LEFT JOIN rb USING (bucket) GROUP BY bucket")(lambda s, d, c=_c: r6(bounds.range_bounds(g := cpy(s, d), part_buckets(s, d, g, "brand"), exact.denominators(g, c), g.edges.count(), SPLIT, True)))


@query("e5_split_extremes", VALS["clustering"].replace("vals AS", "v2 AS") + f""", gr AS (SELECT unnest([0.0::DOUBLE, 1 / 3.0::DOUBLE, 0.5::DOUBLE]) AS q), raw AS (
  SELECT q, u, v, bucket, sum(a / (wt.w * size)) * (SELECT m FROM total) AS x FROM (SELECT q, u, v, w AS node, 1 - 2 * q AS a FROM et, gr UNION ALL SELECT q, u, v, u, count(*) * q FROM et, gr GROUP BY q, u, v UNION ALL SELECT q, u, v, v, count(*) * q FROM et, gr GROUP BY q, u, v)
  JOIN wt ON wt.id = node AND wt.w > 0 JOIN buckets b ON b.id = node JOIN sizes USING (bucket) GROUP BY q, u, v, bucket), got AS (SELECT q, bucket, sum(x) AS x FROM bag JOIN raw USING (u, v) GROUP BY q, bucket)
  SELECT sizes.bucket, size, round(gr.q, 6) AS q, round(coalesce(x, 0) / {DRAWS}, 6) AS f FROM sizes CROSS JOIN gr LEFT JOIN got ON got.bucket = sizes.bucket AND got.q = gr.q""")  # fmt: skip
def _extremes(s: SparkSession, d: str) -> DataFrame:
    g, bag, m, b = _bag(s, d)
    w, out = exact.denominators(g, "clustering"), None
    for q in (0.0, 1 / 3, 0.5):
        row = estimators.bucket_means(estimators.edge_bucket_values(g, bag, b, w, m, q), b, DRAWS).withColumn("q", F.lit(q))
        out = row if out is None else out.unionByName(row)
    return r6(out)


@query("e6_importance_bag")
def _importance(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    b = part_buckets(s, d, g, "brand")
    bag = sampling.draw_weighted(estimators.min_degree_weights(g), DRAWS, SEED)
    return r6(estimators.importance_means(g, bag, b, exact.denominators(g, "clustering"), DRAWS, SPLIT))


# --- bounds and tuning

SPREAD = O.with_buckets("cpy", "brand") + """, sp AS (SELECT id, count(DISTINCT bucket) AS chi FROM (SELECT src AS id, bucket FROM adj JOIN buckets b ON b.id = dst UNION ALL SELECT id, bucket FROM buckets) GROUP BY id)"""
query("b1_spread", SPREAD + " SELECT id, chi FROM sp")(lambda s, d: bounds.bucket_spread(g := cpy(s, d), part_buckets(s, d, g, "brand")))
query("b2_open_spread", O.with_buckets("cpy", "brand") + " SELECT src AS id, count(DISTINCT bucket) AS chi FROM adj JOIN buckets b ON b.id = dst GROUP BY src")(lambda s, d: bounds.bucket_spread(g := cpy(s, d), part_buckets(s, d, g, "brand"), False))
query("b3_spread_sup", SPREAD + " SELECT max(CASE WHEN a.d < b.d THEN p.chi WHEN b.d < a.d THEN q.chi ELSE least(p.chi, q.chi) END) AS chi FROM edges JOIN deg a ON a.id = u JOIN deg b ON b.id = v JOIN sp p ON p.id = u JOIN sp q ON q.id = v")(
    lambda s, d: bounds.spread_sup(g := cpy(s, d), part_buckets(s, d, g, "brand"))
)
query("b4_dimension", "SELECT i AS chi, (floor(log2(i)) + 1)::INTEGER AS zeta FROM range(1, 65) t(i)")(lambda s, d: s.createDataFrame([(i, bounds.dimension_bound(i)) for i in range(1, 65)], "chi long, zeta int"))
query("b5_dimension_by_split", "SELECT i AS chi, (floor(log2(least(i, 2))) + 1)::INTEGER AS zeta FROM range(1, 65) t(i)")(lambda s, d: s.createDataFrame([(i, bounds.dimension_bound(i, 0.5)) for i in range(1, 65)], "chi long, zeta int"))
SIZES_SQL = """SELECT r, eps, ceil(3 * r * ln(4 * 25 / (0.01::DOUBLE / 4)) / eps + 1)::BIGINT AS start, round((r / eps) * (r / eps) * (3 + ln(2 / 0.01::DOUBLE)), 4) AS cap, ceil(ln(2 * 25 / 0.01::DOUBLE) / (2 * eps * eps))::BIGINT AS hoeffding,
  round(1 / (eps * 0.001::DOUBLE * eps * 0.001::DOUBLE), 0) AS relative FROM (SELECT unnest([1.0::DOUBLE, 2.0::DOUBLE, 8.0::DOUBLE, 217.6::DOUBLE]) AS r), (SELECT unnest([0.01::DOUBLE, 0.075::DOUBLE, 0.2::DOUBLE]) AS eps)"""
query("c1_c2_sample_sizes", SIZES_SQL)(lambda s, d: s.createDataFrame(
    [(r, e, C.sample_start(r, e, 25, C.budget_of_round(0, 0.01)), round(C.sample_cap(r, e, 3, 0.01), 4), C.hoeffding_size(e, 25, 0.01), round(C.relative_error_size(e, 0.001), 0)) for r in (1.0, 2.0, 8.0, 217.6) for e in (0.01, 0.075, 0.2)],
    "r double, eps double, start long, cap double, hoeffding long, relative double"))
query("c3_bernstein", VALS["clustering"] + f""", mo AS (SELECT bucket, coalesce(sum(x), 0) AS sx, coalesce(sum(x * x), 0) AS sxx FROM sizes LEFT JOIN (SELECT bucket, x FROM bag JOIN vals USING (u, v)) USING (bucket) GROUP BY bucket), k AS (SELECT count(*) AS k FROM sizes)
  SELECT bucket, round(sqrt(2 * greatest(sxx - sx * sx / {DRAWS}, 0) / ({DRAWS} - 1) * ln(4 * k / 0.0025::DOUBLE) / {DRAWS}) + 7 * 8 * ln(4 * k / 0.0025::DOUBLE) / (3 * ({DRAWS} - 1)), 6) AS halfwidth FROM mo, k""")(
    lambda s, d: _bernstein(s, d)
)


def _bernstein(s: SparkSession, d: str) -> DataFrame:
    g, bag, m, b = _bag(s, d)
    b = written(b, "buckets")
    k = b.select("bucket").distinct().count()
    sums = estimators.moments(estimators.edge_bucket_values(g, bag, b, exact.denominators(g, "clustering"), m, SPLIT))
    full = b.select("bucket").distinct().join(sums, "bucket", "left").fillna(0.0)
    v = (F.col("sxx") - F.col("sx") * F.col("sx") / DRAWS) / (DRAWS - 1)
    return r6(full.select("bucket", C.bernstein_column(v, F.lit(8.0), F.lit(float(DRAWS)), k, 0.0025).alias("halfwidth")))


PLUGIN_SQL = VALS["clustering"] + f""", k AS (SELECT count(*) AS k FROM sizes), lg AS (SELECT ln(2 / (0.0025::DOUBLE / k)) AS l FROM k),
  dn AS (SELECT s.bucket, b.ix, coalesce(vals.x, 0) AS x FROM sizes s CROSS JOIN bag b LEFT JOIN vals ON vals.u = b.u AND vals.v = b.v AND vals.bucket = s.bucket),
  me AS (SELECT *, coalesce(avg(x) OVER (PARTITION BY bucket ORDER BY ix ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS mean FROM dn),
  sp AS (SELECT *, (x - mean) * (x - mean) AS off, CASE WHEN ix = 0 THEN 256.0::DOUBLE ELSE (256 + coalesce(sum((x - mean) * (x - mean)) OVER (PARTITION BY bucket ORDER BY ix ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / ix END AS spread FROM me),
  be AS (SELECT *, least(sqrt(2 * l / ({DRAWS} * spread)), 1 / 64.0::DOUBLE) AS bet FROM sp, lg)
  SELECT bucket, round(sum(bet * x) / sum(bet), 6) AS center, round((any_value(l) + sum((-ln(1 - bet * 32) - bet * 32) / 4 * off) * 4 / 1024.0::DOUBLE) / sum(bet), 6) AS halfwidth FROM be GROUP BY bucket"""  # fmt: skip


def _plugin(s: SparkSession, d: str, chunked: bool) -> DataFrame:
    g, bag, m, b = _bag(s, d)
    b = written(b.select("id", "bucket"), "buckets")
    names = b.select("bucket").distinct()
    k = names.count()
    values = estimators.edge_bucket_values(g, bag, b, exact.denominators(g, "clustering"), m, SPLIT)
    if chunked:
        return r6(C.plugin_chunks(values, b, names.withColumn("r", F.lit(32.0)), DRAWS, 0.0025 / k, 256))
    dense = names.crossJoin(s.range(DRAWS).withColumnRenamed("id", "ix")).join(values, ["bucket", "ix"], "left").fillna(0.0)
    return r6(C.plugin_windows(dense, 32.0, DRAWS, 0.0025 / k))


query("c6_plugin_windows", PLUGIN_SQL)(lambda s, d: _plugin(s, d, False))
query("c6_plugin_chunks", PLUGIN_SQL)(lambda s, d: _plugin(s, d, True))
query("c11_regime")(lambda s, d: _regime(s, d))
query("c12_cost_model")(lambda s, d: _costs(s, d))


@query("q3_minimax")
def _minimax(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    rows, m = numbered(g)
    bag, b = sampling.draw_indexed(rows, m, 500, SEED, "pilot"), part_buckets(s, d, g, "brand")
    out = []
    for c in O.W:
        found = tuning.split_quadratics(g, bag, b, exact.denominators(g, c), m, 500).collect()
        out.append((c, *tuning.minimax_split([(r["qa"], r["qb"], max(0.0, r["qc"])) for r in found])))
    return r6(s.createDataFrame(out, "coefficient string, q double, variance double"))


@query("m14_variance_by_q", FULL["clustering"].replace("vals AS", "v2 AS") + """, gr AS (SELECT unnest([0.0::DOUBLE, 0.2::DOUBLE, 0.5::DOUBLE]) AS q), raw AS (
  SELECT q, u, v, bucket, sum(a / (wt.w * size)) * (SELECT m FROM total) AS x FROM (SELECT q, u, v, w AS node, 1 - 2 * q AS a FROM et, gr UNION ALL SELECT q, u, v, u, count(*) * q FROM et, gr GROUP BY q, u, v UNION ALL SELECT q, u, v, v, count(*) * q FROM et, gr GROUP BY q, u, v)
  JOIN wt ON wt.id = node AND wt.w > 0 JOIN buckets b ON b.id = node JOIN sizes USING (bucket) GROUP BY q, u, v, bucket)
  SELECT q, bucket, round((sum(x * x) - sum(x) * sum(x) / (SELECT m FROM total)) / ((SELECT m FROM total) - 1), 3) AS variance FROM raw GROUP BY q, bucket""")  # fmt: skip
def _variance(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    m = g.edges.count()
    quad = tuning.split_quadratics(g, g.edges, part_buckets(s, d, g, "brand"), exact.denominators(g, "clustering"), m, m)
    return tuning.variance_by_split(quad, (0.0, 0.2, 0.5)).select("q", "bucket", F.round("variance", 3).alias("variance"))


# --- low-degree filter

BETA = """, hist AS (SELECT d, count(*) AS n FROM deg GROUP BY d), beta AS (SELECT coalesce(max(d), 0) AS beta FROM (SELECT d, sum(d * d * n) OVER (ORDER BY d) AS work, (SELECT count(*) FROM deg) AS n FROM hist) WHERE work <= 40 * n)"""
LOWTRI = BETA + ", lt AS (SELECT a, b, c FROM tri JOIN deg x ON x.id = a JOIN deg y ON y.id = b JOIN deg z ON z.id = c CROSS JOIN beta WHERE (x.d <= beta OR y.d <= beta OR z.d <= beta))"


def _beta(g: Graph, factor: float = 40) -> int:
    return prefilter.low_degree_threshold(g, factor).first()["beta"]


query("f1_threshold", CPY + BETA + " SELECT beta FROM beta")(lambda s, d: prefilter.low_degree_threshold(cpy(s, d), 40))
query("f2_low_triangles", CPY + LOWTRI + " SELECT a, b, c FROM lt")(lambda s, d: prefilter.low_degree_triangles(g := cpy(s, d), _beta(g)))
query("f3_residual", CPY + BETA + " SELECT u, v FROM beta, edges JOIN deg a ON a.id = u JOIN deg b ON b.id = v WHERE a.d > beta AND b.d > beta")(lambda s, d: prefilter.residual_edges(g := cpy(s, d), _beta(g)))
query("f3_carried", CPY + LOWTRI + ", cc AS (SELECT id, count(*) AS n FROM (SELECT a AS id FROM lt UNION ALL SELECT b FROM lt UNION ALL SELECT c FROM lt) GROUP BY id) SELECT id, n FROM cc JOIN deg USING (id), beta WHERE d > beta")(
    lambda s, d: exact.corner_counts(prefilter.low_degree_triangles(g := cpy(s, d), b := _beta(g)), "n").join(exact.degrees(g).where(F.col("deg") > b), "id").select("id", "n")
)


@query("f4_combined", O.with_buckets("cpy", "brand") + " SELECT bucket, round(avg(alpha), 6) AS psi FROM prof JOIN buckets USING (id) GROUP BY bucket")
def _combined(s: SparkSession, d: str) -> DataFrame:
    """The exact part and the expectation of the sampled part rebuild the bucket means."""
    g = exact.indexed(cpy(s, d))
    b, w = part_buckets(s, d, g, "brand"), exact.denominators(g, "clustering")
    found = prefilter.apply_filter(g, b, w, _beta(g))
    rest = estimators.exact_edge_moments(found.rest, b, w, found.rest.edges.count(), SPLIT)
    return r6(found.known.join(rest, "bucket").select("bucket", (F.col("known") + F.col("mean")).alias("psi")))


# --- estimators end to end

for _c in O.W:
    query(f"a1_adaptive_bernstein_{_c}")(lambda s, d, c=_c: r6(adaptive_estimate(g := cpy(s, d), part_buckets(s, d, g, "brand"), c, 0.2, 0.01, "bernstein", work_factor=40, seed=SEED, large=None)))
    query(f"a2_adaptive_plugin_{_c}")(lambda s, d, c=_c: r6(adaptive_estimate(g := cpy(s, d), part_buckets(s, d, g, "brand"), c, 0.2, 0.01, "plugin", work_factor=40, seed=SEED, large=None)))
    for _f in (1, 2, 5):
        query(f"a6_fixed_{_f}permille_{_c}", O.with_buckets("cpy", "type") + O.NUMBER + O.bag(f"(SELECT ceil({_f} * 0.001::DOUBLE * m)::BIGINT FROM total)", SEED) + O.values("bag", "0.2", _c) + """
          SELECT bucket, size, round(coalesce(sum(x), 0) / (SELECT count(*) FROM bag), 6) AS f, (SELECT count(*) FROM bag) AS draws, 0.2::DOUBLE AS q FROM sizes LEFT JOIN (SELECT bucket, x FROM bag JOIN vals USING (u, v)) USING (bucket) GROUP BY bucket, size""")(
            lambda s, d, c=_c, f=_f: r6(fixed_size_estimate(g := cpy(s, d), part_buckets(s, d, g, "type"), c, fraction=f / 1000, q=SPLIT, seed=SEED))
        )
    query(f"a6_fixed_tuned_{_c}")(lambda s, d, c=_c: r6(fixed_size_estimate(g := cpy(s, d), part_buckets(s, d, g, "type"), c, fraction=0.1, seed=SEED)))
query("a4_per_bucket_eps")(lambda s, d: r6(adaptive_estimate(g := cpy(s, d), part_buckets(s, d, g, "type"), "closure", dict(enumerate((0.3, 0.3, 0.2, 0.2, 0.25, 0.25))), 0.05, work_factor=40, seed=SEED, large=None)))
query("a7_multipass", O.with_buckets("cpy", "type") + O.NUMBER + f""", dr AS (SELECT u, v, {O.hashed(SEED, "poisson", "u", "v")} AS x, 2000.0::DOUBLE / m AS r FROM edges, total), bag AS (
  SELECT u, v, (x >= exp(-r))::INT + (x >= exp(-r) * (1 + r))::INT + (x >= exp(-r) * (1 + r + r * r / 2))::INT + (x >= exp(-r) * (1 + r + r * r / 2 + r * r * r / 6))::INT + (x >= exp(-r) * (1 + r + r * r / 2 + r * r * r / 6 + r * r * r * r / 24))::INT AS copies FROM dr WHERE x >= exp(-r))"""
  + O.values("bag", "(1 / 3.0::DOUBLE)", "clustering") + " SELECT bucket, size, round(coalesce(sum(x * copies), 0) / (SELECT greatest(1, sum(copies)) FROM bag), 6) AS f FROM sizes LEFT JOIN (SELECT bucket, x, copies FROM bag JOIN vals USING (u, v)) USING (bucket) GROUP BY bucket, size")(lambda s, d: r6(multipass_stream_estimate((g := cpy(s, d)).edges, part_buckets(s, d, g, "type"), "clustering", DRAWS, seed=SEED)))
query("a10_exact_fallback", O.with_buckets("cpy", "type") + " SELECT bucket, count(*) AS size, round(avg(alpha), 6) AS f, 'exact' AS exit_reason FROM prof JOIN buckets USING (id) GROUP BY bucket")(
    lambda s, d: r6(adaptive_estimate(g := cpy(s, d), part_buckets(s, d, g, "type"), "clustering", 0.001, 0.01, work_factor=None, seed=SEED).select("bucket", "size", "f", "exit_reason"))
)


@query("a8_bucket_weighted_triangles", O.with_buckets("cpy", "type") + """, et AS (SELECT e.u, e.v, a.dst AS w FROM edges e JOIN adj a ON a.src = e.u JOIN adj b ON b.src = e.v AND b.dst = a.dst),
  we AS (SELECT et.*, (x.bucket = y.bucket)::INT + (y.bucket = z.bucket)::INT + (x.bucket = z.bucket)::INT AS g FROM et JOIN buckets x ON x.id = u JOIN buckets y ON y.id = v JOIN buckets z ON z.id = w)
  SELECT id, round(sum(a), 6) AS t FROM (SELECT w AS id, g * 0.6::DOUBLE AS a FROM we UNION ALL SELECT u, g * 0.2::DOUBLE FROM we UNION ALL SELECT v, g * 0.2::DOUBLE FROM we) GROUP BY id""")  # fmt: skip
def _own_weights(s: SparkSession, d: str) -> DataFrame:
    """Triangles weighted by how many of their corners share a bucket: expectation over all edges by node."""
    g = cpy(s, d)
    b = part_buckets(s, d, g, "type")
    found = estimators.bag_triangles(g, g.edges)
    for end in "uvw":
        found = found.join(b.select(F.col("id").alias(end), F.col("bucket").alias(f"b{end}")), end)
    weight = (F.col("bu") == F.col("bv")).cast("double") + (F.col("bv") == F.col("bw")).cast("double") + (F.col("bu") == F.col("bw")).cast("double")
    return r6(estimators.edge_shares(found, SPLIT, weight).groupBy(F.col("node").alias("id")).agg(F.sum("a").alias("t")))


# --- baselines

RANKS = """, ranked AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst % 64, dst) - 1 AS r FROM adj)"""


def _wish(stream: str, n: int) -> str:
    return f""", place AS (SELECT bucket, id, row_number() OVER (PARTITION BY bucket ORDER BY id % 64, id) - 1 AS r FROM buckets),
  drawn AS (SELECT w.bucket, ix, id FROM (SELECT bucket, i AS ix, least(floor({O.hashed(SEED, stream, "bucket", "i")} * size)::BIGINT, size - 1) AS r FROM sizes, range(0, {n}) t(i)) w JOIN place USING (bucket, r))"""


@query("wc_wedge_center", O.with_buckets("cpy", "type") + RANKS + _wish("center", 200) + f""", pk AS (SELECT bucket, ix, id, least(floor({O.hashed(SEED, "first", "bucket", "ix")} * d)::BIGINT, d - 1) AS r1,
  least(floor({O.hashed(SEED, "second", "bucket", "ix")} * (d - 1))::BIGINT, d - 2) AS r2 FROM drawn JOIN deg USING (id) WHERE d > 1), en AS (SELECT bucket, ix, x.dst AS x, y.dst AS y FROM pk JOIN ranked x ON x.src = id AND x.r = r1 JOIN ranked y ON y.src = id AND y.r = r2 + (r2 >= r1)::INT),
  hit AS (SELECT bucket, count(*) AS n FROM en JOIN edges ON u = least(x, y) AND v = greatest(x, y) GROUP BY bucket)
  SELECT bucket, size, 200::BIGINT AS draws, round(coalesce(n, 0) / 200.0::DOUBLE, 6) AS f FROM sizes LEFT JOIN hit USING (bucket)""")  # fmt: skip
def _wc(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    b = part_buckets(s, d, g, "type")
    return r6(baselines.wedge_center(g, b, b.select("bucket").distinct().withColumn("s", F.lit(200)), SEED))


@query("wh_wedge_headed", O.with_buckets("cpy", "type") + RANKS + _wish("head", 200) + f""", pk AS (SELECT bucket, ix, id, least(floor({O.hashed(SEED, "hop", "bucket", "ix")} * wh)::BIGINT, wh - 1) AS place FROM drawn JOIN head USING (id) WHERE wh > 0),
  st AS (SELECT src, dst, d - 1 AS more, sum(d - 1) OVER (PARTITION BY src ORDER BY dst % 64, dst) AS high FROM adj JOIN deg ON deg.id = dst),
  hop AS (SELECT bucket, ix, pk.id, st.dst AS mid, more FROM pk JOIN st ON st.src = pk.id AND place < high AND place >= high - more),
  ot AS (SELECT hop.*, o.r AS own, least(floor({O.hashed(SEED, "other", "bucket", "ix")} * more)::BIGINT, more - 1) AS r FROM hop JOIN ranked o ON o.src = mid AND o.dst = hop.id),
  en AS (SELECT bucket, ix, ot.id AS x, y.dst AS y FROM ot JOIN ranked y ON y.src = mid AND y.r = ot.r + (ot.r >= own)::INT),
  hit AS (SELECT bucket, count(*) AS n FROM en JOIN edges ON u = least(x, y) AND v = greatest(x, y) GROUP BY bucket)
  SELECT bucket, size, 200::BIGINT AS draws, round(coalesce(n, 0) / 200.0::DOUBLE, 6) AS f FROM sizes LEFT JOIN hit USING (bucket)""")  # fmt: skip
def _wh(s: SparkSession, d: str) -> DataFrame:
    g = cpy(s, d)
    b = part_buckets(s, d, g, "type")
    return r6(baselines.wedge_headed(g, b, b.select("bucket").distinct().withColumn("s", F.lit(200)), SEED))


MEANS = "SELECT bucket, count(*) AS size, round(avg(CASE WHEN d > 1 THEN 2 * coalesce(te.t, 0) / (d * (d - 1)) ELSE 0 END), 6) AS f FROM deg JOIN buckets USING (id) LEFT JOIN te USING (id) GROUP BY bucket"
query("ne_node_edge", O.with_buckets("cpy", "type") + O.NUMBER + O.bag(str(DRAWS), SEED) + O.values("bag", "(1 / 3.0::DOUBLE)", "clustering") + f", te AS (SELECT node AS id, sum(a) * (SELECT m FROM total) / {DRAWS} AS t FROM bag JOIN shares USING (u, v) GROUP BY node) " + MEANS)(
    lambda s, d: r6(baselines.node_edge_baseline((x := _bag(s, d, "type"))[0], x[3], x[1], DRAWS, x[2]))
)
_MINIMA = ", ".join(f"min((dst * {a} + {b}) % {baselines.PRIME}) AS h{i}" for i in range(16) for a, b in [baselines.hash_order(i)])
_AGREE = " + ".join(f"(p.h{i} = q.h{i})::INT" for i in range(16))
query("ks_sketch", O.with_buckets("cpy", "type") + f""", sg AS (SELECT src, count(*) AS d, {_MINIMA} FROM adj GROUP BY src), eh AS (SELECT u, v, ({_AGREE}) / 16.0::DOUBLE AS j, p.d + q.d AS dd FROM edges JOIN sg p ON p.src = u JOIN sg q ON q.src = v),
  te AS (SELECT id, sum(j / (1 + j) * dd / 2) AS t FROM (SELECT u AS id, j, dd FROM eh UNION ALL SELECT v, j, dd FROM eh) GROUP BY id) """ + MEANS)(lambda s, d: r6(baselines.sketch_baseline(g := cpy(s, d), part_buckets(s, d, g, "type"))))  # fmt: skip
query("tr_retained", O.with_buckets("cpy", "type") + O.NUMBER + f""", kp AS (SELECT * FROM numbered WHERE {O.hashed(SEED, "keep", "u", "v")} < 0.25), kb AS (SELECT eid, u AS a, v AS b FROM kp UNION ALL SELECT eid, v, u FROM kp),
  cl AS (SELECT n.u, n.v, p.b AS w FROM numbered n JOIN kb p ON p.a = n.u AND p.eid < n.eid JOIN kb q ON q.a = n.v AND q.b = p.b AND q.eid < n.eid),
  te AS (SELECT id, count(*) * 16.0::DOUBLE AS t FROM (SELECT u AS id FROM cl UNION ALL SELECT v FROM cl UNION ALL SELECT w FROM cl) GROUP BY id) """ + MEANS)(lambda s, d: r6(baselines.retained_edge_baseline(g := cpy(s, d), part_buckets(s, d, g, "type"), 0.25, SEED)))  # fmt: skip
query("xb_exact_baseline", O.with_buckets("cpy", "type") + " SELECT bucket, count(*) AS size, round(avg(alpha), 6) AS f FROM prof JOIN buckets USING (id) GROUP BY bucket")(lambda s, d: r6(baselines.exact_baseline(g := cpy(s, d), part_buckets(s, d, g, "type"))))
query("g1_capabilities", "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(repr(x) for x in row) + ")" for row in baselines.CAPABILITIES) + ") t(method, clustering, closure, adaptive, draws, per_draw)")(lambda s, d: baselines.capability_table(s))

# --- partitions

for _k in ("brand", "type", "segment", "deg", "log", "rnd", "one"):
    query(f"p_{_k}", O.with_buckets("cpy", _k) + " SELECT id, bucket, label FROM buckets")(lambda s, d, k=_k: part_buckets(s, d, cpy(s, d), k).select("id", "bucket", "label"))
query("p_core")(lambda s, d: part_buckets(s, d, cpy(s, d), "core"))
query("p_clu")(lambda s, d: part_buckets(s, d, cpy(s, d), "clu"))
query("p_sing", O.graph("cpy") + " SELECT id, (row_number() OVER (ORDER BY id % 64, id) - 1)::INTEGER AS bucket, id::VARCHAR AS label FROM nodes")(lambda s, d: P.singleton_buckets(cpy(s, d)))

# --- measures

for _n in ("cp", "cpy", "tr", "ev", "em", "pg", "cv", "ge"):
    query(f"m12_profile_{_n}", O.graph(_n) + " SELECT count(*) AS n, (sum(d) / 2)::BIGINT AS m, max(d) AS dmax, round(avg(alpha), 6) AS alpha, round(avg(phi), 6) AS phi FROM prof")(lambda s, d, n=_n: r6(exact.graph_profile(G.GRAPHS[n](s, d))))
query("m12_profile_dc")(lambda s, d: r6(exact.graph_profile(G.similar_documents(s, d))))
query("wk1_profiles", "SELECT graph, n, m, dmax, alpha, phi FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS graph, * FROM ({O.graph(n)} SELECT count(*) AS n, (sum(d) / 2)::BIGINT AS m, max(d) AS dmax, round(avg(alpha), 6) AS alpha, round(avg(phi), 6) AS phi FROM prof)" for n in ("cpy", "ev", "ge")) + ")")(
    lambda s, d: r6(X.profiles(s, d, ("cpy", "ev", "ge")))
)


def _errors(s: SparkSession, d: str) -> DataFrame:
    g, bag, m, b = _bag(s, d, "type")
    w, out = exact.denominators(g, "clustering"), None
    for run, low in ((0, 0), (1, 1000)):
        part = bag.where((F.col("ix") >= low) & (F.col("ix") < low + 1000))
        row = estimators.bucket_means(estimators.edge_bucket_values(g, part, b, w, m, SPLIT), b, 1000).withColumn("run", F.lit(run))
        out = row if out is None else out.unionByName(row)
    return measures.bucket_error(out, exact.exact_bucket_means(g, b, "clustering"))


ERRORS = O.with_buckets("cpy", "type") + O.NUMBER + O.bag(str(DRAWS), SEED) + O.values("bag", "0.2", "clustering") + """, psi AS (SELECT bucket, avg(alpha) AS psi FROM prof JOIN buckets USING (id) GROUP BY bucket),
  fe AS (SELECT run, sizes.bucket, coalesce(sum(x), 0) / 1000 AS f FROM sizes CROSS JOIN (SELECT unnest([0, 1]) AS run) LEFT JOIN (SELECT ix, bucket, x FROM bag JOIN vals USING (u, v)) y ON y.bucket = sizes.bucket AND ix // 1000 = run GROUP BY run, sizes.bucket),
  er AS (SELECT run, bucket, abs(f - psi) AS err FROM fe JOIN psi USING (bucket))"""  # fmt: skip
query("m1_bucket_error", ERRORS + " SELECT run, bucket, round(err, 6) AS err FROM er")(lambda s, d: r6(_errors(s, d)))
query("m2_max_error", ERRORS + " SELECT bucket, round(max(err), 6) AS max_err FROM er GROUP BY bucket")(lambda s, d: r6(measures.max_error(_errors(s, d))))
query("m3_sup_error", ERRORS + " SELECT round(max(err), 6) AS sup_err FROM er")(lambda s, d: r6(measures.sup_error(_errors(s, d))))
query("m4_mean_sup_error", ERRORS + " SELECT round(max(e), 6) AS avg_sup_err FROM (SELECT avg(err) AS e FROM er GROUP BY run)")(lambda s, d: r6(measures.mean_sup_error(_errors(s, d))))


def _runs(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    g = cpy(s, d)
    run = prepare(g, part_buckets(s, d, g, "type"), "clustering", 40)
    out = None
    for seed in (1, 2):
        row = adaptive_estimate(None, None, "clustering", 0.2, 0.01, seed=seed, run=run, large=None).withColumn("run", F.lit(seed))
        out = row if out is None else out.unionByName(row)
    return out, exact.exact_bucket_means(run.graph, run.buckets, "clustering")


query("m8_tightness")(lambda s, d: r6(measures.tightness(*_runs(s, d))))
query("m9_coverage")(lambda s, d: r6(measures.coverage(*_runs(s, d))))
query("m7_step_shares")(lambda s, d: X.breakdown(g := cpy(s, d), part_buckets(s, d, g, "type"), "clustering", 0.2, 0.01, 40))

# --- workloads


def _regime(s: SparkSession, d: str) -> DataFrame:
    """For each error target: how large the first round is against the cap, from the graph's own range and dimension bounds."""
    g = cpy(s, d)
    b = part_buckets(s, d, g, "type")
    m, w = g.edges.count(), exact.denominators(g, "clustering")
    top = bounds.range_bounds(g, b, w, m, SPLIT).agg(F.max("r").alias("r")).first()["r"]
    zeta = bounds.dimension_bound(bounds.spread_sup(g, b).first()["chi"], SPLIT)
    k = b.select("bucket").distinct().count()
    rows = [(e, float(top), zeta, *C.regime(top, e, k, 0.01, zeta)) for e in (0.2, 0.075, 0.01)]
    return r6(s.createDataFrame(rows, "eps double, r double, zeta int, first_share double, kind string"))


def _costs(s: SparkSession, d: str) -> DataFrame:
    """Rows that each step handles, from the sizes and bounds of the graph itself."""
    g = cpy(s, d)
    b = part_buckets(s, d, g, "brand")
    at = exact.graph_profile(g).first()
    top = bounds.range_bounds(g, b, exact.denominators(g, "clustering"), at["m"], SPLIT).agg(F.max("r").alias("r")).first()["r"]
    zeta = bounds.dimension_bound(bounds.spread_sup(g, b).first()["chi"], SPLIT)
    k = b.select("bucket").distinct().count()
    first = C.sample_start(top, 0.075, k, C.budget_of_round(0, 0.01))
    return r6(s.createDataFrame(C.cost_model(at["n"], at["m"], k, at["dmax"], first, float(top), 0.075, 0.01, zeta), "step string, rows double"))


def _run(s: SparkSession, d: str, kind: str, coefficient: str = "clustering", factor: float | None = 40):
    g = cpy(s, d)
    return prepare(g, part_buckets(s, d, g, kind), coefficient, factor)


FRACTIONS, SEEDS, TEN = (0.001, 0.002, 0.005, 0.01, 0.05, 0.1), (1, 2, 3, 4, 5), tuple(range(1, 11))


def _arms(s: SparkSession, d: str, graphs: Sequence[str], kinds: Sequence[str], coefficients: Sequence[str], arm) -> DataFrame:
    """The rows of ``arm(run, coefficient)`` for each graph, partition and coefficient."""
    out = None
    for graph in graphs:
        g = G.GRAPHS[graph](s, d)
        g = Graph(g.nodes, written(g.edges, "arm"))
        for kind in kinds:
            buckets = X.part_buckets(s, d, g, kind)
            for c in coefficients:
                row = arm(prepare(g, buckets, c, None), c).select(F.lit(graph).alias("graph"), F.lit(kind).alias("part"), F.lit(c).alias("coef"), "*")
                out = row if out is None else out.unionByName(row)
    return out


for _c in O.W:
    query(f"wk2_fixed_fraction_{_c}")(lambda s, d, c=_c: _arms(s, d, ("cpy",), ("deg", "log", "core"), (c,), lambda run, c: X.fixed_fraction(run, c, FRACTIONS, SEEDS)))
    for _g in ("cp", "tr"):
        query(f"wk2_fixed_fraction_{_c}_{_g}")(lambda s, d, c=_c, g=_g: _arms(s, d, (g,), ("deg",), (c,), lambda run, c: X.fixed_fraction(run, c, FRACTIONS, SEEDS)))
    query(f"wk3_equal_guarantee_{_c}")(lambda s, d, c=_c: X.equal_guarantee(_run(s, d, "type", c), c, 0.075, 0.01, SEEDS[:3]))
    query(f"wk5_q_grid_{_c}")(lambda s, d, c=_c: _arms(s, d, ("cpy", "em"), ("deg", "log"), (c,), lambda run, c: X.q_grid(run, c, X.Q_GRID, (0.0001, 0.001, 0.01), TEN)))
query("wk4_breakdown")(lambda s, d: X.breakdown(g := cpy(s, d), part_buckets(s, d, g, "deg"), "clustering", 0.2, 0.01, 40))
query("wk6_q_quality")(lambda s, d: _arms(s, d, ("cpy", "em"), ("deg",), tuple(O.W), lambda run, c: X.q_quality(run, c, X.Q_GRID, TEN, 0.01)))



def _labels(s: SparkSession, d: str, kind: str) -> DataFrame:
    part = G.read(s, d, "part")
    if kind == "type":
        return part.select(F.col("p_partkey").alias("id"), F.col("p_type").alias("label"))
    nodes = Graph(part.select(F.col("p_partkey").alias("id")), part.select(F.col("p_partkey").alias("u"), F.col("p_partkey").alias("v")).limit(0))
    return X.segment_buckets(s, d, nodes)


SNAP = """WITH yl AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem), ye AS (SELECT year(o_orderdate)::INTEGER AS y, a.p AS u, b.p AS v FROM yl a JOIN yl b ON a.o = b.o AND a.p < b.p JOIN orders ON o_orderkey = a.o),
{win}, adj AS (SELECT win, u AS src, v AS dst FROM we UNION ALL SELECT win, v, u FROM we), deg AS (SELECT win, src AS id, count(*) AS d FROM adj GROUP BY win, src), head AS (SELECT adj.win, src AS id, sum(d - 1) AS wh FROM adj JOIN deg ON deg.win = adj.win AND deg.id = dst GROUP BY adj.win, src),
  tri AS (SELECT a.win, a.u AS a, a.v AS b, b.v AS c FROM we a JOIN we b ON a.win = b.win AND a.v = b.u JOIN we x ON x.win = a.win AND x.u = a.u AND x.v = b.v), nt AS (SELECT win, id, count(*) AS t FROM (SELECT win, a AS id FROM tri UNION ALL SELECT win, b FROM tri UNION ALL SELECT win, c FROM tri) GROUP BY win, id),
  prof AS (SELECT deg.win, deg.id, d, CASE WHEN d > 1 THEN 2.0::DOUBLE * coalesce(t, 0) / (d * (d - 1)) ELSE 0 END AS alpha, CASE WHEN wh > 0 THEN 2.0::DOUBLE * coalesce(t, 0) / wh ELSE 0 END AS phi FROM deg JOIN head USING (win, id) LEFT JOIN nt USING (win, id)),
  mean AS (SELECT win, p_type AS community, count(*) AS size, avg(alpha) AS alpha, avg(phi) AS phi FROM prof JOIN part ON p_partkey = id GROUP BY win, p_type)"""
SNAP_MEANS = " SELECT win, community, size, round(alpha, 6) AS alpha, round(phi, 6) AS phi, round(alpha - lag(alpha) OVER w, 6) AS delta_alpha, round(phi - lag(phi) OVER w, 6) AS delta_phi FROM mean WINDOW w AS (PARTITION BY community ORDER BY win)"
YEARLY = SNAP.format(win="we AS (SELECT DISTINCT y AS win, u, v FROM ye)")
SLIDING = SNAP.format(win="we AS (SELECT DISTINCT win, u, v FROM (SELECT y AS win, u, v FROM ye UNION ALL SELECT y - 1, u, v FROM ye) WHERE win BETWEEN (SELECT min(year(o_orderdate)) FROM orders) AND (SELECT max(year(o_orderdate)) - 1 FROM orders))")
query("wk7_snapshots", YEARLY + SNAP_MEANS)(lambda s, d: r6(X.snapshots(X.snapshot_profile(X.snapshot_edges(s, d)), _labels(s, d, "type"))))
query("wk7_sliding", SLIDING + SNAP_MEANS)(lambda s, d: r6(X.snapshots(X.snapshot_profile(X.snapshot_edges(s, d, 2)), _labels(s, d, "type"))))
query("wk7_estimates")(lambda s, d: r6(X.snapshot_estimates(s, d, range(1995, 2002), "type", "clustering")))
query("wk8_induced", O.with_buckets("cpy", "segment") + """, ie AS (SELECT a.label AS community, u, v FROM edges JOIN buckets a ON a.id = u JOIN buckets b ON b.id = v WHERE a.bucket = b.bucket), nn AS (SELECT label AS community, count(*) AS nodes FROM buckets GROUP BY label), ne AS (SELECT community, count(*) AS edges FROM ie GROUP BY community),
  tr2 AS (SELECT community, count(*) AS triangles FROM (SELECT a.community FROM ie a JOIN ie b ON a.v = b.u JOIN ie x ON x.u = a.u AND x.v = b.v) GROUP BY community)
  SELECT community, nodes, coalesce(edges, 0) AS edges, round(CASE WHEN nodes > 1 THEN 2.0::DOUBLE * coalesce(edges, 0) / (nodes * (nodes - 1)) ELSE 0 END, 6) AS density, coalesce(triangles, 0) AS triangles FROM nn LEFT JOIN ne USING (community) LEFT JOIN tr2 USING (community)""")(
    lambda s, d: r6(X.induced(g := cpy(s, d), part_buckets(s, d, g, "segment")))
)
query("wk8_components", O.with_buckets("cpy", "segment").replace("WITH ", "WITH RECURSIVE ", 1) + """, ia AS (SELECT src, dst FROM adj JOIN buckets a ON a.id = src JOIN buckets b ON b.id = dst WHERE a.bucket = b.bucket),
  reach AS (SELECT id, id AS root FROM nodes UNION SELECT dst, root FROM reach JOIN ia ON src = id WHERE dst > root), roots AS (SELECT id, min(root) AS root FROM reach GROUP BY id)
  SELECT community, count(*) AS components, max(n) AS largest FROM (SELECT label AS community, root, count(*) AS n FROM roots JOIN buckets USING (id) GROUP BY label, root) GROUP BY community""")(lambda s, d: X.induced_components(g := cpy(s, d), part_buckets(s, d, g, "segment")))
query("wk9_degree_profile", YEARLY + " SELECT win, p_type AS community, floor(log2(greatest(d, 1)))::INTEGER AS deg_bin, count(*) AS nodes, round(avg(alpha), 6) AS mean_alpha FROM prof JOIN part ON p_partkey = id GROUP BY ALL")(
    lambda s, d: r6(X.degree_profile(X.snapshot_profile(X.snapshot_edges(s, d)), _labels(s, d, "type")))
)
query("wk10_other_partitions")(lambda s, d: _arms(s, d, ("cpy",), ("rnd", "clu"), tuple(O.W), lambda run, c: X.fixed_fraction(run, c, FRACTIONS, SEEDS)))
query("wk11_nonuniform_eps")(lambda s, d: r6(X.nonuniform_eps(prepare(g := cpy(s, d), X.two_buckets(g), "closure", 40), "closure", 0.2, {0: 0.2, 1: 0.1}, 0.05)))
query("wk12_attained_width")(lambda s, d: r6(_runs(s, d)[0].groupBy("run").agg(F.max(F.col("eps_target") / F.col("eps_hat")).alias("requested_over_attained"))))
query("wk13_ablations")(lambda s, d: r6(X.ablations(g := cpy(s, d), part_buckets(s, d, g, "type"), "closure", 0.3, 0.05)))
query("wk14_community_quality")(lambda s, d: r6(X.community_quality(g := cpy(s, d), {"rnd": P.random_buckets(g, 10), "clu": P.cluster_buckets(g, 10)})))
query("wk15_features", O.with_buckets("cpy", "type") + """, bm AS (SELECT bucket, avg(alpha) AS ma, avg(phi) AS mp FROM prof JOIN buckets USING (id) GROUP BY bucket)
  SELECT id, [d::DOUBLE, round(alpha, 6), round(phi, 6), round(ma, 6), round(mp, 6)] AS features FROM prof JOIN buckets USING (id) JOIN bm USING (bucket)""")(lambda s, d: X.features(g := cpy(s, d), part_buckets(s, d, g, "type")))

# --- the operators on the graph of the whole table, and the estimators and bounds on the hub graph

WHOLE = re.compile(r"(?:x\d+|s\d|e\d|b\d|c3|c6|q\d|f\d|a\d+|wc|wh|ne|ks|tr|xb|p)_")
HUBS = re.compile(r"(?:e\d|b\d|c3|c6|q\d|a1|a2|a6|a7)_")
NO_GRAPH = {"b4_dimension", "b5_dimension_by_split", "x7_triangle_count_cp"}


def _on(graph: str, run: Query) -> Query:
    def switched(spark: SparkSession, sf_dir: str) -> DataFrame:
        token = GRAPH.set(graph)
        try:
            return run(spark, sf_dir)
        finally:
            GRAPH.reset(token)

    return switched


def _sql_on(graph: str, sql: str) -> str | None:
    """The SQL of a query on another graph, or None where it does not name the graph in the usual way."""
    for kind in O.LABELS:
        sql = sql.replace(O.with_buckets("cpy", kind), O.with_buckets(graph, "deg" if graph == "tr" else kind))
    sql = sql.replace(O.graph("cpy"), O.graph(graph))
    return None if O.GRAPHS["cpy"] in sql else sql


for _name in [n for n in QUERIES if n not in NO_GRAPH]:
    for _graph, _which in (("cp", WHOLE), ("tr", HUBS)):
        if _which.match(_name):
            QUERIES[f"{_name}_{_graph}"] = _on(_graph, QUERIES[_name])
            if _name in ORACLE_SQL and (_text := _sql_on(_graph, ORACLE_SQL[_name])):
                ORACLE_SQL[f"{_name}_{_graph}"] = _text
