"""The experiment workloads on graphs of the given tables."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence
from itertools import count

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from localcoef.model import Graph
from localcoef.operators.baselines import wedge_baseline
from localcoef.operators.exact import degrees, exact_bucket_means, graph_profile, local_coefficients, node_profile, triangles
from localcoef.operators.measures import bucket_error, coverage, max_error, mean_sup_error, step_shares, sup_error, timed, tuning_report
from localcoef.operators.sampling import BROADCAST_DRAWS, uniform_of
from localcoef.operators.tuning import edge_lines, line_sums, split_quadratics, tuned_from_sums, variance_by_split
from localcoef.plans.estimate import Run, adaptive_estimate, fixed_size_estimate, prepare
from localcoef.plans.store import written
from localcoef.sources import partitions as P
from localcoef.sources.graphs import GRAPHS, read, year_lines

#: Own grid of split weights.
Q_GRID = (0.0, 0.01, 0.05, 0.1, 0.2, 0.3, 1 / 3, 0.4, 0.5)


def part_buckets(spark: SparkSession, sf_dir: str, g: Graph, kind: str) -> DataFrame:
    """The partitions that the workloads use, by name."""
    part = read(spark, sf_dir, "part")
    made: dict[str, Callable[[], DataFrame]] = {
        "brand": lambda: P.metadata_buckets(g, part, "p_partkey", "p_brand"),
        "type": lambda: P.metadata_buckets(g, part, "p_partkey", "p_type"),
        "segment": lambda: segment_buckets(spark, sf_dir, g),
        "deg": lambda: P.degree_buckets(g, 25),
        "log": lambda: P.log_degree_buckets(g),
        "core": lambda: P.core_buckets(g, 30),
        "rnd": lambda: P.random_buckets(g, 30),
        "clu": lambda: P.cluster_buckets(g, 10),
        "one": lambda: P.single_bucket(g),
    }
    return made[kind]()


def segment_buckets(spark: SparkSession, sf_dir: str, g: Graph) -> DataFrame:
    """Parts by the market segment whose orders hold them most often."""
    orders = read(spark, sf_dir, "orders").join(read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    activity = read(spark, sf_dir, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return P.majority_buckets(g, activity, "l_partkey", "c_mktsegment")


def profiles(spark: SparkSession, sf_dir: str, names: Sequence[str]) -> DataFrame:
    """The statistics of several graphs."""
    out = None
    for name in names:
        row = graph_profile(GRAPHS[name](spark, sf_dir)).select(F.lit(name).alias("graph"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _stack(frames: list[tuple[int, DataFrame]]) -> DataFrame:
    out = None
    for seed, df in frames:
        row = df.withColumn("run", F.lit(seed))
        out = row if out is None else out.unionByName(row)
    return out


def run_sums(run: Run, sizes: Sequence[int], seeds: Sequence[int], pilot: int = 500) -> tuple[DataFrame, float]:
    """(stream, run, draws, bucket, b, s, bb, bs, ss) of all runs, bag sizes and pilots in one job, and its seconds.

    A draw's value is a line in the split weight, so these sums give the estimate of every run at every split weight;
    a shorter bag of a run is the begin of a longer one. The bags are those of ``draw_indexed``.
    """
    began = time.perf_counter()
    spark, most, c = run.buckets.sparkSession, max(sizes), min(pilot, max(2, run.m))
    bags = None
    for stream, n in (("main", most), ("pilot", c)):
        names = F.element_at(F.array(*[F.lit(x) for x in seeds]), (F.floor(F.col("id") / n) + 1).cast("int"))
        draws = spark.range(n * len(seeds)).select(F.lit(stream).alias("stream"), names.alias("run"), (F.col("id") % n).alias("ix"))
        draws = draws.withColumn("eid", F.least(F.floor(uniform_of(F.col("run"), stream, F.col("ix")) * run.m).cast("long"), F.lit(run.m - 1)))
        bags = draws if bags is None else bags.unionByName(draws)
    few = (most + c) * len(seeds) <= BROADCAST_DRAWS
    bag = written(run.numbered.join(F.broadcast(bags) if few else bags, "eid").drop("eid"), "bags")
    lines = bag.join(edge_lines(run.rest, bag, run.buckets, run.w, run.m, few), ["u", "v"])
    size = F.array(*[F.lit(x) for x in sorted(set(sizes))])
    long_enough = F.when(F.col("stream") == "pilot", F.array(F.lit(c))).otherwise(F.filter(size, lambda x: x > F.col("ix")))
    out = written(line_sums(lines.withColumn("draws", F.explode(long_enough)), "stream", "run", "draws"), "sums")
    return out, time.perf_counter() - began


def tuned_by_run(run: Run, sums: DataFrame, seeds: Sequence[int], pilot: int = 500) -> dict[int, float]:
    """Each run's split weight from its pilot; a row for each run and bucket comes to the driver."""
    c, rows = min(pilot, max(2, run.m)), {s: [] for s in seeds}
    for r in sums.where("stream = 'pilot'").collect():
        rows[r["run"]].append(r)
    return {s: tuned_from_sums(found, c) for s, found in rows.items()}


def _estimates(run: Run, sums: DataFrame, sizes: Sequence[int], splits: DataFrame) -> DataFrame:
    """(run, draws, q, bucket, f) for the (run, q) of ``splits``; a bucket that no draw touches has its known part alone."""
    spark = run.buckets.sparkSession
    known = spark.createDataFrame([(j, float(run.known[j])) for j in run.sizes], "bucket int, known double")
    main = sums.where("stream = 'main'")
    every = spark.createDataFrame([(x,) for x in sorted(set(sizes))], "draws int").crossJoin(F.broadcast(splits)).crossJoin(F.broadcast(known))
    met = every.join(main.select("run", "draws", "bucket", "b", "s"), ["run", "draws", "bucket"], "left")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0.0))
    return met.select("run", "draws", "q", "bucket", (F.col("known") + (zero("b") + F.col("q") * zero("s")) / F.col("draws")).alias("f"))


def _sizes(run: Run, fractions: Sequence[float]) -> dict[float, int]:
    return {f: max(1, math.ceil(f * run.m)) for f in fractions}


def fixed_fraction(run: Run, coefficient: str, fractions: Sequence[float], seeds: Sequence[int], q: float | None = None) -> DataFrame:
    """(fraction, draws, bucket, psi, max_err, sup_err, avg_sup_err, avg_seconds) of the fixed-size variant over several runs.

    All runs are one job; ``avg_seconds`` is its time over the number of runs.
    """
    truth = written(exact_bucket_means(run.graph, run.buckets, coefficient), "truth")
    sizes = _sizes(run, fractions)
    sums, seconds = run_sums(run, list(sizes.values()), seeds)
    tuned = tuned_by_run(run, sums, seeds) if q is None else dict.fromkeys(seeds, q)
    spark = run.buckets.sparkSession
    every = written(_estimates(run, sums, list(sizes.values()), spark.createDataFrame([(s, float(x)) for s, x in tuned.items()], "run int, q double")), "estimates")
    out = None
    for fraction, s in sizes.items():
        errors = bucket_error(every.where(F.col("draws") == s), truth)
        rows = max_error(errors).join(truth, "bucket").crossJoin(F.broadcast(sup_error(errors))).crossJoin(F.broadcast(mean_sup_error(errors)))
        rows = rows.select(F.lit(fraction).alias("fraction"), F.lit(s).cast("long").alias("draws"), "bucket", "psi", "max_err", "sup_err", "avg_sup_err", F.lit(seconds / len(seeds)).alias("avg_seconds"))
        out = rows if out is None else out.unionByName(rows)
    return out


def equal_guarantee(run: Run, coefficient: str, eps: float, eta: float, seeds: Sequence[int], bounds: Sequence[str] = ("plugin", "bernstein"), limit: float = 300.0) -> DataFrame:
    """(method, avg_err, max_avg_err, sup_err, covered, draws, eps_hat, seconds): wedge sampling gets the half-widths that the adaptive run attained; the ratios are the baseline's figures over ours."""
    spark, k = run.buckets.sparkSession, len(run.sizes)
    truth = written(exact_bucket_means(run.graph, run.buckets, coefficient), "truth")
    ours: dict[str, list] = {b: [] for b in bounds} | {"wedge": []}
    took: dict[str, float] = dict.fromkeys(ours, 0.0)
    for seed in seeds:
        for b in bounds:
            df, seconds = timed(lambda b=b, seed=seed: written(adaptive_estimate(None, None, coefficient, eps, eta, b, seed=seed, run=run, large=None), "adaptive"))
            ours[b].append((seed, df.select("bucket", "f", "eps_hat", "draws")))
            took[b] += seconds
        if took["wedge"] < limit:
            # a bucket that is known exactly has width 0, which no number of draws attains; there the target is asked for
            widths = ours[bounds[0]][-1][1].select("bucket", F.when(F.col("eps_hat") > 0, F.col("eps_hat")).otherwise(F.lit(eps)).alias("eps"))
            df, seconds = timed(lambda widths=widths, seed=seed: written(wedge_baseline(run.graph, run.buckets, coefficient, widths, k, eta, seed).join(widths, "bucket"), "wedge"))
            ours["wedge"].append((seed, df.select("bucket", "f", F.col("eps").alias("eps_hat"), "draws")))
            took["wedge"] += seconds
    out = None
    for method, frames in ours.items():
        every = _stack(frames)
        errors = bucket_error(every, truth)
        draws = every.groupBy("run").agg((F.sum("draws") if method == "wedge" else F.max("draws")).alias("d"), F.max("eps_hat").alias("e")).agg(F.avg("d").alias("draws"), F.avg("e").alias("eps_hat"))
        rows = errors.agg(F.avg("err").alias("avg_err")).crossJoin(mean_sup_error(errors).withColumnRenamed("avg_sup_err", "max_avg_err")).crossJoin(sup_error(errors)).crossJoin(coverage(every, truth).select("covered")).crossJoin(draws)
        rows = rows.select(F.lit(method).alias("method"), "avg_err", "max_avg_err", "sup_err", "covered", "draws", "eps_hat", F.lit(took[method] / len(frames)).alias("seconds"))
        out = rows if out is None else out.unionByName(rows)
    out = written(out, "methods")
    wedge = out.where("method = 'wedge'").select(F.col("avg_err").alias("e"), F.col("seconds").alias("t"), F.col("draws").alias("d"))
    gains = [(F.col(x) / F.when(F.col(y) > 0, F.col(y))).alias(n) for x, y, n in (("e", "avg_err", "error_ratio"), ("t", "seconds", "time_ratio"), ("d", "draws", "draw_ratio"))]
    return out.crossJoin(F.broadcast(wedge)).select(*out.columns, *gains)


def breakdown(g: Graph, buckets: DataFrame, coefficient: str, eps: float, eta: float, work_factor: float = 10) -> DataFrame:
    """(step, seconds, share) of the four steps."""
    run = prepare(g, buckets, coefficient, work_factor)
    adaptive_estimate(None, None, coefficient, eps, eta, run=run).count()
    return buckets.sparkSession.createDataFrame(step_shares(run.seconds), "step string, seconds double, share double")


def q_grid(run: Run, coefficient: str, grid: Sequence[float], fractions: Sequence[float], seeds: Sequence[int], sums: DataFrame | None = None) -> DataFrame:
    """(fraction, draws, q, sup_err): all runs, sizes and split weights from one table of sums."""
    truth = written(exact_bucket_means(run.graph, run.buckets, coefficient), "truth")
    spark, sizes = run.buckets.sparkSession, _sizes(run, fractions)
    sums = run_sums(run, list(sizes.values()), seeds)[0] if sums is None else sums
    splits = spark.createDataFrame([(s, float(q)) for s in seeds for q in grid], "run int, q double")
    errors = _estimates(run, sums, list(sizes.values()), splits).join(truth.select("bucket", "psi"), "bucket")
    sup = errors.groupBy("draws", "q").agg(F.max(F.abs(F.col("f") - F.col("psi"))).alias("sup_err"))
    names = spark.createDataFrame([(f, s) for f, s in sizes.items()], "fraction double, draws int")
    return sup.join(F.broadcast(names), "draws").select("fraction", F.col("draws").cast("long").alias("draws"), "q", "sup_err")


def q_quality(run: Run, coefficient: str, grid: Sequence[float], seeds: Sequence[int], fraction: float, pilot: int = 500) -> DataFrame:
    """(q_mean, q_sd, best_grid_q, tuned_variance, best_variance): the tuned weights against the grid."""
    sums, _ = run_sums(run, list(_sizes(run, [fraction]).values()), seeds, pilot)
    tuned = list(tuned_by_run(run, sums, seeds, pilot).values())
    errors = {r["q"]: r["sup_err"] for r in q_grid(run, coefficient, grid, [fraction], seeds, sums).collect()}
    report = tuning_report(tuned, errors)
    full = written(split_quadratics(run.rest, run.rest.edges, run.buckets, run.w, run.m, run.m), "quadratics")
    worst = {r["q"]: r["v"] for r in variance_by_split(full, [*grid, report["q_mean"]]).groupBy("q").agg(F.max("variance").alias("v")).collect()}
    row = [(report["q_mean"], report["q_sd"], report["best_grid_q"], worst[report["q_mean"]], min(worst[float(q)] for q in grid))]
    return run.buckets.sparkSession.createDataFrame(row, "q_mean double, q_sd double, best_grid_q double, tuned_variance double, best_variance double")


def snapshot_edges(spark: SparkSession, sf_dir: str, span: int = 1) -> DataFrame:
    """(win, u, v): parts that share an order, for each window of so many years; a pair counts once a window."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"))
    rows = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = rows.withColumnRenamed("l_partkey", "u"), rows.withColumnRenamed("l_partkey", "v")
    pairs = a.join(b, "l_orderkey").where("u < v").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    if span == 1:
        return pairs.select(F.col("y").alias("win"), "u", "v").distinct()
    bounds = orders.agg(F.min("y").alias("low"), F.max("y").alias("high")).first()
    wins = F.explode(F.sequence(F.greatest(F.col("y") - span + 1, F.lit(bounds["low"])), F.least(F.col("y"), F.lit(bounds["high"] - span + 1))))
    return pairs.where(F.lit(bounds["high"] - bounds["low"] + 1 >= span)).select(wins.alias("win"), "u", "v").distinct()


def snapshot_profile(edges: DataFrame) -> DataFrame:
    """(win, id, deg, alpha, phi) of every snapshot in one job: the exact layer with the window in every key."""
    both = edges.select("win", F.inline(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))))
    deg = both.groupBy("win", F.col("src").alias("id")).agg(F.count("*").alias("deg"))
    d = lambda x: deg.select("win", F.col("id").alias(x), F.col("deg").alias(f"d{x}"))
    placed = edges.join(d("u"), ["win", "u"]).join(d("v"), ["win", "v"])
    up = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    out = placed.select("win", F.when(up, F.col("u")).otherwise(F.col("v")).alias("src"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("dst"))
    pairs = out.withColumnRenamed("dst", "x").join(out.withColumnRenamed("dst", "y"), ["win", "src"]).where("x < y")
    closed = pairs.join(edges.select("win", F.col("u").alias("x"), F.col("v").alias("y")), ["win", "x", "y"], "left_semi")
    t = closed.select("win", F.explode(F.array("src", "x", "y")).alias("id")).groupBy("win", "id").agg(F.count("*").alias("t"))
    heads = both.join(d("dst"), ["win", "dst"]).groupBy("win", F.col("src").alias("id")).agg(F.sum(F.col("ddst") - 1).alias("wh"))
    full = deg.join(heads, ["win", "id"]).join(t, ["win", "id"], "left").withColumn("t", F.coalesce("t", F.lit(0)))
    alpha = F.when(F.col("deg") > 1, 2 * F.col("t") / (F.col("deg") * (F.col("deg") - 1))).otherwise(F.lit(0.0))
    return full.select("win", "id", "deg", alpha.alias("alpha"), F.when(F.col("wh") > 0, 2 * F.col("t") / F.col("wh")).otherwise(F.lit(0.0)).alias("phi"))


def snapshots(profile: DataFrame, labels: DataFrame) -> DataFrame:
    """(win, community, size, alpha, phi, delta_alpha, delta_phi): averages, and their change since the window before."""
    means = profile.join(labels.select("id", F.col("label").alias("community")), "id").groupBy("win", "community").agg(F.count("*").alias("size"), F.avg("alpha").alias("alpha"), F.avg("phi").alias("phi"))
    w = Window.partitionBy("community").orderBy("win")
    return means.select("win", "community", "size", "alpha", "phi", (F.col("alpha") - F.lag("alpha").over(w)).alias("delta_alpha"), (F.col("phi") - F.lag("phi").over(w)).alias("delta_phi"))


def snapshot_estimates(spark: SparkSession, sf_dir: str, years: Sequence[int], kind: str, coefficient: str, fraction: float = 0.2, seed: int = 0) -> DataFrame:
    """(win, bucket, size, f, draws, q) by the fixed-size variant, a snapshot after another."""
    from localcoef.sources.graphs import copart_year

    out = None
    for y in years:
        g = copart_year(spark, sf_dir, y)
        row = fixed_size_estimate(g, part_buckets(spark, sf_dir, g, kind), coefficient, fraction=fraction, seed=seed).select(F.lit(y).alias("win"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def induced(g: Graph, labels: DataFrame) -> DataFrame:
    """(community, nodes, edges, density, triangles): the subgraphs inside each bucket."""
    at = lambda x, c: labels.select(F.col("id").alias(x), F.col("label").alias(c))
    inside = g.edges.join(at("u", "cu"), "u").join(at("v", "cv"), "v").where("cu = cv").select("u", "v", F.col("cu").alias("community"))
    sizes = labels.groupBy(F.col("label").alias("community")).agg(F.count("*").alias("nodes"))
    edges = inside.groupBy("community").agg(F.count("*").alias("edges"))
    found = triangles(Graph(g.nodes, inside.select("u", "v"))).join(at("a", "community"), "a").groupBy("community").agg(F.count("*").alias("triangles"))
    full = sizes.join(edges, "community", "left").join(found, "community", "left").fillna(0, ["edges", "triangles"])
    return full.select("community", "nodes", "edges", F.when(F.col("nodes") > 1, 2 * F.col("edges") / (F.col("nodes") * (F.col("nodes") - 1))).otherwise(F.lit(0.0)).alias("density"), "triangles")


def induced_components(g: Graph, labels: DataFrame, rounds: int | None = None) -> DataFrame:
    """(community, components, largest): connected parts inside each bucket, by least labels over written rounds until none moves; more than ``rounds``, if given, are an error."""
    at = lambda x, c: labels.select(F.col("id").alias(x), F.col("label").alias(c))
    inside = g.edges.join(at("u", "cu"), "u").join(at("v", "cv"), "v").where("cu = cv").select("u", "v")
    adj = written(Graph(g.nodes, inside).adjacency, "inside")
    now = written(labels.select("id", F.col("id").alias("root")), "roots")
    for n in count():
        if n == rounds:
            raise RuntimeError(f"components have not settled in {rounds} rounds")
        near = adj.join(now.select(F.col("id").alias("dst"), "root"), "dst").groupBy(F.col("src").alias("id")).agg(F.min("root").alias("least"))
        new = now.join(near, "id", "left").select("id", "root", F.least("root", F.coalesce("least", "root")).alias("next"))
        jump = new.select("id", "root", "next").join(new.select(F.col("id").alias("next"), F.col("next").alias("far")), "next").select("id", F.least("next", "far").alias("next"), F.col("root").alias("was"))
        out = written(jump, "roots")
        moved = out.where("next <> was").limit(1).count()
        now = out.select("id", F.col("next").alias("root"))
        if not moved:
            break
    parts = now.join(labels.select("id", F.col("label").alias("community")), "id").groupBy("community", "root").agg(F.count("*").alias("n"))
    return parts.groupBy("community").agg(F.count("*").alias("components"), F.max("n").alias("largest"))


def degree_profile(profile: DataFrame, labels: DataFrame) -> DataFrame:
    """(win, community, deg_bin, nodes, mean_alpha): averages within strata of equal log-degree."""
    bins = F.floor(F.log2(F.greatest(F.col("deg"), F.lit(1)))).cast("int")
    return profile.join(labels.select("id", F.col("label").alias("community")), "id").groupBy("win", "community", bins.alias("deg_bin")).agg(F.count("*").alias("nodes"), F.avg("alpha").alias("mean_alpha"))


def two_buckets(g: Graph) -> DataFrame:
    """Nodes up to the median degree, and the others."""
    deg = degrees(g)
    middle = deg.agg(F.percentile("deg", 0.5).alias("mid"))
    return P.numbered(deg.crossJoin(F.broadcast(middle)).select("id", F.when(F.col("deg") <= F.col("mid"), "low").otherwise("top").alias("label")))


def nonuniform_eps(run: Run, coefficient: str, uniform: float, each: dict[int, float], eta: float, seed: int = 0) -> DataFrame:
    """(mode, bucket, eps_target, eps_hat, f) for one target for all and one for each."""
    names = ["bucket", "eps_target", "eps_hat", "f"]
    a = adaptive_estimate(None, None, coefficient, uniform, eta, seed=seed, run=run, large=None).select(F.lit("uniform").alias("mode"), *names)
    b = adaptive_estimate(None, None, coefficient, each, eta, seed=seed, run=run, large=None).select(F.lit("each").alias("mode"), *names)
    return a.unionByName(b)


def ablations(g: Graph, buckets: DataFrame, coefficient: str, eps: float, eta: float, work_factor: float = 40, seed: int = 0) -> DataFrame:
    """(variant, draws, range_bound, zeta, eps_hat, sup_err) with one part changed at a time."""
    plain, filtered = prepare(g, buckets, coefficient, None), prepare(g, buckets, coefficient, work_factor)
    truth = written(exact_bucket_means(plain.graph, plain.buckets, coefficient), "truth")
    k = len(plain.sizes)
    variants = {
        "full": (filtered, {}), "no_filter": (plain, {}), "bernstein": (filtered, {"bound": "bernstein"}), "zeta_log_k": (filtered, {"zeta": max(1, math.ceil(math.log(max(2, k))))}),
        "q_third": (filtered, {"q": 1 / 3}), "uncentered": (filtered, {"bound": "bernstein", "centered": False}), "tight_ranges": (filtered, {"tight": True}), "no_union": (filtered, {"union": False}),
    }
    out = None
    for name, (run, change) in variants.items():
        found = written(adaptive_estimate(None, None, coefficient, eps, eta, seed=seed, run=run, large=None, **change), "variant")
        row = found.join(truth, "bucket").agg(F.max("draws").alias("draws"), F.max("range_bound").alias("range_bound"), F.max("zeta").alias("zeta"), F.max("eps_hat").alias("eps_hat"), F.max(F.abs(F.col("f") - F.col("psi"))).alias("sup_err")).select(F.lit(name).alias("variant"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def community_quality(g: Graph, labelled: dict[str, DataFrame]) -> DataFrame:
    """(partition, bucket, size, psi): mean clustering of the buckets of several partitions."""
    psi = written(local_coefficients(g, "clustering"), "psi")
    out = None
    for name, buckets in labelled.items():
        row = psi.join(buckets.select("id", "bucket"), "id").groupBy("bucket").agg(F.count("*").alias("size"), F.avg("psi").alias("psi")).select(F.lit(name).alias("partition"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def features(g: Graph, buckets: DataFrame) -> DataFrame:
    """(id, features): degree, both coefficients, and the averages of the node's bucket, for learning."""
    node = node_profile(g).join(buckets.select("id", "bucket"), "id")
    means = node.groupBy("bucket").agg(F.avg("alpha").alias("ma"), F.avg("phi").alias("mp"))
    return node.join(F.broadcast(means), "bucket").select("id", F.array(*[F.round(F.col(c).cast("double"), 6) for c in ("deg", "alpha", "phi", "ma", "mp")]).alias("features"))


def yearly_lines(spark: SparkSession, sf_dir: str, years: Sequence[int]) -> DataFrame:
    """(win, lines): sizes of the snapshots' inputs."""
    out = None
    for y in years:
        row = year_lines(spark, sf_dir, y).agg(F.count("*").alias("lines")).select(F.lit(y).alias("win"), "lines")
        out = row if out is None else out.unionByName(row)
    return out
