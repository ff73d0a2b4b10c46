"""The adaptive estimator and its fixed-size variant: driver loops over one plan, with one row a bucket to the driver."""

from __future__ import annotations

import math
import time
from collections.abc import Mapping
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from localcoef.functions.concentration import bernstein_halfwidth, budget_of_round, check_unit, plugin_chunks, sample_cap, sample_start, variance_of_sums
from localcoef.model import Graph, bucket_sizes, check_coefficient
from localcoef.operators.bounds import dimension_bound, range_bounds, spread_sup
from localcoef.operators.estimators import edge_bucket_values, moments
from localcoef.operators.exact import denominators, exact_bucket_means
from localcoef.operators.prefilter import apply_filter, low_degree_threshold
from localcoef.operators.sampling import BROADCAST_DRAWS, draw_indexed, number_edges
from localcoef.operators.tuning import tune_split
from localcoef.plans.store import written

RESULT = (
    "bucket int, size long, f double, eps_target double, eps_hat double, lo double, hi double, lo01 double, hi01 double, "
    "draws long, rounds int, q double, range_bound double, zeta int, exit_reason string"
)


@dataclass
class Run:
    """A prepared input: written tables, the sampled graph, and the seconds of each step."""

    graph: Graph
    rest: Graph
    buckets: DataFrame
    w: DataFrame
    numbered: DataFrame
    m: int
    sizes: dict[int, int]
    known: dict[int, float]
    seconds: dict[str, float] = field(default_factory=dict)


def prepare(g: Graph, buckets: DataFrame, coefficient: str, work_factor: float | None = None) -> Run:
    """Writes the derived tables once, so that the rounds read them and do not work them out again."""
    began = time.perf_counter()
    check_coefficient(coefficient)
    g = Graph(written(g.nodes, "nodes"), written(g.edges, "edges"))
    buckets = written(buckets.select("id", F.col("bucket").cast("int").alias("bucket")), "buckets")
    w = written(denominators(g, coefficient), "wedges")
    sizes = {r["bucket"]: r["size"] for r in bucket_sizes(buckets).collect()}
    rest, known = g, dict.fromkeys(sizes, 0.0)
    if work_factor is not None:
        beta = low_degree_threshold(g, work_factor).first()["beta"]
        if beta > 0:
            found = apply_filter(g, buckets, w, beta)
            rest = Graph(g.nodes, written(found.rest.edges, "rest"))
            known = {r["bucket"]: r["known"] for r in found.known.collect()}
    numbered = written(number_edges(rest.edges), "numbered")
    rest = Graph(g.nodes, numbered.select("u", "v"))
    m = numbered.count()
    return Run(g, rest, buckets, w, numbered, m, sizes, known, {"filter": time.perf_counter() - began})


def _tuned(run: Run, q: float | None, pilot: int, seed: int) -> float:
    began = time.perf_counter()
    if q is None:
        c = min(pilot, max(2, run.m))
        bag = written(draw_indexed(run.numbered, run.m, c, seed, "pilot"), "pilot")
        q = tune_split(run.rest, bag, run.buckets, run.w, run.m, c, few=c <= BROADCAST_DRAWS)
    run.seconds["tuning"] = time.perf_counter() - began
    return q


def _values(run: Run, low: int, high: int, q: float, seed: int) -> DataFrame:
    bag = draw_indexed(run.numbered, run.m, high - low, seed, "main", low)
    return edge_bucket_values(run.rest, bag, run.buckets, run.w, run.m, q, few=high - low <= BROADCAST_DRAWS)


def _result(run: Run, rows: list[dict]) -> DataFrame:
    out = []
    for r in rows:
        lo, hi = r["f"] - r["eps_hat"], r["f"] + r["eps_hat"]
        out.append((r["bucket"], run.sizes[r["bucket"]], float(r["f"]), r["eps"], float(r["eps_hat"]), lo, hi, min(1.0, max(0.0, lo)), min(1.0, max(0.0, hi)), r["draws"], r["rounds"], r["q"], float(r["r"]), r["zeta"], r["why"]))
    return run.buckets.sparkSession.createDataFrame(out, RESULT)


def _targets(eps: float | Mapping[int, float], sizes: Mapping[int, int]) -> dict[int, float]:
    targets = {j: float(eps[j]) if isinstance(eps, Mapping) else float(eps) for j in sizes}
    for e in targets.values():
        check_unit("eps", e)
    return targets


def _exact(run: Run, coefficient: str, targets: Mapping[int, float], q: float, r: float, zeta: int) -> DataFrame:
    truth = exact_bucket_means(run.graph, run.buckets, coefficient).collect()
    return _result(run, [{"bucket": t["bucket"], "f": t["psi"], "eps": targets[t["bucket"]], "eps_hat": 0.0, "draws": run.m, "rounds": 0, "q": q, "r": r, "zeta": zeta, "why": "exact"} for t in truth])


def adaptive_estimate(
    g: Graph | None, buckets: DataFrame | None, coefficient: str, eps: float | Mapping[int, float] = 0.075, eta: float = 0.01, bound: str = "plugin", q: float | None = None,
    pilot: int = 500, work_factor: float | None = 10, growth: float = 1.5, budget: str = "strict", seed: int = 0, max_rounds: int = 60, union: bool = True, ddof: int = 1,
    centered: bool = True, tight: bool = False, zeta: int | None = None, large: float | None = 0.5, run: Run | None = None,
) -> DataFrame:
    """Per bucket an estimate and a half-width, all valid at once with probability 1 - eta.

    Rounds grow by a fixed factor, so their sizes do not depend on the draws. ``large`` is the share of the edges from
    which the bag that the target may need, whatever the data, would be no cheaper than the exact way, which is then taken;
    None never takes it.
    """
    check_unit("eta", eta)
    if bound not in ("plugin", "bernstein"):
        raise ValueError(f"unknown bound {bound!r}")
    run = run or prepare(g, buckets, coefficient, work_factor)
    targets = _targets(eps, run.sizes)
    k, least = len(run.sizes), min(targets.values(), default=0.5)
    if run.m == 0:
        return _exact(run, coefficient, targets, 0.0 if q is None else q, 0.0, 1)
    q = _tuned(run, q, pilot, seed)
    began = time.perf_counter()
    ranges = {r["bucket"]: r["r"] for r in range_bounds(run.rest, run.buckets, run.w, run.m, q, tight).collect()}
    top = max(ranges.values())
    zeta = zeta or dimension_bound(spread_sup(run.rest, run.buckets).first()["chi"], q)
    run.seconds["ranges"] = time.perf_counter() - began
    began = time.perf_counter()
    cap = max(2, math.ceil(sample_cap(top, least, zeta, eta, budget)))
    s = max(2, min(sample_start(top, least, k, budget_of_round(0, eta, budget)), cap))
    if top == 0:
        rows = [{"bucket": j, "f": run.known[j], "eps": targets[j], "eps_hat": 0.0, "draws": 0, "rounds": 0, "q": q, "r": 0.0, "zeta": zeta, "why": "exact"} for j in run.sizes]
        return _result(run, rows)
    if large is not None and cap >= large * run.m:
        out = _exact(run, coefficient, targets, q, top, zeta)
        run.seconds["loop"] = time.perf_counter() - began
        return out
    spark = run.buckets.sparkSession
    range_rows = spark.createDataFrame([(j, float(ranges[j])) for j in run.sizes], "bucket int, r double")
    sums, drawn, parts = {j: (0.0, 0.0) for j in run.sizes}, 0, []
    for i in range(max_rounds):
        values = written(_values(run, drawn, s, q, seed), "values")
        parts.append(values)
        for row in moments(values).collect():
            a, b = sums[row["bucket"]]
            sums[row["bucket"]] = (a + row["sx"], b + row["sxx"])
        drawn = s
        left = budget_of_round(i, eta, budget)
        mean = {j: a / s for j, (a, _) in sums.items()}
        if bound == "bernstein":
            half = {j: bernstein_halfwidth(variance_of_sums(*sums[j], s, ddof, centered), ranges[j], s, k, left) for j in run.sizes}
            center = mean
        else:
            every = parts[0]
            for p in parts[1:]:
                every = every.unionByName(p)
            found = plugin_chunks(every, run.buckets, range_rows, s, left / (k if union else 1)).collect()
            half, center = ({r["bucket"]: r[c] for r in found} for c in ("halfwidth", "center"))
        done = all(half[j] <= targets[j] for j in run.sizes)
        if done or s >= cap or i == max_rounds - 1:
            why = "bounds" if done else "cap" if s >= cap else "rounds"
            if not done and s >= cap:  # here the plain mean is as good as the least target, whatever the data
                center, half = mean, dict.fromkeys(run.sizes, least)
            run.seconds["loop"] = time.perf_counter() - began
            return _result(run, [{"bucket": j, "f": center[j] + run.known[j], "eps": targets[j], "eps_hat": half[j], "draws": s, "rounds": i + 1, "q": q, "r": ranges[j], "zeta": zeta, "why": why} for j in run.sizes])
        s = min(cap, max(s + 1, math.ceil(s * growth)))
    raise AssertionError("unreachable")


def fixed_size_estimate(
    g: Graph | None, buckets: DataFrame | None, coefficient: str, s: int | None = None, fraction: float | None = None, q: float | None = None, pilot: int = 500,
    work_factor: float | None = None, seed: int = 0, run: Run | None = None,
) -> DataFrame:
    """(bucket, size, f, draws, q): exactly s draws, or a share of the edges; no guarantee is worked out."""
    run = run or prepare(g, buckets, coefficient, work_factor)
    if (s is None) == (fraction is None):
        raise ValueError("give the number of draws or their share of the edges")
    s = s if s is not None else max(1, math.ceil(fraction * run.m))
    q = _tuned(run, q, pilot, seed) if run.m else q or 0.0
    known = run.buckets.sparkSession.createDataFrame([(j, run.sizes[j], float(run.known[j])) for j in run.sizes], "bucket int, size long, known double")
    sums = moments(_values(run, 0, s, q, seed)) if run.m else None
    joined = known.join(sums, "bucket", "left") if sums is not None else known.withColumn("sx", F.lit(0.0))
    return joined.select("bucket", "size", (F.col("known") + F.coalesce("sx", F.lit(0.0)) / s).alias("f"), F.lit(s).cast("long").alias("draws"), F.lit(float(q)).alias("q"))


def multipass_stream_estimate(edges: DataFrame, buckets: DataFrame, coefficient: str, s: int, q: float = 1 / 3, seed: int = 0) -> DataFrame:
    """(bucket, size, f) in three passes over an edge table that is never held: degrees and a one-pass bag, then closures, then sums."""
    from localcoef.operators.estimators import bag_triangles, bucket_means, bucket_weights, edge_shares, edge_values
    from localcoef.operators.sampling import draw_poisson

    g = Graph.of(edges, buckets)
    m = edges.count()
    bag = written(draw_poisson(edges, m, s, seed), "bag")
    drawn = bag.agg(F.coalesce(F.sum("copies"), F.lit(0)).alias("n")).first()["n"]
    w = denominators(g, coefficient)
    values = edge_values(edge_shares(bag_triangles(g, bag), q), bucket_weights(buckets, w), m)
    weighted = bag.join(values, ["u", "v"]).select("bucket", (F.col("x") * F.col("copies")).alias("x"))
    return bucket_means(weighted, buckets, max(1, drawn))
