"""Worked examples, identities, guarantees and errors on hand graphs."""

import math

import pytest
from pyspark.sql import functions as F

from localcoef.functions import concentration as C
from localcoef.model import Graph, canonical, check_partition
from localcoef.operators import baselines, bounds, estimators, exact, prefilter, sampling, tuning
from localcoef.plans.estimate import adaptive_estimate, fixed_size_estimate
from localcoef.sources import graphs as G
from localcoef.sources import partitions as P


@pytest.fixture(scope="module")
def toy(spark):
    g = G.toy(spark)
    return g, spark.createDataFrame(G.TOY_BUCKETS, "id long, bucket int")


def rows(df, *keys):
    return {tuple(r[k] for k in keys) if len(keys) > 1 else r[keys[0]]: r for r in df.collect()}


def test_profile(toy):
    got = rows(exact.node_profile(toy[0]), "id")
    want = {0: (2, 1, 1, 4, 1, 0.5), 1: (3, 2, 3, 5, 2 / 3, 0.8), 2: (3, 2, 3, 5, 2 / 3, 0.8), 3: (3, 1, 3, 4, 1 / 3, 0.5), 4: (1, 0, 0, 2, 0, 0), 5: (0, 0, 0, 0, 0, 0)}
    for i, values in want.items():
        assert tuple(got[i][c] for c in ("deg", "t", "wc", "wh", "alpha", "phi")) == pytest.approx(values)
    assert exact.triangles(toy[0]).count() == 2


@pytest.mark.parametrize("coefficient,want", [("clustering", (5 / 6, 0.5, 0)), ("closure", (0.65, 0.65, 0))])
def test_means_and_expectation(toy, coefficient, want):
    g, b = toy
    w = exact.denominators(g, coefficient)
    means = rows(exact.exact_bucket_means(g, b, coefficient), "bucket")
    assert [means[j]["psi"] for j in range(3)] == pytest.approx(want)
    for q in (0.0, 0.25, 0.5):
        found = rows(estimators.exact_edge_moments(g, b, w, 6, q), "bucket")
        assert [found[j]["mean"] for j in range(3)] == pytest.approx(want)
        ranges = rows(bounds.range_bounds(g, b, w, 6, q), "bucket")
        tight = rows(bounds.range_bounds(g, b, w, 6, q, True), "bucket")
        for j in range(3):
            assert found[j]["variance"] <= C.variance_ceiling(want[j], 6, 1) + 1e-9
            assert found[j]["largest"] - 1e-9 <= tight[j]["r"] <= ranges[j]["r"] + 1e-9


def test_single_edge_values(toy):
    g, b = toy
    got = rows(estimators.all_edge_values(g, b, exact.denominators(g, "clustering"), 6, 0.25), "u", "v", "bucket")
    assert got[1, 2, 0]["x"] == pytest.approx(2.0) and got[0, 2, 1]["x"] == pytest.approx(0.25) and (3, 4, 0) not in got


@pytest.mark.parametrize("coefficient,q,value", [("clustering", 13 / 38, 0.477193), ("closure", 0.310345, 0.217345)])
def test_tuning(toy, coefficient, q, value):
    g, b = toy
    found = tuning.split_quadratics(g, g.edges, b, exact.denominators(g, coefficient), 6, 6).collect()
    x, t = tuning.minimax_split([(r["qa"], r["qb"], r["qc"]) for r in found])
    assert x == pytest.approx(q, abs=1e-6) and t == pytest.approx(value, abs=1e-6)


def test_minimax_crossing_and_section():
    assert tuning.minimax_split([(1, -4, 4), (0, 0, 4)]) == pytest.approx((0.25, 0.25))
    many = [(1 + i * 1e-9, -4.0, 4.0) for i in range(300)] + [(0.0, 0.0, 4.0)]
    assert tuning.minimax_split(many)[0] == pytest.approx(0.25, abs=1e-6)
    assert tuning.minimax_split([]) == (0.0, 0.0)


def test_filter(toy):
    g, b = toy
    assert prefilter.low_degree_threshold(g, 1).first()["beta"] == 2
    found = prefilter.apply_filter(g, b, exact.denominators(g, "clustering"), 2)
    assert {(r["u"], r["v"]) for r in found.rest.edges.collect()} == {(1, 2), (1, 3), (2, 3)}
    rest = rows(estimators.exact_edge_moments(found.rest, b, exact.denominators(g, "clustering"), 3, 0.2), "bucket")
    known = rows(found.known, "bucket")
    assert [known[j]["known"] + rest[j]["mean"] for j in range(3)] == pytest.approx([5 / 6, 0.5, 0])


def test_spread_and_dimension(toy, spark):
    assert bounds.spread_sup(*toy).first()["chi"] == 2
    assert bounds.dimension_bound(1) == 1 and bounds.dimension_bound(2) == 2 and bounds.dimension_bound(9, 0.5) == 2
    star = G.star(spark, 10, chord=False)
    assert bounds.spread_sup(star, P.singleton_buckets(star), closed=False).first()["chi"] == 1


def test_sizes_and_bounds():
    assert C.sample_start(2, 0.075, 6, 0.005) == 680
    assert C.sample_cap(2, 0.075, 2, 0.01, "printed") == pytest.approx(4697.01, abs=0.01)
    assert C.hoeffding_size(0.075, 6, 0.01) == 631
    assert C.relative_error_size(1e-2, 1e-3) == pytest.approx(1e10)
    assert sum(C.budget_of_round(i, 0.01) for i in range(60)) <= 0.005 + 1e-12
    wide, narrow = C.plugin_loop([0.5] * 50, 1.0, 0.05)[1], C.plugin_loop([0.5] * 5000, 1.0, 0.05)[1]
    assert narrow < wide


def test_plugin_paths_agree(spark):
    import numpy as np

    x = np.random.default_rng(1).random(300) * (np.random.default_rng(2).random(300) < 0.4)
    values = spark.createDataFrame([(i, 0, float(v)) for i, v in enumerate(x) if v], "ix long, bucket int, x double")
    names = spark.createDataFrame([(0,)], "bucket int")
    want = C.plugin_loop(x.tolist(), 1.0, 0.01)
    got = C.plugin_chunks(values, names, names.withColumn("r", F.lit(1.0)), 300, 0.01, 64).first()
    assert (got["center"], got["halfwidth"]) == pytest.approx(want)


def test_coverage_and_cap(toy):
    g, b = toy
    for bound in ("plugin", "bernstein"):
        got = rows(adaptive_estimate(g, b, "clustering", 0.5, 0.1, bound, work_factor=None, seed=3, large=None), "bucket")
        for j, psi in enumerate((5 / 6, 0.5, 0)):
            assert abs(got[j]["f"] - psi) <= got[j]["eps_hat"] + 1e-9 and got[j]["eps_hat"] <= 0.5
    small = rows(adaptive_estimate(g, b, "closure", 0.05, 0.1, work_factor=None), "bucket")
    assert small[0]["exit_reason"] == "exact" and small[0]["f"] == pytest.approx(0.65)


def test_prefix_of_a_longer_bag(toy):
    numbered = sampling.number_edges(toy[0].edges)
    short, long = ({(r["ix"], r["u"], r["v"]) for r in sampling.draw_indexed(numbered, 6, n, 1).collect()} for n in (20, 50))
    assert short < long and len(long) == 50


def test_wedge_baselines_find_the_means(toy):
    g, b = toy
    draws = b.select("bucket").distinct().withColumn("s", F.lit(3000))
    for f, want in ((baselines.wedge_center, (5 / 6, 0.5, 0)), (baselines.wedge_headed, (0.65, 0.65, 0))):
        got = rows(f(g, b, draws, 5), "bucket")
        assert [got[j]["f"] for j in range(3)] == pytest.approx(want, abs=0.04)


def test_exact_where_the_bag_may_grow_too_large(spark):
    """the first round is small, the bag that the target may need is not."""
    g = G.of_pairs(spark, [(i, j) for i in range(50) for j in range(i) if (i, j) != (1, 0)])
    got = adaptive_estimate(g, P.single_bucket(g), "clustering", 0.06, 0.1, work_factor=None, q=0.25).first()
    sampled = adaptive_estimate(g, P.single_bucket(g), "clustering", 0.06, 0.1, work_factor=None, q=0.25, large=None).first()
    assert sampled["exit_reason"] == "bounds" and sampled["draws"] < 0.5 * (1225 - 1)
    assert got["exit_reason"] == "exact" and got["eps_hat"] == 0
    assert got["f"] == pytest.approx(exact.exact_bucket_means(g, P.single_bucket(g), "clustering").first()["psi"])


def test_closed_forms(spark):
    complete = G.of_pairs(spark, [(i, j) for i in range(6) for j in range(i)])
    cycle = G.of_pairs(spark, [(i, (i + 1) % 7) for i in range(7)])
    empty = Graph.of(spark.createDataFrame([], "u long, v long"), spark.createDataFrame([(1,), (2,)], "id long"))
    for c in ("clustering", "closure"):
        assert exact.exact_bucket_means(complete, P.single_bucket(complete), c).first()["psi"] == 1
        assert exact.exact_bucket_means(cycle, P.single_bucket(cycle), c).first()["psi"] == 0
        got = adaptive_estimate(empty, P.single_bucket(empty), c, 0.1).first()
        assert got["f"] == 0 and got["exit_reason"] == "exact"


def test_loops_and_duplicates_go(spark):
    df = spark.createDataFrame([(1, 1), (2, 1), (1, 2), (None, 3)], "u long, v long")
    assert [(r["u"], r["v"]) for r in canonical(df).collect()] == [(1, 2)]


def test_cores(spark):
    g = G.of_pairs(spark, [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)])
    assert {r["id"]: r["core"] for r in P.core_numbers(g).collect()} == {0: 2, 1: 2, 2: 2, 3: 1, 4: 1}


def test_errors(toy, spark):
    g, b = toy
    with pytest.raises(ValueError):
        exact.denominators(g, "other")
    with pytest.raises(ValueError):
        adaptive_estimate(g, b, "clustering", 1.5)
    with pytest.raises(ValueError):
        adaptive_estimate(g, b, "clustering", 0.1, 0.0)
    with pytest.raises(ValueError):
        fixed_size_estimate(g, b, "clustering")
    with pytest.raises(ValueError):
        check_partition(g.nodes, b.where("id > 0"))
    with pytest.raises(ValueError):
        check_partition(g.nodes, b.unionByName(b))
    check_partition(g.nodes, b)
    assert math.isclose(estimators.bucket_means(estimators.edge_bucket_values(g, g.edges.withColumn("ix", F.lit(0)), b, exact.denominators(g, "closure"), 6, 0.1), b, 6).where("bucket = 1").first()["f"], 0.65)


def test_loops_end_settled_or_fail(spark):
    from localcoef.plans.experiments import induced_components

    g = G.of_pairs(spark, [(i, i + 1) for i in range(11)])
    with pytest.raises(RuntimeError):
        P.core_numbers(g, 2)
    with pytest.raises(RuntimeError):
        induced_components(g, P.single_bucket(g), 1)
    assert {r["core"] for r in P.core_numbers(g).collect()} == {1}
    assert [(r["components"], r["largest"]) for r in induced_components(g, P.single_bucket(g)).collect()] == [(1, 12)]


def test_variance_ceiling_is_squared(toy):
    """The ceiling holds, and for a mean below 1 it is the squared one, not the looser linear one."""
    assert C.variance_ceiling(0.5, 6, 1) == 1.25 and C.variance_ceiling(0.5, 6, 10) == 0.125
    g, b = toy
    for coefficient in ("clustering", "closure"):
        psi = {r["bucket"]: r["psi"] for r in exact.exact_bucket_means(g, b, coefficient).collect()}
        for q in (0.0, 0.2, 0.5):
            for r in estimators.exact_edge_moments(g, b, exact.denominators(g, coefficient), 6, q).collect():
                assert r["variance"] <= C.variance_ceiling(psi[r["bucket"]], 6, 1) + 1e-9


@pytest.mark.parametrize("bound", ["plugin", "bernstein"])
def test_the_cap_reports_the_common_target(toy, monkeypatch, bound):
    """At the cap the plain mean comes with the least target for every bucket, not with its own half-width."""
    from localcoef.plans import estimate

    g, b = toy
    monkeypatch.setattr(estimate, "sample_cap", lambda *_: 20.0)
    run = estimate.prepare(g, b, "clustering")
    got = rows(adaptive_estimate(None, None, "clustering", {0: 0.9, 1: 0.3, 2: 0.9}, 0.1, bound, q=0.5, large=None, run=run, seed=5), "bucket")
    plain = rows(fixed_size_estimate(None, None, "clustering", s=20, q=0.5, run=run, seed=5), "bucket")
    for j, r in got.items():
        assert r["exit_reason"] == "cap" and r["eps_hat"] == 0.3 and r["draws"] == 20 and r["f"] == pytest.approx(plain[j]["f"])


def test_sums_of_lines_equal_single_runs(toy):
    from localcoef.plans import estimate, experiments

    g, b = toy
    run = estimate.prepare(g, b, "closure")
    sums, _ = experiments.run_sums(run, [7, 40], [3, 4], pilot=6)
    tuned = experiments.tuned_by_run(run, sums, [3, 4], pilot=6)
    splits = g.edges.sparkSession.createDataFrame([(3, 0.2), (4, float(tuned[4]))], "run int, q double")
    got = {(r["run"], r["draws"], r["bucket"]): r["f"] for r in experiments._estimates(run, sums, [7, 40], splits).collect()}
    for s in (7, 40):
        for seed, q in ((3, 0.2), (4, None)):
            one = estimate.fixed_size_estimate(None, None, "closure", s=s, q=q, pilot=6, seed=seed, run=run)
            for r in one.collect():
                assert got[seed, s, r["bucket"]] == pytest.approx(r["f"], abs=1e-9)


def test_coverage_over_a_hundred_runs(spark):
    """Simultaneous intervals hold in all of 120 runs at 1 - eta = 0.9, by sums of lines and the half-width of each run."""
    from localcoef.plans import estimate, experiments

    pairs = [(a, c) for a in range(24) for c in range(a + 1, 24) if (a * 5 + c * 3) % 4]
    g = Graph.of(spark.createDataFrame(pairs, "u long, v long"))
    b = g.nodes.select("id", (F.col("id") % 3).cast("int").alias("bucket"))
    run, seeds, s, q, eta = estimate.prepare(g, b, "clustering"), list(range(120)), 400, 0.2, 0.1
    psi = {r["bucket"]: r["psi"] for r in exact.exact_bucket_means(g, b, "clustering").collect()}
    r = {x["bucket"]: x["r"] for x in bounds.range_bounds(run.rest, run.buckets, run.w, run.m, q).collect()}
    sums, _ = experiments.run_sums(run, [s], seeds)
    missed, seen = set(), set()
    for x in sums.where("stream = 'main'").collect():
        sx, sxx = x["b"] + q * x["s"], x["bb"] + 2 * q * x["bs"] + q * q * x["ss"]
        half = C.bernstein_halfwidth(C.variance_of_sums(sx, sxx, s), r[x["bucket"]], s, 3, eta)
        seen.add((x["run"], x["bucket"]))
        if abs(sx / s - psi[x["bucket"]]) > half:
            missed.add(x["run"])
    assert len(seen) == 360 and len(missed) <= 0.1 * 120


def test_few_triangles_equal_all(toy):
    g, _ = toy
    some = g.edges.limit(4)
    assert sorted(map(tuple, estimators.bag_triangles(g, some, few=True).collect())) == sorted(map(tuple, estimators.bag_triangles(g, some).collect()))
    assert estimators.bag_triangles(g, some.limit(0), few=True).count() == 0


def test_regime():
    assert C.regime(0.9, 0.075, 6, 0.01, 2)[1] == "optimistic" and C.regime(8.0, 0.01, 25, 0.01, 3)[1] == "mixed"


def test_labels_beyond_the_broadcast_bound_keep_their_order(spark):
    labels = spark.range(5000).selectExpr("md5(cast(id as string)) as named")
    got = [r["named"] for r in P._numbered_by_ranges(labels).orderBy("bucket").collect()]
    assert got == sorted(r["named"] for r in labels.collect())
    assert [r["bucket"] for r in P._numbered_by_ranges(labels).orderBy("bucket").collect()] == list(range(5000))


@pytest.mark.parametrize("q", [0.0, 0.2, 0.5])
def test_range_bounds_hold_for_every_edge_and_are_met_by_one(spark, q):
    """Against the bound of each edge, worked out one by one, with nodes that have no bucket and others without wedges."""
    import random

    rng = random.Random(3)
    pairs = sorted({tuple(sorted(rng.sample(range(30), 2))) for _ in range(90)} | {(40, 41), (0, 42)})
    ids = sorted({x for p in pairs for x in p})
    bucket = {i: rng.randrange(4) for i in ids if i % 7}
    g = Graph.of(spark.createDataFrame(pairs, "u long, v long"))
    b = spark.createDataFrame(list(bucket.items()), "id long, bucket int")
    for c in ("clustering", "closure"):
        w = exact.denominators(g, c)
        inverse = {r["id"]: 1 / r["w"] for r in w.collect() if r["w"] > 0}
        around = {i: [x + y - i for x, y in pairs if i in (x, y)] for i in ids}
        want = dict.fromkeys(set(bucket.values()), 0.0)
        for u, v in pairs:
            z, o = (u, v) if len(around[u]) <= len(around[v]) else (v, u)
            t = len(around[z]) - 1
            for j in want if t else ():
                of = lambda x, j=j: inverse.get(x, 0.0) if bucket.get(x) == j else 0.0
                want[j] = max(want[j], q * t * (of(z) + of(o)) + (1 - 2 * q) * sum(of(x) for x in around[z] if x != o))
        size = {j: list(bucket.values()).count(j) for j in want}
        got = {r["bucket"]: r["r"] for r in bounds.range_bounds(g, b, w, len(pairs), q).collect()}
        assert got == pytest.approx({j: x * len(pairs) / size[j] for j, x in want.items()})
