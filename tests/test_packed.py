"""Packed neighbour lists against brute force, and how many rows they shuffle."""

import itertools
import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from localcoef.model import Graph
from localcoef.operators import estimators, exact, packed
from localcoef.sources import graphs as G


def brute(edges):
    near = {}
    for u, v in edges:
        near.setdefault(u, set()).add(v)
    return sorted((a, b, c) for a in near for b in near[a] for c in near.get(b, ()) if c in near[a])


def drawn(kind, seed=0):
    r = random.Random(seed)
    if kind == "dense":
        ids = list(range(-20, 20))
    elif kind == "wide":
        ids = [r.randrange(-(2**61), 2**61) for _ in range(40)]
    else:  # hubs at the least, the middle and the largest id
        ids = list(range(0, 6000, 60))
    edges = {(a, b) for a, b in itertools.combinations(sorted(ids), 2) if r.random() < (0.1 if kind == "hub" else 0.5)}
    if kind == "hub":
        s = sorted(ids)
        edges |= {tuple(sorted((h, x))) for h in (s[0], s[50], s[-1]) for x in s if x != h}
    return sorted(edges)


@pytest.mark.parametrize("kind", ["dense", "wide", "hub"])
@pytest.mark.parametrize("longer", [0.1, 8, 1e9])
def test_ranges_meet_every_list(kind, longer, monkeypatch):
    """Few marks, short steps and small rows; all, some or no lists are searched."""
    for name, value in (("MARKS", 64), ("STEP", 50), ("BUNDLE", 37), ("LONGER", longer)):
        monkeypatch.setattr(packed, name, value)
    edges = drawn(kind)
    u, v = packed._distinct(*np.array(edges + edges[::3]).T)
    heads, sizes = np.unique(u, return_counts=True)
    for cuts in ([], sorted({e[0] for e in edges})[5::9]):
        rows = packed._bundles(packed._PACKED, 0, 0, heads, sizes, v)
        sent = sorted(packed._send(np.array(cuts, np.int64))(rows), key=lambda b: (b.column(0)[0].as_py(), b.column(1)[0].as_py()))
        want = brute(edges)
        listed = [t for b in packed._meet(True)(iter(sent)) for t in zip(*(c.to_pylist() for c in b.columns), strict=True)]
        assert sorted(listed) == want and want
        counted = Counter()
        for b in packed._meet(False)(iter(sent)):
            for i, t in zip(*(c.to_pylist() for c in b.columns), strict=True):
                counted[i] += t
        assert counted == Counter(i for t in want for i in t)


@pytest.mark.parametrize("x", [[], [5], [-(2**62), 2**62, 0], list(range(100)), [7, 7, 3, 2**40]])
def test_squeezed_numbers_come_back(x):
    assert packed.unsqueezed(packed.squeezed(np.array(x, np.int64))).tolist() == x
    assert pa.array([packed.squeezed(np.array(x, np.int64))], pa.binary())[0].as_py() is not None


@pytest.mark.parametrize("kind", ["dense", "wide", "hub"])
def test_profile_equals_brute_force(spark, kind):
    edges = drawn(kind, 1)
    lonely = max(b for _, b in edges) + 1
    ids = sorted({i for e in edges for i in e})
    got = {r["id"]: r for r in exact.node_profile(G.of_pairs(spark, edges, [*ids, lonely])).collect()}
    t, deg = Counter(i for x in brute(edges) for i in x), Counter(i for e in edges for i in e)
    ahead = Counter()
    for u, v in edges:
        ahead[u] += deg[v] - 1
        ahead[v] += deg[u] - 1
    assert {i: (r["deg"], r["t"], r["wh"]) for i, r in got.items()} == {i: (deg[i], t[i], ahead[i]) for i in [*ids, lonely]}


def test_graph_without_edges(spark):
    g = Graph.of(spark.createDataFrame([], "u long, v long"))
    assert exact.node_profile(g).count() == 0 and exact.triangles(g).count() == 0
    assert exact.graph_profile(g).first()["n"] == 0


def shuffled(spark, run):
    """Records that a run writes to shuffles."""
    store, jvm = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._jvm

    def total():
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        stages = store.stageList(None, False, False, spark.sparkContext._gateway.new_array(jvm.double, 0), None)
        return sum(stages.apply(i).shuffleWriteRecords() for i in range(stages.size()))

    before = total()
    run()
    return total() - before


def complete(spark, n=200):
    return Graph.of(spark.range(n).selectExpr("id AS u").crossJoin(spark.range(n).selectExpr("id AS v")).where("u < v"))


def test_profile_shuffles_no_row_for_each_wedge(spark):
    """F1: 19,900 edges and 1.3 million wedges."""
    g = complete(spark)
    n = shuffled(spark, lambda: exact.graph_profile(g).collect())
    assert n < 5 * 19_900
    assert exact.graph_profile(g).first()["alpha"] == 1


@pytest.mark.parametrize("name", ["x11_bucket_means_clustering_log_cp", "x11_bucket_means_clustering_rnd_cp", "x11_bucket_means_clustering_type_cp", "x12_global_closure_cp", "x7_triangle_count_cp"])
def test_whole_graph_is_made_once(spark, name):
    """F2 to F6: pairs of lines are shuffled once, whatever the query reads of the graph."""
    from oracle import DATA

    from localcoef.queries import QUERIES

    d = f"{DATA}/sf0.01"
    pairs, lines = G.copart(spark, d).pairs.count(), G.read(spark, d, "lineitem").count()
    nodes = exact.degrees(exact.indexed(G.copart(spark, d))).count()
    assert shuffled(spark, lambda: QUERIES[name](spark, d).collect()) < pairs + lines + 40 * nodes


def test_expectation_over_all_edges_shuffles_triangles_not_wedges(spark):
    """F8: a grid of 1,568 edges that hang on two hubs: a million pairs of neighbours, 784 triangles."""
    pairs = spark.range(2, 786).selectExpr("0L AS u", "id AS v").unionByName(spark.range(2, 786).selectExpr("1L AS u", "id AS v"))
    g = Graph.of(pairs.unionByName(spark.createDataFrame([(0, 1)], "u long, v long")))
    b = g.nodes.selectExpr("id", "0 AS bucket")
    w = exact.denominators(g, "clustering")
    run = lambda: estimators.exact_edge_moments(g, b, w, 1569, 0.2).collect()
    assert shuffled(spark, run) < 20_000
    every = sorted(map(tuple, estimators.bag_triangles(g, g.edges).collect()))
    assert every == sorted(map(tuple, estimators.all_triangles(g).collect())) and len(every) == 3 * 784


def test_blocks_of_vectors_against_pairs(spark, tmp_path):
    """short, unequal, empty, null and zero vectors, a cosine at the threshold, negative ids; no pair is a row of a join."""
    r = random.Random(3)
    vectors = [(i, [r.gauss(0, 1) for _ in range(3)]) for i in range(-20, 20)] + [(50, [1.0, 2.0]), (51, [2.0, 4.0]), (52, []), (53, None), (54, [0.0] * 3), (60, [1.0, 0.0, 0.0]), (61, [1.0, 24.0**0.5, 0.0])]
    spark.createDataFrame(vectors, "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))

    def cosine(x, y):
        dot = lambda p, q: sum((a * b for a, b in zip(p, q, strict=True)), 0.0)
        return dot(x, y) / (dot(x, x) ** 0.5 * dot(y, y) ** 0.5)

    real = [(i, x) for i, x in vectors if x and any(x)]
    want = {(i, j) for (i, x), (j, y) in itertools.combinations(real, 2) if len(x) == len(y) and cosine(x, y) > 0.2}
    g = G.similar_vectors(spark, str(tmp_path))
    assert {(e["u"], e["v"]) for e in g.edges.collect()} == want and (50, 51) in want
    assert "Join" not in g.edges._jdf.queryExecution().executedPlan().toString()


def test_graph_profiles_of_groups_shuffle_no_wedges(spark):
    """users of a slot and suppliers of an order; dense graphs have far more wedges than edges."""
    from oracle import DATA

    for make in (G.active_together, G.suppliers_sharing_orders):
        g = make(spark, f"{DATA}/sf0.01")
        rows, edges = g.pairs.count(), g.edges.count()
        assert shuffled(spark, lambda g=g: exact.graph_profile(g).collect()) < 3 * rows + edges + 50_000
