"""Packed lists made of groups: what is shuffled, and results against brute force."""

import random

from test_packed import brute, shuffled

from localcoef.operators import exact, packed
from localcoef.sources import graphs as G


def crowd(spark, groups, members, low=0):
    rows = spark.range(groups).selectExpr("id AS g").crossJoin(spark.range(low, low + members).selectExpr("id AS i"))
    return G.shared_group_graph(rows, "g", "i")


def test_slots_of_many_users_shuffle_no_pairs(spark):
    """three slots of 400 users, 239,400 pairs of which 79,800 differ."""
    g = crowd(spark, 3, 400, -200)
    n = shuffled(spark, lambda: exact.graph_profile(g).collect())
    assert n < 10_000
    assert exact.graph_profile(g).first().asDict() == {"n": 400, "m": 79_800, "dmax": 399, "alpha": 1.0, "phi": 1.0}


def test_suppliers_of_orders_shuffle_packed_rows(spark):
    """neither lines nor pairs of suppliers are rows of a shuffle."""
    from oracle import DATA

    g = G.suppliers_sharing_orders(spark, f"{DATA}/sf0.01")
    pairs = g.pairs.count()
    assert shuffled(spark, lambda: exact.graph_profile(g).collect()) < 10_000 < pairs


def test_ranges_read_their_lists(spark, monkeypatch):
    """from DIRECT edges on no list is shuffled."""
    r = random.Random(7)
    edges = sorted({tuple(sorted(r.sample(range(-300, 300), 2))) for _ in range(8000)})
    p = packed.pack(G.of_pairs(spark, edges))
    monkeypatch.setattr(packed, "DIRECT", 1)
    monkeypatch.setattr(packed, "RANGE", 1000)
    assert sorted(map(tuple, packed.listed_triangles(p).collect())) == brute(edges)
    assert packed._met(p, False)._jdf.queryExecution().executedPlan().toString().count("Exchange") == 0


def test_every_range_has_a_task(spark, monkeypatch):
    """a union of single partitions would run all ranges one after the other in one task."""
    r = random.Random(8)
    p = packed.pack(G.of_pairs(spark, sorted({tuple(sorted(r.sample(range(-300, 300), 2))) for _ in range(8000)})))
    monkeypatch.setattr(packed, "DIRECT", 1)
    monkeypatch.setattr(packed, "RANGE", 1000)
    ranges = len(packed._ranges(p, 8)) + 1
    for listing in (True, False):
        assert ranges <= packed._met(p, listing).rdd.getNumPartitions() <= ranges + 2
    assert ranges > 4


def test_ranges_of_groups_have_tasks(spark, monkeypatch):
    """suppliers of orders, where the ranges read the lists: a task for each, and the profile stays as it is."""
    from oracle import DATA

    g = exact.indexed(G.suppliers_sharing_orders(spark, f"{DATA}/sf0.01"))
    want = exact.graph_profile(g).first()
    monkeypatch.setattr(packed, "DIRECT", 1)
    monkeypatch.setattr(packed, "RANGE", g.packed.m // 4)
    assert packed._met(g.packed, False).rdd.getNumPartitions() > 3
    assert exact.graph_profile(g).first() == want
