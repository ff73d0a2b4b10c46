"""Rows of bits of dense graphs: profiles and edges against brute force."""

import itertools
import random
from collections import Counter

import pytest
from test_packed import brute

from localcoef.model import Graph
from localcoef.operators import bits, exact
from localcoef.sources import graphs as G


def members(seed, groups=9, ids=300, share=0.12, copies=()):
    """(g, i): some ids with the groups of another one, some alone in a group, ids negative and far apart."""
    r = random.Random(seed)
    rows = {(g, i) for g in range(groups) for i in range(ids) if r.random() < share}
    for k, n in copies:
        rows |= {(g, ids + 1000 * n + j) for g, i in list(rows) if i == k for j in range(n)}
    return sorted({(g - 4, i * 7 - 500) for g, i in rows} | {(99, 2**40), (99, 2**40), (98, -(2**50)), (98, -(2**50) + 1)})


def joined(rows):
    by = {}
    for g, i in rows:
        by.setdefault(g, set()).add(i)
    return sorted({p for x in by.values() for p in itertools.combinations(sorted(x), 2)})


def numbers(edges):
    t, deg, wh = Counter(i for x in brute(edges) for i in x), Counter(i for e in edges for i in e), Counter()
    for u, v in edges:
        wh[u] += deg[v] - 1
        wh[v] += deg[u] - 1
    return {i: (deg[i], t[i], wh[i]) for i in deg}


@pytest.mark.parametrize("copies", [(), ((3, 5), (8, 70), (11, 5), (20, 1))])
def test_profile_of_groups_equals_brute_force(spark, copies, monkeypatch):
    """classes of one and of many, in several blocks; every node's numbers are those of its class."""
    monkeypatch.setattr(bits, "CROWD", 1)
    monkeypatch.setattr(bits, "SLICE", 700)
    rows = members(1, copies=copies)
    g = G.shared_group_graph(spark.createDataFrame(rows, "g long, i long"), "g", "i")
    want = numbers(joined(rows))
    made = g.bits()
    assert made.places.blocks > 1
    found = {r["id"]: (r["size"], r["deg"], r["t"], r["wh"]) for r in bits.profile(made).collect()}
    got = {r["i"]: found[r["c"]][1:] for r in made.classed.collect() if r["c"] in found}
    assert got == want
    assert sum(x[0] for x in found.values()) == len(want) and (not copies or max(x[0] for x in found.values()) >= 71)
    assert exact.graph_profile(g).first().asDict() == pytest.approx(exact.graph_profile(Graph(g.nodes, g.edges, g.pairs, g.groups, ends=True)).first().asDict(), rel=1e-12)


def test_marks_that_agree_by_chance(spark, monkeypatch):
    """Classes are confirmed against their groups."""
    from pyspark.sql import functions as F

    monkeypatch.setattr(bits, "CROWD", 1)
    monkeypatch.setattr(F, "xxhash64", lambda *c: F.lit(7).cast("long"))
    rows = members(2)
    made = bits.of_groups(spark.createDataFrame(rows, "g long, i long"))
    assert {r["id"]: (r["deg"], r["t"], r["wh"]) for r in bits.profile(made).collect()} == numbers(joined(rows))


def test_groups_of_twins_are_met_once(spark):
    """60 copies of 50 users in 40 slots: as many classes as users, whatever the copies."""
    r = random.Random(5)
    rows = [(g, i) for g in range(40) for i in range(50) if r.random() < 0.2]
    every = spark.createDataFrame(rows, "g long, i long").crossJoin(spark.range(60).withColumnRenamed("id", "k")).selectExpr("g", "i + 50 * k AS i")
    made = G.shared_group_graph(every, "g", "i").bits()
    assert made is not None and len(made.places.ids) <= 50


def test_small_groups_keep_their_lists(spark):
    rows = spark.createDataFrame(members(4), "g long, i long")
    assert bits.of_groups(rows) is None
    assert bits.of_groups(rows.limit(0)) is None


def test_profile_of_vectors_equals_brute_force(spark, tmp_path):
    """no edge is a row; several blocks, unequal lengths, a zero vector, cosines at the threshold."""
    r = random.Random(3)
    vectors = [(i * 3, [r.gauss(0, 1) for _ in range(5)]) for i in range(-150, 150)] + [(1001, [1.0, 2.0]), (1002, [2.0, 4.0]), (1003, []), (1004, None), (1005, [0.0] * 5), (1006, [1.0, 0.0, 0.0]), (1007, [1.0, 24.0**0.5, 0.0]), (1009, [float("nan"), 1.0])]
    spark.createDataFrame(vectors, "vec_id long, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    g = G.similar_vectors(spark, str(tmp_path))
    made = g.bits()
    assert made.places.blocks > 1
    edges = sorted((e["u"], e["v"]) for e in g.edges.collect())
    assert {r["id"]: (r["deg"], r["t"], r["wh"]) for r in bits.profile(made).collect()} == numbers(edges)
    assert exact.graph_profile(g).first().asDict() == pytest.approx(exact.graph_profile(Graph(g.nodes, g.edges, g.pairs, ends=True)).first().asDict(), rel=1e-12)


@pytest.mark.parametrize("crowd", [1, 10**9])
def test_streamed_pairs_of_late_files(spark, tmp_path, monkeypatch, crowd):
    """files whose events are days before those of the files read first; twins; pairs once, none shuffled."""
    import os

    from test_packed import shuffled

    from localcoef.streaming.edges import co_activity, event_stream

    monkeypatch.setattr(bits, "CROWD", crowd)
    rows = sorted(set(members(6, copies=((3, 5), (8, 20)))))
    for k, days in enumerate(("g > 0", "g <= 0")):
        part = spark.createDataFrame(rows, "g long, i long").where(days).selectExpr("cast(timestamp_seconds(600 * (1000 * g + 2800000) + 3) AS timestamp_ntz) AS ts", "i AS user_id")
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
        for f in (tmp_path / "events.parquet").glob("*.parquet"):
            os.utime(f, (1e9 + k, 1e9 + k)) if f.stat().st_mtime > 2e9 - 5e8 else None
    pairs = co_activity(event_stream(spark, str(tmp_path)))
    n = shuffled(spark, lambda: pairs.count())
    assert sorted(map(tuple, pairs.collect())) == joined(rows) and n < 100


def test_pairs_equal_the_stream_join(spark):
    """One file in order of time: the pairs of the whole slots are those of the stream-stream join."""
    from oracle import DATA

    from localcoef.streaming import edges as S

    d = f"{DATA}/sf0.001"
    join = S.run_to_files(S.co_activity_join(S.event_stream(spark, d))).select("u", "v").distinct()
    assert sorted(map(tuple, S.co_activity(S.event_stream(spark, d)).collect())) == sorted(map(tuple, join.collect())) != []
