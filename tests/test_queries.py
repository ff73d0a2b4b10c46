"""Some registered queries against their SQL; the driver compares all of them."""

import pytest
from oracle import DATA, compare

import localcoef.relational  # noqa: F401
from localcoef.queries import ORACLE_SQL, QUERIES

NAMES = ["x8_node_triangles", "e4_fixed_bag_means_clustering", "b6_range_bounds_closure", "f4_combined", "wc_wedge_center", "wk7_snapshots", "op_join_asof", "op_pivot", "st_tumbling", "st_distinct", "b7_tight_ranges_closure", "e5_split_extremes", "a7_multipass", "a8_bucket_weighted_triangles", "wk8_components", "wh_wedge_headed", "tr_retained", "st_co_activity"]


@pytest.mark.parametrize("name", NAMES)
def test_equal_to_sql(spark, name):
    assert compare(spark, QUERIES[name], ORACLE_SQL[name], "sf0.001") == ""


def test_every_sql_has_a_query():
    assert set(ORACLE_SQL) <= set(QUERIES)


def test_retained_stream_equals_batch(spark, tmp_path):
    from pyspark.sql import functions as F

    from localcoef.model import Graph
    from localcoef.operators.exact import triangles
    from localcoef.streaming.edges import retained_triangles, run_to_memory

    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    pairs = [(a, b) for a in range(12) for b in range(a + 1, 12) if (a * 7 + b) % 3]
    edges = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(pairs)], "i int, u long, v long").withColumn("ts", F.timestamp_seconds("i")).drop("i")
    edges.write.parquet(str(tmp_path / "edges"))
    stream = spark.readStream.schema(edges.schema).parquet(str(tmp_path / "edges"))
    want = triangles(Graph.of(edges)).count()
    for colours in (1, 3):
        out = run_to_memory(retained_triangles(stream, 1.0, colours), "update")
        assert out.groupBy("a", "b", "c").agg(F.max("triangles").alias("n")).agg(F.sum("n").alias("n")).first()["n"] == want > 0


def test_co_activity_leaves_no_rows_with_the_driver(spark):
    """the pairs of the stream are in files, not in a table of the driver's memory."""
    df = QUERIES["st_co_activity"](spark, f"{DATA}/sf0.001")
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    assert "MemoryPlan" not in plan and "parquet" in plan and df.count() > 0


def test_streamed_passes_equal_the_batch_form(spark):
    from localcoef.plans.estimate import multipass_stream_estimate
    from localcoef.relational import _edge_files
    from localcoef.sources.graphs import copart_year
    from localcoef.streaming.edges import streamed_passes

    edges, buckets = _edge_files(spark, f"{DATA}/sf0.001")
    for c in ("clustering", "closure"):
        got = {r["bucket"]: r["f"] for r in streamed_passes(edges, buckets, c, 300).collect()}
        batch = multipass_stream_estimate(copart_year(spark, f"{DATA}/sf0.001").edges, buckets, c, 300)
        assert got == pytest.approx({r["bucket"]: r["f"] for r in batch.collect()})


def test_entry_shape(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.count() > 0 and DATA


@pytest.mark.parametrize("name", ["x8_node_triangles_cp", "e4_fixed_bag_means_clustering_cp", "b6_range_bounds_closure_tr", "f3_carried_cp"])
def test_whole_graphs_equal_to_sql(spark, name):
    assert compare(spark, QUERIES[name], ORACLE_SQL[name], "sf0.001") == ""


def test_whole_table_reaches_the_operators(spark):
    from localcoef.sources.graphs import copart

    assert QUERIES["s2_number_edges_cp"](spark, f"{DATA}/sf0.001").count() == copart(spark, f"{DATA}/sf0.001").edges.count()


def test_entry_without_the_text_operators(tmp_path):
    """A copy without the folders of the text operators still lists the other queries."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    shutil.copytree(root / "localcoef", tmp_path / "localcoef", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", "corpus_pipeline.py"):
        if (root / name).exists():
            shutil.copy(root / name, tmp_path)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'x1_degree' in q and set(o) <= set(q) and not any(n.startswith('op1_') or n == 'pipeline' for n in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
