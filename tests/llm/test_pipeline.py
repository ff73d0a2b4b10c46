"""The pipeline's stages, each on what the one before kept."""

import corpus_pipeline as cp
from test_text_operators import groups_by_force, prose, table


def test_stages(spark, tmp_path):
    spark.createDataFrame([(0, " ".join(prose(31, 30)))], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    clean = [" ".join(prose(k, 60)) for k in range(6)]
    near = clean[0].split()
    near[3] = "changed"
    texts = [*clean, " ".join(near), None, "123", "\n".join(["same a b", "same c d", "same e f", "own g h i j k"]), "\n".join(["same a b", "same c d", "same e f"]), " ".join(prose(40, 20) + prose(31, 30) + prose(41, 20))]
    docs, sizes = table(spark, texts), []
    for name, stage in cp.STAGES:
        columns = docs.columns
        docs = cp.written(stage(spark, docs, str(tmp_path)), name)
        sizes.append(docs.count())
        assert name == "tokens" or docs.columns == columns
    assert sizes == [10, 9, 8, 7, 7]
    assert groups_by_force(clean + [" ".join(near)], list(range(7)))[6] == 0
    assert {r["doc_id"] for r in docs.collect()} == {0, 1, 2, 3, 4, 5, 9}


def test_empty(spark, tmp_path):
    spark.createDataFrame([], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs = table(spark, ["a"]).limit(0)
    for name, stage in cp.STAGES:
        docs = cp.written(stage(spark, docs, str(tmp_path)), name)
    assert docs.count() == 0


def test_run(spark):
    got = cp.run(spark, "/root/testdata/sf0.001")
    assert 0 < got.count() <= 200 and got.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
