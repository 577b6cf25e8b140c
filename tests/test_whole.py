"""Queries without the caps of their namesakes, on tables that go over them."""

from weftgraph.queries import QUERIES


def test_lines_of_many_documents(spark, tmp_path):
    rows = [(i, f"own line {i}\n a line that very many documents hold ") for i in range(1, 61)] + [(99, "alone")]
    spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'en' as lang").write.parquet(str(tmp_path / "documents.parquet"))
    assert QUERIES["edges_d9"](spark, str(tmp_path)).count() == 0
    assert QUERIES["edges_d9_all"](spark, str(tmp_path)).count() == 60 * 59 // 2
    assert QUERIES["triangle_count_d9_all"](spark, str(tmp_path)).first()[0] == 60 * 59 * 58 // 6
    assert {tuple(r) for r in QUERIES["op_connected_components_d9_all"](spark, str(tmp_path)).collect()} == {(i, 1) for i in range(1, 61)}


def test_benchmark_passages_anywhere(spark, tmp_path):
    item = " ".join(f"word{i}" for i in range(30))
    docs = [(1, f"Before {item} after"), (2, "x " + " ".join(item.split()[15:25])), (3, " ".join(item.split()[:5])), (4, "say Short  ITEM here"), (5, "short items")]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(7, item), (8, "short item")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert {tuple(r) for r in QUERIES["op_contains_bench_all"](spark, str(tmp_path)).collect()} == {(7, 2), (8, 1)}


def test_cosines_within_every_label(spark):
    v = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet")
    pairs = sum(n * (n - 1) // 2 for _, n in v.groupBy("label").count().collect())
    got = QUERIES["op_cosine_pairs_all"](spark, "/root/testdata/sf0.001")
    some = QUERIES["op_cosine_pairs"](spark, "/root/testdata/sf0.001")
    print("cosine pairs", some.count(), got.count())
    assert got.count() == pairs > some.count() and some.exceptAll(got).isEmpty()
