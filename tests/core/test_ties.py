"""Order and ties where Spark leaves them open."""

from caseloom.operators import registry


def orders(spark, path, rows):
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").write.parquet(f"{path}/orders.parquet")
    for n in ("region", "nation", "supplier", "part", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        spark.range(0).write.parquet(f"{path}/{n}.parquet")
    spark.createDataFrame([(1,), (2,), (3,)], "c_custkey long").write.parquet(f"{path}/customer.parquet")
    return str(path)


def test_argmax_takes_the_smallest_key_of_equal_prices(spark, tmp_path):
    path = orders(spark, tmp_path, [(9, 1, 5.0), (2, 1, 5.0), (4, 1, 5.0), (1, 1, 4.0), (7, 2, None), (8, 2, 1.0), (None, 2, 9.0), (5, 3, None)])
    assert {r["o_custkey"]: r["top"] for r in registry.queries()["q_argmax"](spark, path).collect()} == {1: 2, 2: 8, 3: None}


def test_lateral_topn_ranks_by_price(spark, tmp_path):
    path = orders(spark, tmp_path, [(k, 1, float(k % 7)) for k in range(40)] + [(100, 2, 1.0)])
    got = registry.queries()["q_lateral_topn"](spark, path)
    assert sorted(tuple(r) for r in got.collect()) == [(1, 6), (1, 13), (2, 100)]
    window = next(x for x in got._jdf.queryExecution().optimizedPlan().toString().split("\n") if "row_number() windowspec" in x)
    assert "o_totalprice" in window
