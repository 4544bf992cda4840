from rulepush.workloads.ops import QUERIES


def test_range_join_of_all_parts(spark, tmp_path):
    # ids of 200 and more, prices just at and beyond the range, and one whose sum rounds up to the next bin
    prices = [900.0, 900.5, 900.51, 901.0, 0.49999999999999994, 1.0, -0.25, 0.25, None]
    parts = [(150 + 40 * i, x) for i, x in enumerate(prices)]
    spark.createDataFrame(parts, "p_partkey long, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    want = sorted((i, j) for i, a in parts for j, b in parts if i != j and None not in (a, b) and a <= b <= a + 0.5)
    assert sorted(tuple(r) for r in QUERIES["op_range"](spark, str(tmp_path)).collect()) == want
