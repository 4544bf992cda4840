"""The range join is shared by tasks however small its files are."""

from rulepush.workloads.ops import QUERIES


def test_range_join_has_tasks(spark, tmp_path):
    spark.range(40).selectExpr("id AS p_partkey", "900 + id / 4 AS p_retailprice").coalesce(1).write.parquet(f"{tmp_path}/part.parquet")
    out = QUERIES["op_range"](spark, str(tmp_path))
    assert out.count() == 39 + 38 and out.rdd.getNumPartitions() >= 4
