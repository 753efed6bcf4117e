"""The diagonal mask has no bound of its own."""

from semimul.queries import QUERIES


def test_masks_reach_large_ids(spark, tmp_path):
    spark.createDataFrame([(1, 7, 5), (2, 7, 300_000), (3, 7, 5)], "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(1, 300_000), (2, 5), (3, 8)], "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    cells = lambda name: {(r.i, r.j): r.v for r in QUERIES[name](spark, str(tmp_path)).collect()}
    assert cells("masked") == {(5, 5): 2, (300_000, 300_000): 1}
    assert cells("masked_complement") == {(5, 300_000): 2, (5, 8): 2, (300_000, 5): 1, (300_000, 8): 1}
