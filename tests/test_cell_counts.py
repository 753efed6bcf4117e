"""Counts of cells that exchange no pair."""

import pytest
from pyspark.sql import functions as F

from semimul.plans import cost
from tests.test_blocks import operands  # noqa: F401


@pytest.mark.parametrize("block_cells, wide", [(1 << 26, 32), (1 << 26, 1), (1 << 26, 10**9), (500, 32), (1, 32)])
def test_cells_are_counted_in_blocks(spark, monkeypatch, operands, block_cells, wide):
    """By rows of flags, by single flags and by sorted numbers, on whole numbers and on texts, with nulls."""
    monkeypatch.setattr(cost, "BLOCK_PRODUCTS", 3000)
    a, b = (t.unionByName(spark.createDataFrame([(None, 1, 1), (3, None, 1), (10**9, 7, 1)], t.schema)) for t in operands)
    want = a.join(b, "k").select("i", "j").dropna().distinct().count()
    assert cost.result_entries(a, b).first()[0] == want
    text = lambda t, c: t.withColumn(c, F.col(c).cast("string")).withColumn("k", F.col("k").cast("string"))
    assert cost.result_entries(text(a, "i"), text(b, "j")).first()[0] == want
    got = 0
    monkeypatch.setattr(cost, "BLOCK_CELLS", block_cells)
    monkeypatch.setattr(cost, "WIDE", wide)
    none = F.lit(None).cast("array<long>")
    rows = a.dropna().groupBy("k").agg(F.collect_list("i").alias("i")).select(F.lit(0).alias("side"), "k", "i", none.alias("j")).unionByName(b.dropna().groupBy("k").agg(F.collect_list("j").alias("j")).select(F.lit(1).alias("side"), "k", none.alias("i"), "j"))
    for t in cost._count_block(rows.toArrow().to_batches()):
        got += t["n"][0].as_py()
    assert got == want
    assert cost.result_entries(a.filter("false"), b).first()[0] == 0


def test_no_pair_is_exchanged_to_count_cells(operands):
    plan = cost.result_entries(*operands)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan
