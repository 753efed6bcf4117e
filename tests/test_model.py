import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from semimul.functions.model import KeyIndex, Shape, TripleTable, encode_keys, live_progress, to_core, to_wide
from semimul.operators.multiply import outer_product


def test_triples_reject_bad_keys(spark):
    t = spark.createDataFrame([(0, 1, 5), (None, 1, 2)], "row long, col long, v long")
    with pytest.raises(PySparkException):
        TripleTable(t).checked().entries.collect()
    with pytest.raises(PySparkException):
        TripleTable(t.filter("row = 0"), Shape(1, 1)).checked().entries.collect()
    assert TripleTable(t.filter("row = 0"), Shape(1, 2)).checked().entries.count() == 1
    with pytest.raises(ValueError):
        TripleTable(t.drop("v"))


def test_wide_round_trip_takes_the_newest(spark):
    t = TripleTable(spark.createDataFrame([("a", "x", 1), ("b", "y", 2)], "row string, col string, v long"))
    old = to_wide(t, "f")
    new = to_wide(TripleTable(t.entries.withColumn("v", F.col("v") * 10)), "f", F.lit("2024-01-01").cast("timestamp"))
    junk = to_wide(t, "other").withColumn("val", F.lit("no number"))
    got = to_core(old.unionByName(new).unionByName(junk), "f")
    assert sorted(map(tuple, got.entries.collect())) == [("a", "x", 10), ("b", "y", 20)]


def test_key_index_is_dense_and_ordered(spark):
    keys = spark.createDataFrame([(f"k{i * 37 % 101:03d}",) for i in range(300)], "key string")
    index = KeyIndex(keys)
    got = [(r.number, r.key) for r in index.table.orderBy("number").collect()]
    assert [n for n, _ in got] == list(range(101)) and [k for _, k in got] == sorted(k for _, k in got)
    t = keys.select(F.col("key").alias("k"), F.lit(1).alias("v")).limit(20)
    assert sorted(map(tuple, index.undo(index.apply(t, "k"), "k").collect())) == sorted(map(tuple, t.collect()))


def test_operands_and_layout(spark):
    t = TripleTable(spark.createDataFrame([(r, c, r + c) for r in range(4) for c in range(3)], "row long, col long, v long"), Shape(4, 3))
    got = outer_product(t.left(), TripleTable(t.laid_out(2).entries.select(F.col("col").alias("row"), F.col("row").alias("col"), "v")).right())
    want = {(i, j): sum((i + c) * (j + c) for c in range(3) if i + c and j + c) for i in range(4) for j in range(4)}
    assert {(r.i, r.j): r.v for r in got.collect()} == want


def test_small_surfaces(spark):
    assert live_progress(spark) == []
    assert spark.range(1).select(encode_keys(F.lit(42), 5).alias("x")).first().x == "00042"
