import pytest

from semimul.sources import matrix_market, select


def test_matrix_market_round_trip(spark, tmp_path):
    matrix_market.register(spark)
    t = spark.createDataFrame([(1, 2, 3.5), (4, 1, -2.0), (3, 3, 1e20)], "row long, col long, v double")
    path = str(tmp_path / "m")
    t.write.format("matrix_market").option("path", path).mode("overwrite").save()
    assert sorted(map(tuple, spark.read.format("matrix_market").option("path", path).load().collect())) == sorted(map(tuple, t.collect()))


def test_matrix_market_symmetric_pattern(spark, tmp_path):
    (tmp_path / "s.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n% remark\n3 3 2\n2 1\n3 3\n")
    matrix_market.register(spark)
    got = sorted(map(tuple, spark.read.format("matrix_market").option("path", str(tmp_path / "s.mtx")).load().collect()))
    assert got == [(1, 2, 1.0), (2, 1, 1.0), (3, 3, 1.0)]


@pytest.mark.parametrize("kind", ["parquet", "orc", "json", "csv"])
def test_table_source(spark, tmp_path, kind):
    t = spark.createDataFrame([(k, k % 7, k * 2) for k in range(100)], "k long, i long, v long")
    path = str(tmp_path / kind)
    t.write.format(kind).save(path)
    source = select.TableSource(kind, path, {"password": "never shown"}, "k long, i long, v long")
    assert "never shown" not in repr(source)
    got = source.scan(spark, rows="3..5;50;98..", cols="0..3")
    assert sorted(r.k for r in got.collect()) == [k for k in (3, 4, 5, 50, 98, 99) if k % 7 <= 3]


def test_row_selection_reaches_the_scan(spark, tmp_path):
    spark.range(1000).selectExpr("id AS k", "id AS i", "id AS v").write.parquet(str(tmp_path / "p"))
    plan = select.TableSource("parquet", str(tmp_path / "p")).scan(spark, rows="10..20")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "GreaterThanOrEqual(k,10)" in plan


def test_range_table(spark):
    t = spark.range(5000).selectExpr("id AS k", "id AS i", "id AS v")
    ranges = spark.createDataFrame([(5, 7), (6, 9), (2000, 2001), (1020, 1030)], "low long, high long")
    assert sorted(r.k for r in select.select_rows(t, ranges).collect()) == [5, 6, 7, 8, 9, *range(1020, 1031), 2000, 2001]
