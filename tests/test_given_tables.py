"""Queries that made their data up, or read a table without its rows, follow the given tables; drained streams stay out of the driver."""

import pytest

from semimul.queries import QUERIES
from semimul.streaming import incremental as inc


def tables(spark, path, lines, orders, parts):
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int").write.parquet(f"{path}/lineitem.parquet")
    spark.createDataFrame([(x,) for x in orders], "o_orderkey long").write.parquet(f"{path}/orders.parquet")
    spark.createDataFrame([(x,) for x in parts], "p_partkey long").write.parquet(f"{path}/part.parquet")
    return str(path)


@pytest.fixture(scope="module")
def two(spark, tmp_path_factory):
    """A small set of tables, and a larger one."""
    small = tables(spark, tmp_path_factory.mktemp("small"), [(1, 1, 2, 1), (1, 3, 3, 2)], [1, 2], [1, 2])
    large = tables(spark, tmp_path_factory.mktemp("large"), [(1, 1, 2, 1), (1, 2, 3, 2), (2, 3, 4, 3), (2, 4, 1, 4), (3, 1, 5, 2)], range(1, 400), [1, 2, 3, 4, 5])
    return small, large


@pytest.mark.parametrize("name", ["band_bounds_table", "bfs_levels", "bool_reach2", "choose_bands_table", "even_reach", "power_3", "power_law_edges", "power_law_product", "power_law_sizes", "semiring_laws"])
def test_results_follow_the_tables(spark, two, name):
    small, large = (sorted(map(tuple, QUERIES[name](spark, d).collect()), key=str) for d in two)
    assert small != large


def test_searches_on_the_given_links(spark, two):
    _, d = two
    assert {(r.node, r.level) for r in QUERIES["bfs_levels"](spark, d).collect()} == {(1, 0), (2, 1), (5, 1), (3, 2), (4, 3)}
    assert {r.node for r in QUERIES["bool_reach2"](spark, d).collect()} == {3}
    assert {r.node for r in QUERIES["even_reach"](spark, d).collect()} == {1, 3}


def test_band_bounds_count_the_column(spark, tmp_path):
    """A plain count takes the number of rows from the file's footer, and would count a part without a key."""
    d = tables(spark, tmp_path, [], [], [1, 2, None])
    assert {r.n for r in QUERIES["band_bounds_table"](spark, d).collect()} == {2}


@pytest.mark.parametrize("mode", ["complete", "update"])
def test_drained_streams_are_written_tables(spark, tmp_path, mode):
    spark.range(10).selectExpr("id % 3 AS k").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("k long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in").groupBy("k").count()
    got = inc.drain(stream, "drained", mode)
    assert got.inputFiles()  # a memory table has none, and holds its rows on the driver
    most = {}
    for r in got.collect():
        most[r.k] = max(r["count"], most.get(r.k, 0))
    assert most == {0: 4, 1: 3, 2: 3} and (mode == "update" or got.count() == 3)
