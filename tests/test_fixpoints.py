"""Searches end at a fixpoint or with an error, never at a silent limit."""

import pytest

from semimul.operators import graph


def chain(spark, n):
    return spark.createDataFrame([(k, k + 1, 2) for k in range(n)], "row long, col long, v long").coalesce(1)


def start(spark):
    return spark.createDataFrame([(0,)], "node long").coalesce(1)


def test_sssp_goes_on_past_fifty_edges(spark):
    assert {r.node: r.dist for r in graph.sssp(start(spark), chain(spark, 53)).collect()} == {k: 2 * k for k in range(54)}


def test_even_reach_goes_on_past_ten_double_steps(spark):
    assert sorted(r.node for r in graph.even_reach(start(spark), chain(spark, 24)).collect()) == list(range(0, 25, 2))


def test_limits_are_errors(spark):
    with pytest.raises(RuntimeError):
        graph.sssp(start(spark), chain(spark, 4), max_iter=2)
    with pytest.raises(RuntimeError):
        graph.even_reach(start(spark), chain(spark, 8), max_iter=2)
    with pytest.raises(ValueError):
        graph.sssp(start(spark), spark.createDataFrame([(0, 1, 1), (1, 0, -2)], "row long, col long, v long"))
