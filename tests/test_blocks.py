"""Bands that are cut in blocks."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semimul.functions.semiring import MIN_PLUS, PLUS_TIMES
from semimul.operators import multiply


@pytest.fixture(scope="module")
def operands(spark):
    rng = np.random.default_rng(5)
    make = lambda name, n: spark.createDataFrame([(int(k), int(x), int(v)) for k, x, v in zip(rng.zipf(1.4, n) % 90, rng.integers(0, 120, n), rng.integers(1, 9, n))], f"k long, {name} long, v long").groupBy("k", name).agg(F.max("v").alias("v"))
    return make("i", 1500), make("j", 1200)


@pytest.mark.parametrize("s", [PLUS_TIMES, MIN_PLUS])
@pytest.mark.parametrize("cache", [None, 50])
def test_large_bands_are_many_tasks(operands, monkeypatch, s, cache):
    monkeypatch.setattr(multiply, "BAND_PRODUCTS", 500)
    a, b = operands
    cells = lambda t: {(r.i, r.j): r.v for r in t.collect()}
    got = multiply.hybrid_product(a, b, s, bands=2, cache_entries=cache)
    assert cells(got) == cells(multiply.outer_product(a, b, s, expand="join"))
    assert cache or got.rdd.getNumPartitions() > 2
