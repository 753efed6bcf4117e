"""The pre-sum cache, local products and the guard of pipelines."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from semimul.functions.semiring import COUNT, MAX_MIN, MIN_PLUS, OR_AND, PLUS_TIMES
from semimul.operators import graph, multiply


def repeated(spark, cells, times):
    return spark.range(cells * times).coalesce(1).select((F.col("id") % cells).alias("i"), F.lit(0).cast("long").alias("j"), F.lit(1).cast("long").alias("v"))


@pytest.mark.parametrize("cache, rows", [(None, 20_000), (50_000, 20_000), (20_000, 20_000), (19_999, None), (10_000, None), (100, 100_000)])
def test_the_cache_outlives_batches(spark, cache, rows):
    """20,000 cells that come five times: a table that holds them all gives each once, smaller ones more often, and never fewer than there are."""
    got = multiply.presum(repeated(spark, 20_000, 5), cache_entries=cache)
    n = got.count()
    assert n == rows if rows else 20_000 < n <= 100_000
    assert multiply.fold(got).filter("v <> 5").isEmpty()


@pytest.fixture(scope="module")
def operands(spark):
    rng = np.random.default_rng(4)
    make = lambda name: spark.createDataFrame([(int(k), int(x), int(v)) for k, x, v in zip(rng.zipf(1.5, 800) % 60, rng.integers(0, 40, 800), rng.integers(1, 9, 800))], f"k long, {name} long, v long").groupBy("k", name).agg(F.max("v").alias("v"))
    return make("i"), make("j")


@pytest.mark.parametrize("s", [PLUS_TIMES, MIN_PLUS, MAX_MIN, COUNT])
def test_local_products_equal_the_outer_product(operands, s):
    a, b = operands
    cells = lambda t: {(r.i, r.j): r.v for r in t.collect()}
    want = cells(multiply.outer_product(a, b, s, expand="join"))
    assert cells(multiply.hybrid_product(a, b, s, bands=3)) == want
    assert cells(multiply.hybrid_product(a, b, s, bands=3, cache_entries=7)) == want
    assert cells(multiply.grid_product(a, b, s, grid=(2, 3))) == want
    assert cells(multiply.inner_product(a, b, s)) == want
    assert cells(multiply.outer_product(a, b, s, tile=(3, 4))) == want
    assert cells(multiply.outer_product(a, b, s, expand="blocks", tile=(3, 4))) == want


def test_local_products_need_a_known_semiring(operands):
    with pytest.raises(ValueError):
        multiply.local_product(*[t.withColumnRenamed("v", x) for t, x in zip(operands, ("av", "bv"))], ["k"], OR_AND, parts=2)


def test_no_second_exchange_in_local_products(operands):
    a, b = operands
    plan = multiply.hybrid_product(a, b, bands=3, n=40, first=0)._jdf.queryExecution().executedPlan().toString()
    assert plan.index("MapInArrow") < plan.index("Exchange hashpartitioning(band")


def test_unsummed_products_are_not_piped_to_any_consumer(operands):
    a, b = operands
    with pytest.raises(AssertionError):
        graph.pipeline_partials(a.toDF("col", "row", "v"), b.toDF("row", "col", "v"), lambda x: x, "i long, j long, v long")


def test_planner_makes_no_product(operands):
    from semimul.plans import cost

    a, b = operands
    got = cost.choose(a, b, broadcast_entries=1)
    assert got["method"] == "summed" and abs(got["n_c"] - cost.result_entries(a, b).first()[0]) < 0.2 * got["n_c"]
    assert multiply.multiply(a, b, method="partials").count() == cost.result_entries(a, b).first()[0]


def test_an_unbounded_cache_merges_seldom(monkeypatch):
    """Rows that go through the sum grow with what is added, not with its square."""
    import pyarrow as pa

    from semimul.operators.multiply import _Cache

    seen, schema = [], pa.schema([("i", pa.int64()), ("j", pa.int64()), ("v", pa.int64())])
    concat = pa.concat_tables
    monkeypatch.setattr(pa, "concat_tables", lambda ts: seen.append(sum(t.num_rows for t in ts)) or concat(ts))
    cache = _Cache(["i", "j"], "sum", schema, None)
    for q in range(64):
        ids = [*range(q * 100, q * 100 + 100), 0]
        assert not list(cache.add(pa.table({"i": ids, "j": ids, "v": [1] * 101}, schema=schema)))
    got = {i: v for b in cache.rest() for i, v in zip(b["i"].to_pylist(), b["v"].to_pylist())}
    assert got == {i: 1 + 64 * (i == 0) for i in range(6400)}
    assert sum(seen) < 10 * 6464
