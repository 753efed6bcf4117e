"""Large bands and grids: entries are packed once within their group, and no copy, product or sum passes an exchange."""

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semimul.functions.semiring import COUNT, MAX_TIMES, MIN_MAX, MIN_PLUS, PLUS_TIMES
from semimul.operators import blockwise, multiply
from semimul.plans import cost
from tests.test_blocks import operands  # noqa: F401


def cells(t) -> list:
    return sorted(map(tuple, t.select("i", "j", "v").collect()))


def exchanges_nothing(t) -> bool:
    plan = t._jdf.queryExecution().executedPlan().toString()
    return "CartesianProduct" in plan and "Exchange" not in plan


@pytest.mark.parametrize("s", [PLUS_TIMES, MIN_PLUS, MAX_TIMES, MIN_MAX, COUNT])
@pytest.mark.parametrize("options", [{"bands": 1}, {"bands": 8}, {"bands": 3, "cache_entries": 20}, {"bands": 3, "bounds": [(0, 3), (4, 60), (61, 119)]}])
def test_large_bands_are_packed_once(operands, monkeypatch, s, options):  # noqa: F811
    monkeypatch.setattr(multiply, "BAND_PRODUCTS", 300)
    monkeypatch.setattr(blockwise, "GROUP_ENTRIES", 400)
    a, b = operands
    got = multiply.hybrid_product(a, b, s, **options)
    assert exchanges_nothing(got)
    assert cells(got) == cells(multiply.outer_product(a, b, s, expand="join"))


@pytest.mark.parametrize("s", [PLUS_TIMES, MIN_PLUS])
def test_large_grids_are_packed_once(operands, monkeypatch, s):  # noqa: F811
    monkeypatch.setattr(multiply, "BAND_PRODUCTS", 300)
    a, b = operands
    got = multiply.grid_product(a, b, s)
    assert exchanges_nothing(got)
    assert cells(got) == cells(multiply.outer_product(a, b, s, expand="join"))


def test_sums_that_may_overflow_take_the_other_way(spark, operands, monkeypatch):  # noqa: F811
    monkeypatch.setattr(multiply, "BAND_PRODUCTS", 300)
    a, b = operands
    big = a.withColumn("v", a["v"] * 2**58)
    assert not exchanges_nothing(multiply.hybrid_product(big, b, bands=2))


def test_bounded_blocks_hold_few_cells():
    """Cells wait until they are more than the bound, and none is lost."""
    import numpy as np

    some = [tuple(np.arange(q, q + n) for _ in "ijv") for q, n in ((0, 3), (3, 1), (4, 6), (10, 2))]
    got = list(blockwise._held(iter(some), 3))
    assert [len(x[2]) for x in got] == [4, 6, 2]
    assert np.concatenate([x[0] for x in got]).tolist() == list(range(12))


@pytest.mark.parametrize("counted, block_cells", [(4_000_000, 1 << 26), (200, 500), (200, 1)])
@pytest.mark.parametrize("text", [False, True])
def test_cells_are_counted_from_packs(operands, monkeypatch, counted, block_cells, text):  # noqa: F811
    """In pieces and at once, by flags and by sorted numbers; nothing but the count is left."""
    monkeypatch.setattr(blockwise, "COUNTED", counted)
    monkeypatch.setattr(cost, "BLOCK_CELLS", block_cells)
    a, b = ((t.withColumn("k", F.col("k").cast("string")).withColumn(c, F.col(c).cast("string")) if text else t).drop("v") for t, c in zip(operands, "ij"))
    met = blockwise.count_in_blocks(a, b, 10_000)
    monkeypatch.setattr(blockwise, "_met_packs", lambda x, y: x.toDF(*(f"a_{c}" for c in blockwise.PACK)).crossJoin(y.toDF(*(f"b_{c}" for c in blockwise.PACK))))
    plan = met._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
    want = a.join(b, "k").select("i", "j").distinct().count()
    assert sum(r.n for r in met.collect()) == want
    here = blockwise._met_packs(blockwise._packs(a.withColumn("v", F.lit(1).cast("byte")), "i", "v", 2, a.schema["i"].dataType, T.ByteType()), blockwise._packs(b.withColumn("v", F.lit(1).cast("byte")), "j", "v", 2, b.schema["j"].dataType, T.ByteType()))
    assert sum(x["n"][0].as_py() for x in blockwise._count(here.toArrow().to_batches())) == want


def test_a_large_count_leaves_no_copies(operands, monkeypatch):  # noqa: F811
    monkeypatch.setattr(cost, "BLOCK_PRODUCTS", 3000)
    monkeypatch.setattr(cost, "BLOCK_CELLS", 1000)
    a, b = operands
    got = cost.result_entries(a.groupBy("k", "i").count(), b.groupBy("k", "j").count())
    assert "MapInArrow" not in got._jdf.queryExecution().executedPlan().toString()
    assert got.first()[0] == a.join(b, "k").select("i", "j").distinct().count()
