"""Products that are summed in blocks of the result."""

import numpy as np
import pytest

from semimul import queries
from semimul.operators import blockwise, multiply


def sums(ka, i, va, kb, j, vb):
    out = {}
    for k, x, v in zip(ka, i, va):
        for q in np.flatnonzero(kb == k):
            out[int(x), int(j[q])] = out.get((int(x), int(j[q])), 0) + int(v) * int(vb[q])
    return out


@pytest.mark.parametrize("n_k,n_i,n_j,n,values", [(3, 40, 50, 300, (1, 9)), (60, 30, 40, 500, (-4, 4)), (400, 900, 800, 900, (1, 5)), (5, 9, 8, 60, (2**27, 2**28)), (2, 200, 300, 1500, (-3, 3))])
@pytest.mark.parametrize("at_once", [50, 4_000_000])
def test_cells_of_a_block(monkeypatch, n_k, n_i, n_j, n, values, at_once):
    """Dense and sparse keys, repeated entries, sums of zero, sums beyond 2 ** 53, in pieces and at once."""
    monkeypatch.setattr(blockwise, "AT_ONCE", at_once)
    monkeypatch.setattr(blockwise, "CELLS", at_once)
    r = np.random.default_rng(7)
    side = lambda m: (r.integers(0, n_k, n), r.integers(0, m, n), r.integers(*values, n))
    (ka, i, va), (kb, j, vb) = side(n_i), side(n_j)
    va, vb = np.where(va == 0, 1, va), np.where(vb == 0, 1, vb)
    got = [(int(x), int(y), int(v)) for xs, ys, vs in blockwise.block_cells(ka, i, va, n_i, kb, j, vb, n_j, n_k) for x, y, v in zip(xs, ys, vs)]
    want = sums(ka, i, va, kb, j, vb)
    assert len(got) == len(want) and {(x, y): v for x, y, v in got} == want


def no_exchange_of_products(t) -> bool:
    plan = t._jdf.queryExecution().executedPlan().toString()
    return "MapInArrow" in plan and "keys=[i" not in plan


@pytest.mark.parametrize("name,w", [("outer_terms", "W10"), ("outer_links", "W13"), ("outer_parts_by_customer", "W4"), ("outer_by_hour", "W8"), ("outer_skewed", "W8"), ("outer_tiled", "W8")])
def test_large_products_are_summed_in_blocks(spark, monkeypatch, name, w):
    a = spark.createDataFrame([(f"k{k}", i, (k + i) % 5 - 1) for k in range(6) for i in range(k, 30, 2)], "k string, i long, v long")
    b = a.withColumnRenamed("i", "j")
    monkeypatch.setattr(blockwise, "FROM_PRODUCTS", 10)
    monkeypatch.setattr(queries.build, "workload", lambda *_: (a, b))
    got = queries.QUERIES[name](spark, "")
    assert no_exchange_of_products(got)
    cells = lambda t: sorted(map(tuple, t.select("i", "j", "v").collect()))
    zeros = cells(multiply.outer_product(a, b, expand="join"))
    assert cells(got) == zeros and len(zeros) > 100


def test_vectors_and_json_keys_are_summed_in_blocks(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(blockwise, "FROM_PRODUCTS", 10)
    d, n = str(tmp_path), 90
    vectors = {x: [x % 7 - 3.0, 0.5, (x % 3) - 1.0] for x in range(n)}
    spark.createDataFrame(list(vectors.items()), "vec_id long, embedding array<float>").write.parquet(f"{d}/embeddings.parquet")
    spark.createDataFrame([(x % 31, f'{{"k": {x % 4}}}') for x in range(n)], "user_id long, props string").write.parquet(f"{d}/events.parquet")
    got = queries.QUERIES["dense_vectors_all"](spark, d)
    assert no_exchange_of_products(got)
    assert {(r.i, r.j): r.v for r in got.collect()} == {(i, j): round(1e6 * sum(x * y for x, y in zip(vectors[i], vectors[j]))) for i in vectors for j in vectors}
    got = queries.QUERIES["json_keys"](spark, d)
    assert no_exchange_of_products(got)
    count = lambda k, u: sum(x % 4 == k and x % 31 == u for x in range(n))
    want = {(i, j): sum(count(k, i) * count(k, j) for k in range(4)) for i in range(31) for j in range(31)}
    assert {(r.i, r.j): r.v for r in got.collect()} == {c: v for c, v in want.items() if v}


def test_entries_are_not_copied_for_each_block(spark, monkeypatch):
    """Blocks read written packs: between these and the cells there is no exchange, however many blocks an entry takes part in."""
    monkeypatch.setattr(blockwise, "FROM_PRODUCTS", 10)
    monkeypatch.setattr(blockwise, "TASK_ENTRIES", 40)
    a = spark.createDataFrame([(f"k{k % 7}", i, 1 + (k + i) % 3) for k in range(9) for i in range(k % 4, 90, 3)], "k string, i long, v long")
    b = spark.createDataFrame([(f"k{k}", f"j{j}", 2 - j % 2) for k in range(3, 12) for j in range(k, 60, 2)], "k string, j string, v long")
    got = multiply.outer_product(a, b)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" in plan and "Exchange" not in plan
    cells = lambda t: sorted(map(tuple, t.select("i", "j", "v").collect()))
    assert cells(got) == cells(multiply.outer_product(a, b, expand="join"))
