"""The client baseline beyond its memory."""

import pytest

from semimul import queries
from semimul.operators import multiply as mul


def test_the_client_goes_on_beyond_its_memory(spark, monkeypatch):
    """What its memory cannot hold at once is merged key by key; the whole mode alone still refuses."""
    a = spark.createDataFrame([(k, i, k + i) for k in range(5) for i in range(6)], "k long, i long, v long")
    b = a.withColumnRenamed("i", "j")
    monkeypatch.setitem(mul.client_product.__kwdefaults__, "max_entries", 10)
    monkeypatch.setattr(queries.build, "workload", lambda *_: (a, b))
    cells = lambda t: sorted(map(tuple, t.select("i", "j", "v").collect()))
    assert cells(queries.QUERIES["client_product"](spark, "")) == cells(mul.naive_product(a, b).filter("v <> 0"))
    with pytest.raises(mul.ClientMemoryExceeded):
        mul.client_product(a, b)


def test_streaming_merges_tables_in_pieces(spark):
    """Keys that go over several pieces, that one side lacks, and that end a side; few runs are read as one table."""
    import pyarrow as pa

    cut = lambda ks, n: iter([pa.table({"k": ks[x:x + n]}) for x in range(0, len(ks), n)])
    for left, right in (([1, 1, 1, 1, 2, 4, 4, 7], [0, 1, 1, 4, 4, 4, 4, 5, 7, 7]), ([1, 2, 3], [3, 3, 3]), ([5], [1, 2, 3]), ([], [1]), ([2, 2, 2], [2])):
        for n in (1, 2, 3, 20):
            seen = [(x["k"].to_pylist(), y["k"].to_pylist()) for x, y in mul._merged(cut(left, n), cut(right, n))]
            for k in set(left) & set(right):
                assert [(x.count(k), y.count(k)) for x, y in seen if k in x or k in y] == [(left.count(k), right.count(k))]
    a = spark.createDataFrame([(f"k{k}", i, k + i) for k in range(40) for i in range(k, k + 7)], "k string, i long, v long")
    b = a.filter("k < 'k35'").withColumnRenamed("i", "j")
    got = mul.client_product(a, b, mode="streaming", flush=20)[0]
    cells = lambda t: sorted(map(tuple, t.select("i", "j", "v").collect()))
    assert cells(got) == cells(mul.naive_product(a, b).filter("v <> 0"))
    assert got._jdf.queryExecution().optimizedPlan().toString().count("Relation [") == 1
