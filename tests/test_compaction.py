"""Compaction keeps every orientation that the runs hold."""

import pytest

from semimul.plans.staging import fresh
from semimul.plans.store import PartialLog


@pytest.mark.parametrize("write", ["both", "ct"])
def test_compaction_keeps_each_orientation(spark, write):
    log = PartialLog(spark, fresh(spark, "log"))
    for run, v in (("r0", 2), ("r1", 3), ("r2", 4)):
        log.append(spark.createDataFrame([(1, 10, v), (2, 20, 1)], "i long, j long, v long"), run, write)
    cells = lambda orient: {(r.i, r.j): r.v for r in log.scan(orient=orient).collect()}
    want = {"c": {(1, 10): 9, (2, 20): 3} if write == "both" else {}, "ct": {(10, 1): 9, (20, 2): 3}}
    log.minor_compact(["r0", "r1"])
    assert {o: cells(o) for o in want} == want
    log.major_compact()
    assert {o: cells(o) for o in want} == want


def test_a_crash_between_write_and_commit_changes_nothing(spark, monkeypatch):
    from semimul.plans import staging

    log = PartialLog(spark, fresh(spark, "log"))
    run = spark.createDataFrame([(1, 10, 2)], "i long, j long, v long")
    log.append(run, "r0")
    before = log.manifest()

    def crash(self, path, value):
        raise RuntimeError("the writer died")

    with monkeypatch.context() as m:
        m.setattr(staging.Files, "write_json", crash)
        with pytest.raises(RuntimeError):
            log.append(run, "r1")
        with pytest.raises(RuntimeError):
            log.major_compact()
    again = PartialLog(spark, log.path)
    assert again.manifest() == before and [r.v for r in again.scan().collect()] == [2]
    assert [r.v for r in again.scan(allow_uncommitted=True).collect()] == [4]
    assert again.append(run, "r1") and [r.v for r in again.scan().collect()] == [4]


def test_of_two_writers_one_fails(spark):
    log = PartialLog(spark, fresh(spark, "log"))
    log.append(spark.createDataFrame([(1, 10, 2)], "i long, j long, v long"), "r0")
    stale = log.manifest() | {"generation": 0}
    with pytest.raises(OSError):
        log._commit(stale)
    assert log.manifest()["runs"] == ["r0"]
    log.vacuum([])
    assert log.manifest()["runs"] == ["r0"]


@pytest.mark.parametrize("write", ["both", "ct"])
def test_large_runs_are_compacted_by_ranges(spark, monkeypatch, write):
    """No entry of a large run passes an exchange; cells and sums are the same, negative rows and sums of zero included."""
    from semimul.plans import store

    monkeypatch.setattr(store, "BY_RANGES", 10)
    monkeypatch.setattr(store, "RANGE_ENTRIES", 40)
    monkeypatch.setattr(store, "AT_ONCE", 3)
    monkeypatch.setattr(store, "fold", None)
    log, want = PartialLog(spark, fresh(spark, "log")), {}
    for run in range(3):
        rows = [(x % 13 - 4, x % 7 + run, (x + run) % 5 - 2) for x in range(90)]
        log.append(spark.createDataFrame(rows, "i long, j long, v long").repartition(4), f"r{run}", write)
        for i, j, v in rows:
            want[i, j] = want.get((i, j), 0) + v
    minor = log.minor_compact(["r0", "r1"])
    log.vacuum(["r0", "r1"])
    log.major_compact(prune_zero=write == "ct")
    log.vacuum([minor, "r2"])
    if write == "ct":
        want = {c: v for c, v in want.items() if v}
    else:
        assert {(r.i, r.j): r.v for r in log.live("c").collect()} == want and 0 in want.values()
    got = log.live("ct").collect()
    assert len(got) == len(want) and {(r.j, r.i): r.v for r in got} == want


def test_a_bounded_pre_sum_stays_bounded(spark, monkeypatch):
    """Only a pre-sum without a bound on its cache is made in blocks, and then in the order of columns if that is asked for."""
    from semimul.operators import blockwise, multiply

    monkeypatch.setattr(blockwise, "FROM_PRODUCTS", 10)
    a = spark.createDataFrame([(k, i, 1) for k in range(5) for i in range(20)], "k long, i long, v long")
    made = {c: multiply.outer_product(a, a.withColumnRenamed("i", "j"), emit="presum", cache_entries=c, by="j") for c in (100, None)}
    blocks = {c: "CartesianProduct" in t._jdf.queryExecution().executedPlan().toString() for c, t in made.items()}
    assert blocks == {100: False, None: True}
    assert {(r.i, r.j, r.v) for r in made[None].collect()} == {(i, j, 5) for i in range(20) for j in range(20)}
