import pytest
from pyspark.sql import functions as F

from semimul.functions import exact
from semimul.functions import semiring as sr
from semimul.operators import kernels, multiply
from semimul.plans import cost, progress
from semimul.plans.staging import fresh
from semimul.plans.store import PartialLog, multiply_into
from semimul.sources import generate, select


def triples(spark, rows, name):
    return spark.createDataFrame(rows, f"k string, {name} string, v long")


@pytest.fixture(scope="module")
def tiny(spark):
    at = triples(spark, [("k1", "i1", 2), ("k1", "i2", 3), ("k2", "i1", 5), ("k3", "i2", 7)], "i")
    b = triples(spark, [("k1", "j1", 1), ("k1", "j2", 4), ("k2", "j1", 6), ("k4", "j1", 9)], "j")
    return at, b


WANT = {("i1", "j1"): 32, ("i1", "j2"): 8, ("i2", "j1"): 3, ("i2", "j2"): 12}


def cells(df):
    return {(r.i, r.j): r.v for r in df.collect()}


@pytest.mark.parametrize(
    "make",
    [
        lambda a, b: multiply.outer_product(a, b),
        lambda a, b: multiply.fold(multiply.outer_product(a, b, emit="partials")),
        lambda a, b: multiply.fold(multiply.outer_product(a, b, emit="presum", cache_entries=2)),
        lambda a, b: multiply.outer_product(a, b, expand="blocks"),
        lambda a, b: multiply.outer_product(a, b, expand="tiled", tile=(1, 1)),
        lambda a, b: multiply.outer_product(a, b, expand="cogroup"),
        lambda a, b: multiply.inner_product(a, b),
        lambda a, b: multiply.inner_product(a, b, form="dot"),
        lambda a, b: multiply.inner_product(a, b, form="multipass"),
        lambda a, b: multiply.rowwise_product(a, b),
        lambda a, b: multiply.grid_product(a, b, grid=(2, 3)),
        lambda a, b: multiply.multiply(a, b),
        lambda a, b: multiply.client_product(a, b)[0],
        lambda a, b: multiply.client_product(a, b, mode="streaming")[0],
        lambda a, b: multiply.naive_product(a, b),
        lambda a, b: multiply.dense_product(a, b),
    ],
)
def test_all_methods_agree(tiny, make):
    assert cells(make(*tiny)) == WANT


def test_measures(tiny):
    assert cost.partial_products(*tiny).first().pp == 5
    assert cost.result_entries(*tiny).first().n_c == 4
    assert multiply.outer_product(*tiny, emit="partials").count() == 5


def test_zero_rules(spark, tiny):
    at, b = tiny
    stored = at.unionByName(triples(spark, [("k1", "i3", 0)], "i"))
    assert cells(multiply.outer_product(stored, b)) == WANT
    left, right = triples(spark, [("k1", "i1", 1), ("k2", "i1", -1)], "i"), triples(spark, [("k1", "j1", 5), ("k2", "j1", 5)], "j")
    assert cells(multiply.multiply(left, right, method="summed")) == {("i1", "j1"): 0}
    assert cells(multiply.multiply(left, right, method="summed", prune_zero=True)) == {}


def test_empty_disjoint_and_null(spark, tiny):
    at, b = tiny
    none = triples(spark, [], "i")
    assert cells(multiply.outer_product(none, b)) == {}
    assert multiply.outer_product(none, b).columns == ["i", "j", "v"]
    assert cells(multiply.outer_product(triples(spark, [("zz", "i", 1), (None, "i", 1), ("k1", "x", None)], "i"), b)) == {}


@pytest.mark.parametrize("bands", [1, 2, 3, 7, 9])
@pytest.mark.parametrize("execution", ["sequential", "replicated", "broadcast"])
def test_bands_change_nothing(spark, bands, execution):
    at = spark.createDataFrame([(k, i, k * i + 1) for k in range(4) for i in range(1, 8) if (k + i) % 3], "k long, i long, v long")
    b = spark.createDataFrame([(k, j, k - j) for k in range(4) for j in range(5)], "k long, j long, v long")
    assert cells(multiply.hybrid_product(at, b, bands=bands, execution=execution)) == cells(multiply.outer_product(at, b))


def test_band_bounds_cover():
    for n in range(1, 12):
        for p in range(1, 15):
            rows = [r for low, high in cost.band_bounds(n, p) for r in range(low, high + 1)]
            assert rows == list(range(1, n + 1))


def test_choose_bands():
    assert cost.choose_bands(3, 2, 3) == 2
    assert cost.choose_bands(3, 2, 3, "strict") == 3
    assert cost.choose_bands(3, 5, 3) is None
    assert cost.choose_bands(10, 100, 20, "sparse", n_c=100) == 5


def test_lazy_sum_schedules_agree(spark, tiny):
    at, b = tiny
    log = PartialLog(spark, fresh(spark, "t"))
    assert multiply_into(log, at, b, "one")["products"] == 5
    assert multiply_into(log, at, b, "one")["written"] is False
    twice = {k: 2 * v for k, v in WANT.items()}
    log.append(multiply.outer_product(at, b), "two")
    assert cells(log.scan()) == twice
    log.minor_compact(["one", "two"])
    assert cells(log.scan()) == twice
    log.major_compact()
    assert cells(log.live()) == twice
    log.append(multiply.outer_product(at, b, emit="partials"), "three")
    assert cells(log.scan(F.col("i") == "i2")) == {k: 3 * v for k, v in WANT.items() if k[0] == "i2"}


def test_gather_refuses_partial_sums(spark, tiny):
    log = PartialLog(spark, fresh(spark, "t"), sr.gather(lambda vs: F.aggregate(vs, F.lit(0).cast("long"), lambda a, x: x - a)))
    log.append(multiply.outer_product(*tiny, emit="partials"), "one")
    with pytest.raises(ValueError):
        log.minor_compact(["one"])
    assert cells(log.scan())["i1", "j1"] == 28


def test_semiring_check_flags_bad_zero(spark):
    laws = {r.law: r.holds for r in sr.check_semiring(spark, sr.Semiring("min_times", F.min, lambda a, b: a * b, 0), [1, 2, 3]).collect()}
    assert not laws["zero is neutral"] and laws["sum commutes"]


def test_exact_beyond_38_digits(spark):
    at = spark.createDataFrame([("k", "i", "12345678901234567890"), ("m", "i", "99999999999999999999")], "k string, i string, v string").withColumn("v", F.col("v").cast("decimal(38,0)"))
    b = spark.createDataFrame([("k", "j", "98765432109876543210"), ("m", "j", "-99999999999999999999")], "k string, j string, v string").withColumn("v", F.col("v").cast("decimal(38,0)"))
    want = 12345678901234567890 * 98765432109876543210 - 99999999999999999999**2
    assert int(exact.limb_product(at, b, 0, 0).first().v) == want
    from pyspark.sql.types import DecimalType

    assert exact.plan(DecimalType(20, 6), DecimalType(20, 6), 10) is None
    assert exact.plan(DecimalType(10, 2), DecimalType(10, 4), 100) == DecimalType(23, 6)


def test_client_guard(tiny):
    with pytest.raises(multiply.ClientMemoryExceeded):
        multiply.client_product(*tiny, max_entries=3)


def test_transpose_law(spark):
    a = spark.createDataFrame([(r, c, r * 3 + c) for r in range(4) for c in range(3)], "row long, col long, v long")
    b = spark.createDataFrame([(r, c, r - c + 1) for r in range(3) for c in range(5)], "row long, col long, v long")
    left = kernels.transpose(kernels.product(a, b))
    right = kernels.product(kernels.transpose(b), kernels.transpose(a))
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(left) == key(right)


def test_generator_matches_published_sizes(spark):
    a, b = generate.power_law_graph(spark, 10, 1), generate.power_law_graph(spark, 10, 2)
    got = cost.write_amplification(a.select(F.col("row").alias("k"), F.col("col").alias("i"), "v"), kernels.by_row(b)).first()
    assert (got.pp, got.n_c) == (795086, 262706)
    assert abs(got.pp / 804989 - 1) < 0.05 and abs(got.n_c / 269404 - 1) < 0.05


def test_selection_language():
    assert select.parse_selection("a;b..c;d*;..z") == [("point", "a"), ("range", "b", "c"), ("prefix", "d"), ("range", None, "z")]


def test_resume_equals_whole(tiny):
    at, b = tiny
    head = multiply.outer_product(at.filter("k <= 'k1'"), b, emit="partials")
    assert cells(multiply.fold(head.unionByName(progress.resume_after(at, b, "k1")))) == WANT


def test_outer_plan_is_one_pass(tiny):
    at, b = tiny
    plan = multiply.outer_product(at, b)._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "Python" not in plan


def test_inner_is_sorted(tiny):
    assert multiply.is_sorted(multiply.inner_product(*tiny), ["i", "j"])
