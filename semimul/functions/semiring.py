"""Semirings: a sum, a product and a zero, as Column expressions so that products stay in generated code.

Matrices are triple tables. The left operand is stored by the shared key as (k, i, v), the right one as (k, j, v), a product as (i, j, v).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """`add` folds a column of values; `mul` takes the left and the right value, in that order; entries equal to `zero` are absent (None:
    every stored entry counts). `lazy`: the sum is associative and commutative, so that it may be done in parts and in any order."""

    name: str
    add: Callable[[Column], Column]
    mul: Callable[[Column, Column], Column]
    zero: object = 0
    lazy: bool = True


PLUS_TIMES = Semiring("plus_times", F.sum, lambda a, b: a * b)
OR_AND = Semiring("or_and", F.bool_or, lambda a, b: a & b, False)
MIN_PLUS = Semiring("min_plus", F.min, lambda a, b: a + b, None)
MAX_PLUS = Semiring("max_plus", F.max, lambda a, b: a + b, None)
MAX_TIMES = Semiring("max_times", F.max, lambda a, b: a * b)
MAX_MIN = Semiring("max_min", F.max, F.least, None)
MIN_MAX = Semiring("min_max", F.min, F.greatest, None)
COUNT = Semiring("count", F.sum, lambda a, b: F.lit(1).cast("long"), None)
SET_UNION = Semiring("set_union", lambda c: F.array_sort(F.array_distinct(F.flatten(F.collect_set(c)))), lambda a, b: F.array(a, b), None)
ANY_FIRST = Semiring("any_first", F.min, lambda a, b: a, None)
ANY_SECOND = Semiring("any_second", F.min, lambda a, b: b, None)
#: Values are structs (v, via); the least v wins and takes its witness along.
ARG_MIN = Semiring("arg_min", F.min, lambda a, b: F.struct((a["v"] + b["v"]).alias("v"), a["via"].alias("via")), None)


def gather(fold: Callable[[Column], Column], mul: Callable[[Column, Column], Column] = PLUS_TIMES.mul) -> Semiring:
    """A sum that needs all of a cell's partials at once, as a function of their sorted array."""
    return Semiring("gather", lambda c: fold(F.sort_array(F.collect_list(c))), mul, 0, lazy=False)


BY_NAME = {s.name: s for s in (PLUS_TIMES, OR_AND, MIN_PLUS, MAX_PLUS, MAX_TIMES, MAX_MIN, MIN_MAX, COUNT, SET_UNION, ANY_FIRST, ANY_SECOND, ARG_MIN)}


def _combinations(spark: SparkSession, samples: list) -> DataFrame:
    """(n, a, b, c): all combinations of three samples, numbered."""
    kind = spark.createDataFrame([(x,) for x in samples], "v: long" if all(isinstance(x, int) and not isinstance(x, bool) for x in samples) else None).schema[0].dataType.simpleString()
    rows = [(n, *abc) for n, abc in enumerate(product(samples, repeat=3))]  # the samples are a few values
    return spark.createDataFrame(rows, f"n long, a {kind}, b {kind}, c {kind}").coalesce(1)


def check_semiring(spark: SparkSession, s: Semiring, samples: list | DataFrame) -> DataFrame:
    """One row for each law: whether it holds on all combinations of the sample values (a few, as a list or as a table (v) without repeats),
    and the number of combinations."""
    if isinstance(samples, DataFrame):
        one = lambda name: samples.select(F.col("v").alias(name))
        abc = one("a").crossJoin(one("b")).crossJoin(one("c")).select(F.struct("a", "b", "c").alias("n"), "a", "b", "c").coalesce(1)
    else:
        abc = _combinations(spark, samples)
    z = F.lit(s.zero) if s.zero is not None else None

    def with_sums(df: DataFrame, cells: dict[str, list[Column]]) -> DataFrame:
        """Each named list of cells summed, all lists in one aggregate; the sums come as columns."""
        tagged = F.array(*[F.struct(F.lit(name).alias("name"), F.array(*xs).alias("xs")) for name, xs in cells.items()])
        got = df.select("n", F.inline(tagged)).select("n", "name", F.explode("xs").alias("x")).groupBy("n", "name").agg(s.add(F.col("x")).alias("x"))
        got = got.groupBy("n").agg(F.map_from_entries(F.collect_list(F.struct("name", "x"))).alias("sums"))
        return df.join(got, "n").select(*df.columns, *[F.col("sums")[name].alias(name) for name in cells])

    a, b, c = F.col("a"), F.col("b"), F.col("c")
    df = with_sums(abc, {"ab": [a, b], "ba": [b, a], "bc": [b, c], "split": [s.mul(a, b), s.mul(a, c)]} | ({"az": [a, z]} if z is not None else {}))
    df = with_sums(df, {"ab_c": [F.col("ab"), c], "a_bc": [a, F.col("bc")]})
    laws = {"sum commutes": F.col("ab").eqNullSafe(F.col("ba")), "sum associates": F.col("ab_c").eqNullSafe(F.col("a_bc")), "product distributes": s.mul(a, F.col("bc")).eqNullSafe(F.col("split"))}
    if z is not None:
        laws |= {"zero is neutral": F.col("az").eqNullSafe(a), "zero annihilates": s.mul(a, z).eqNullSafe(z)}
    found = df.agg(F.count(F.lit(1)).alias("n"), *[F.min(v.cast("int")).alias(k) for k, v in laws.items()])
    return found.select("n", F.explode(F.map_from_arrays(F.array(*map(F.lit, laws)), F.array(*laws))).alias("law", "ok")).select("law", (F.col("ok") == 1).alias("holds"), F.col("n").alias("cases"))
