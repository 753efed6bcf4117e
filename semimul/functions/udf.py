"""Products and sums by user functions, and the SQL surface."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from semimul.functions.semiring import BY_NAME, PLUS_TIMES, Semiring
from semimul.operators.multiply import fold, outer_product, presum


def with_arrow_mul(f, returns: str = "long") -> Semiring:
    """Sum of products by a vectorised user function of two pandas series."""
    def mul(a: pd.Series, b: pd.Series) -> pd.Series:
        return f(a, b)

    return Semiring("arrow_mul", F.sum, F.pandas_udf(mul, returns), None)


def udaf_fold(partials: DataFrame, f, returns: str = "long") -> DataFrame:
    """Cells folded by a user function of a pandas series, all partials of a cell together."""
    def run(v: pd.Series) -> int:
        return f(v)

    run.__annotations__ = {"v": pd.Series, "return": int}
    return partials.groupBy("i", "j").agg(F.pandas_udf(run, returns, F.PandasUDFType.GROUPED_AGG)("v").alias("v"))


def reduce_fold(partials: DataFrame, start: Column, step) -> DataFrame:
    """Cells folded by a Column function over their sorted partials."""
    return partials.groupBy("i", "j").agg(F.sort_array(F.collect_list("v")).alias("vs")).select("i", "j", F.aggregate("vs", start, step).alias("v"))


class OuterRows:
    """Table function over rows (k, side, x, v) of one key: the product of its rows of side a with those of side b."""

    def __init__(self):
        self.a, self.b = [], []

    def eval(self, row):
        (self.a if row["side"] == "a" else self.b).append((row["x"], row["v"]))

    def terminate(self):
        for i, x in self.a:
            for j, y in self.b:
                yield i, j, x * y


def register(spark: SparkSession) -> None:
    """Makes outer_rows(TABLE(t) PARTITION BY k) known to SQL."""
    spark.udtf.register("outer_rows", F.udtf(OuterRows, returnType="i: string, j: string, v: bigint"))


def sql_multiply(spark: SparkSession, left: str, right: str, semiring: str = "plus_times", view: str = "product") -> str:
    """Registers the product of two views (k, i, v) and (k, j, v) as a view and returns its name."""
    outer_product(spark.table(left), spark.table(right), BY_NAME[semiring]).createOrReplaceTempView(view)
    return view


def arrow_presum(partials: DataFrame, cache_entries: int | None = 100_000) -> DataFrame:
    """A partition operator that sums in a table it keeps from batch to batch, and then the cells."""
    return fold(presum(partials, PLUS_TIMES, cache_entries))
