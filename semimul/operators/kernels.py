"""Graph kernels around the product. Plain matrices are (row, col, v)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from semimul.functions.semiring import COUNT, PLUS_TIMES, Semiring
from semimul.operators.multiply import multiply
from semimul.plans.staging import written


def by_col(t: DataFrame) -> DataFrame:
    """(row, col, v) laid out as the left operand of a product, A's transpose."""
    return t.select(F.col("col").alias("k"), F.col("row").alias("i"), "v")


def by_row(t: DataFrame) -> DataFrame:
    """(row, col, v) laid out as the right operand."""
    return t.select(F.col("row").alias("k"), F.col("col").alias("j"), "v")


def plain(c: DataFrame) -> DataFrame:
    return c.select(F.col("i").alias("row"), F.col("j").alias("col"), "v")


def product(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, **options) -> DataFrame:
    return plain(multiply(by_col(a), by_row(b), s, **{"method": "summed"} | options))


def transpose(t: DataFrame) -> DataFrame:
    return t.select(F.col("col").alias("row"), F.col("row").alias("col"), "v")


def apply(t: DataFrame, f: Callable[[Column], Column]) -> DataFrame:
    return t.select("row", "col", f(F.col("v")).alias("v"))


def select_vals(t: DataFrame, keep: Column) -> DataFrame:
    return t.filter(keep)


def tril(t: DataFrame) -> DataFrame:
    return t.filter("row >= col")


def triu(t: DataFrame) -> DataFrame:
    return t.filter("row <= col")


def reduce_rows(t: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return t.groupBy("row").agg(s.add(F.col("v")).alias("v"))


def reduce_cols(t: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return t.groupBy("col").agg(s.add(F.col("v")).alias("v"))


def reduce_all(t: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return t.agg(s.add(F.col("v")).alias("v"))


def ewise_add(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return a.select("row", "col", "v").unionByName(b.select("row", "col", "v")).groupBy("row", "col").agg(s.add(F.col("v")).alias("v"))


def ewise_mult(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES) -> DataFrame:
    return a.select("row", "col", F.col("v").alias("x")).join(b.select("row", "col", F.col("v").alias("y")), ["row", "col"]).select("row", "col", s.mul(F.col("x"), F.col("y")).alias("v"))


def extract(t: DataFrame, rows: Column | DataFrame | None = None, cols: Column | DataFrame | None = None) -> DataFrame:
    """Submatrix by predicates (pushed to the scan) or by one-column tables of keys (semi-joins)."""
    for name, keys in (("row", rows), ("col", cols)):
        if isinstance(keys, DataFrame):
            t = t.join(keys.toDF(name), name, "left_semi")
        elif keys is not None:
            t = t.filter(keys)
    return t


def assign(t: DataFrame, source: DataFrame, rows: DataFrame, cols: DataFrame) -> DataFrame:
    """`t` with the block of the given row and column keys replaced by `source`."""
    marked = t.join(rows.toDF("row").withColumn("in_row", F.lit(True)), "row", "left").join(cols.toDF("col").withColumn("in_col", F.lit(True)), "col", "left")
    return marked.filter("in_row is null or in_col is null").select("row", "col", "v").unionByName(source.select("row", "col", "v"))


def scale(t: DataFrame, vector: DataFrame, side: str = "left", s: Semiring = PLUS_TIMES) -> DataFrame:
    """Product with a diagonal matrix whose entries are `vector` (key, x)."""
    key = "row" if side == "left" else "col"
    met = t.join(vector.withColumnRenamed("key", key), key)
    return met.select("row", "col", (s.mul(F.col("x"), F.col("v")) if side == "left" else s.mul(F.col("v"), F.col("x"))).alias("v"))


def kron(a: DataFrame, b: DataFrame, s: Semiring = PLUS_TIMES, *, max_entries: int = 10_000_000) -> DataFrame:
    """Kronecker product with keys (row, row2), (col, col2); refused beyond `max_entries` entries."""
    if a.count() * b.count() > max_entries:
        raise ValueError(f"more than {max_entries} entries")
    right = b.select(F.col("row").alias("row2"), F.col("col").alias("col2"), F.col("v").alias("y"))
    return a.crossJoin(right).select("row", "row2", "col", "col2", s.mul(F.col("v"), F.col("y")).alias("v"))


def identity(keys: DataFrame, one=1) -> DataFrame:
    key = F.col(keys.columns[0])
    return keys.select(key.alias("row"), key.alias("col"), F.lit(one).cast("long").alias("v"))


def diag(vector: DataFrame) -> DataFrame:
    return vector.select(F.col("key").alias("row"), F.col("key").alias("col"), F.col("x").alias("v"))


def empty(spark: SparkSession, schema: str = "row long, col long, v long") -> DataFrame:
    return spark.createDataFrame([], schema)


def degrees(t: DataFrame, by: str = "row") -> DataFrame:
    return t.groupBy(by).agg(F.count(F.lit(1)).alias("degree"))


def power(t: DataFrame, n: int, s: Semiring = PLUS_TIMES) -> DataFrame:
    """The n-th power (n >= 1) by squaring; each square is a written table."""
    out, base = None, t
    while n:
        if n & 1:
            out = base if out is None else written(product(out, base, s), "power")
        n >>= 1
        if n:
            base = written(product(base, base, s), "square")
    return out


def triangles(t: DataFrame) -> DataFrame:
    """One row (n): triangles of an undirected graph, whose entries below the diagonal are used: wedges masked by edges."""
    low = t.filter("row > col").select("row", "col", F.lit(1).cast("long").alias("v")).distinct()
    wedges = multiply(by_col(low), by_row(low), COUNT, mask=low.select(F.col("row").alias("i"), F.col("col").alias("j")))
    return wedges.agg(F.coalesce(F.sum("v"), F.lit(0)).cast("long").alias("n"))


def top_k(t: DataFrame, k: int) -> DataFrame:
    """The k greatest cells of each row; ties by column."""
    w = Window.partitionBy("row").orderBy(F.desc("v"), "col")
    return t.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
