"""Power-law graphs by recursive quadrants, from whole-number arithmetic that any SQL engine repeats exactly."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

M = (1 << 31) - 1


def power_law_edges(spark: SparkSession, scale: int, seed: int, edges_per_vertex: int = 16, numbers: DataFrame | None = None) -> DataFrame:
    """(row, col) of each edge, repeats included, on 2 ** scale vertices. Each bit of an edge's end points is drawn by a mixing function of the
    edge's number, the bit and the seed; quadrant shares are .57, .19, .19 and .05. The edges' numbers
    are those of the table `numbers` (e), each once, or `edges_per_vertex` for each vertex."""
    numbers = spark.range(edges_per_vertex << scale).select(F.col("id").alias("e")) if numbers is None else numbers
    bits = numbers.select("e", F.explode(F.sequence(F.lit(0), F.lit(scale - 1))).alias("b"))
    x = F.lit(0).cast("long")
    inputs = (F.col("e") % M, F.col("b") * F.lit(7368787).cast("long") + 15485863 * seed, F.call_function("div", F.col("e"), F.lit(M).cast("long")) * 32452843 + 49979687 * seed)
    step = bits.withColumn("x", x)
    for n in inputs:
        step = step.withColumn("x", (F.col("x") * 48271 + n + 12345) % M)
        step = step.withColumn("x", F.col("x").bitwiseXOR(F.call_function("div", F.col("x"), F.lit(65536).cast("long"))))
        step = step.withColumn("x", (F.col("x") * F.col("x") % M + F.col("x") * 69621) % M)
    u = F.col("x") % 10000
    weight = F.expr("shiftleft(1L, b)")
    drawn = step.select("e", F.when(u >= 7600, weight).otherwise(F.lit(0)).alias("r"), F.when(((u >= 5700) & (u < 7600)) | (u >= 9500), weight).otherwise(F.lit(0)).alias("c"))
    return drawn.groupBy("e").agg(F.sum("r").alias("row"), F.sum("c").alias("col")).select("row", "col")


def power_law_graph(spark: SparkSession, scale: int, seed: int, edges_per_vertex: int = 16, permute: bool = False, numbers: DataFrame | None = None) -> DataFrame:
    """(row, col, v) with v = 1 for each distinct edge. Unpermuted, the first rows are the heaviest; `permute` spreads them by an odd
    multiplier modulo the number of vertices."""
    got = power_law_edges(spark, scale, seed, edges_per_vertex, numbers).distinct()
    if permute:
        n = 1 << scale
        move = lambda c: (F.col(c) * (40503 + 2 * seed) + 12289 * seed) % n  # noqa: E731  (the multiplier is odd)
        got = got.select(move("row").alias("row"), move("col").alias("col"))
    return got.withColumn("v", F.lit(1).cast("long"))


def sql(scale: int, seed: int, edges_per_vertex: int = 16, numbers: str | None = None) -> str:
    """The same edges as a query for other engines (distinct rows row, col)."""
    mix = lambda x: f"SELECT e, b, ((x * x) % {M} + x * 69621) % {M} AS x FROM (SELECT e, b, xor(x, x // 65536) AS x FROM ({x}))"
    q = f"SELECT e, b, (e % {M} + 12345) % {M} AS x FROM {f'({numbers})' if numbers else f'range({edges_per_vertex << scale})'} r(e), range({scale}) s(b)"
    q = mix(q)
    q = mix(f"SELECT e, b, (x * 48271 + b * 7368787 + {15485863 * seed} + 12345) % {M} AS x FROM ({q})")
    q = mix(f"SELECT e, b, (x * 48271 + (e // {M}) * 32452843 + {49979687 * seed} + 12345) % {M} AS x FROM ({q})")
    return f"SELECT DISTINCT row, col FROM (SELECT e, sum(CASE WHEN u >= 7600 THEN 1::BIGINT << b ELSE 0 END)::BIGINT AS row, sum(CASE WHEN (u >= 5700 AND u < 7600) OR u >= 9500 THEN 1::BIGINT << b ELSE 0 END)::BIGINT AS col FROM (SELECT e, b, x % 10000 AS u FROM ({q})) GROUP BY e)"
