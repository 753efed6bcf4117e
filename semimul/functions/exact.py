"""Exact decimal products: a precision plan where 38 digits suffice, limbs of nine digits beyond."""

from __future__ import annotations

import math
from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

BASE = 10**9


def plan(left: T.DecimalType, right: T.DecimalType, products: int) -> T.DecimalType | None:
    """The type that holds sums of so many products without loss, or None where 38 digits are too few."""
    digits = left.precision + right.precision + 1 + max(0, math.ceil(math.log10(max(products, 1))))
    return T.DecimalType(digits, left.scale + right.scale) if digits <= 38 else None


def narrow(df: DataFrame, name: str) -> T.DecimalType:
    """The least decimal type of the column's scale that holds its greatest absolute value."""
    kind = df.schema[name].dataType
    top = df.agg(F.max(F.abs(name))).first()[0] or Decimal(0)
    whole = len(str(int(top))) if top else 0
    return T.DecimalType(max(1, whole + kind.scale), kind.scale)


def exact_mul(a: Column, b: Column, out: T.DecimalType) -> Column:
    """Product cast to the planned type; operands are widened first so that Spark keeps the whole scale."""
    return (a * b).cast(out)


def limbs(value: Column, scale: int, count: int = 5) -> Column:
    """Unscaled absolute value of a decimal column as `count` limbs in base 10^9, lowest first, each with the value's sign."""
    unscaled = F.regexp_replace(F.abs(value).cast(T.DecimalType(38, scale)).cast("string"), r"\.", "")
    padded = F.lpad(unscaled, 9 * count, "0")
    sign = F.when(value < 0, F.lit(-1)).otherwise(F.lit(1)).cast("long")
    return F.array(*[F.substring(padded, 9 * (count - 1 - i) + 1, 9).cast("long") * sign for i in range(count)])


def limb_product(at: DataFrame, b: DataFrame, left_scale: int, right_scale: int, count: int = 5) -> DataFrame:
    """(i, j, v): exact sums of products as decimal strings of scale left + right, for operands and sums beyond 38 digits. Products are
    summed by weight class as 38-digit decimals, an associative sum that parts and merges; carries are done once at the end."""
    l = at.select("k", "i", F.posexplode(limbs(F.col("v"), left_scale, count)).alias("p", "x")).filter("x <> 0")
    r = b.select("k", "j", F.posexplode(limbs(F.col("v"), right_scale, count)).alias("q", "y")).filter("y <> 0")
    parts = l.join(r, "k").groupBy("i", "j", (F.col("p") + F.col("q")).alias("w")).agg(F.sum((F.col("x") * F.col("y")).cast("decimal(38,0)")).alias("s"))
    scale = left_scale + right_scale

    @F.udf("string")
    def carried(cells):
        total = sum(int(c["s"]) * BASE ** c["w"] for c in cells)
        return str(Decimal(total).scaleb(-scale)) if abs(total) < 10**28 else f"{'-' if total < 0 else ''}{abs(total) // 10**scale}" + (f".{abs(total) % 10**scale:0{scale}d}" if scale else "")

    return parts.groupBy("i", "j").agg(F.collect_list(F.struct("w", "s")).alias("cells")).select("i", "j", carried("cells").alias("v"))
