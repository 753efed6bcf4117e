"""Row and column subsets: a small language for keys, tables of ranges, and tables elsewhere."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def parse_selection(text: str, kind: str = "string") -> list[tuple]:
    """`a;b` single keys, `lo..hi` a range with both ends (either may be empty), `pre*` a prefix. kind: `string` or `long`."""
    cast = int if kind == "long" else str
    out: list[tuple] = []
    for part in filter(None, (p.strip() for p in text.split(";"))):
        if ".." in part:
            low, high = part.split("..", 1)
            out.append(("range", cast(low) if low else None, cast(high) if high else None))
        elif part.endswith("*"):
            out.append(("prefix", part[:-1]))
        else:
            out.append(("point", cast(part)))
    return out


def predicate(text: str, column: str, kind: str = "string") -> Column:
    """The selection as one predicate that Spark pushes to the scan: points as IN, ranges as comparisons, prefixes as STARTS WITH."""
    c, out = F.col(column), F.lit(False)
    points = [p[1] for p in parse_selection(text, kind) if p[0] == "point"]
    if points:
        out = c.isin(points)
    for p in parse_selection(text, kind):
        if p[0] == "range":
            one = F.lit(True)
            one = one if p[1] is None else one & (c >= F.lit(p[1]))
            one = one if p[2] is None else one & (c <= F.lit(p[2]))
            out = out | one
        elif p[0] == "prefix":
            out = out | c.startswith(p[1])
    return out


def select_rows(t: DataFrame, rows: str | DataFrame, column: str = "k", kind: str = "long") -> DataFrame:
    """Rows by a selection text, by a table of single keys (key), or by one of ranges (low, high). Tables are joined, however many keys they
    hold: single keys by a semi-join, ranges by the buckets that they touch."""
    if isinstance(rows, str):
        return t.filter(predicate(rows, column, kind))
    if rows.columns == ["key"]:
        return t.join(rows.withColumnRenamed("key", column), column, "left_semi")
    return range_join(t, rows, column)


#: Keys of a block hold so many bits less from one size of block to the next.
_BLOCK_BITS = 8


def range_join(t: DataFrame, ranges: DataFrame, column: str) -> DataFrame:
    """Rows of `t` whose whole-number key lies in any of the ranges (low, high). A range is laid out in blocks of 1, 256, 256 ** 2 ... keys, few
    of each size however wide it is; each distinct key of `t` looks for its block of every size that occurs, and the found keys pick the
    rows."""
    bits, kind = _BLOCK_BITS, "array<struct<q: int, block: bigint>>"
    up, down = f"shiftleft(shiftright(s.l + {(1 << bits) - 1}, {bits}), {bits})", f"shiftleft(shiftright(s.r, {bits}), {bits})"
    left = f"least({up}, s.r)"
    right = f"greatest({down}, {left})"
    piece = lambda a, z: f"IF({a} < {z}, transform(sequence({a}, {z} - 1), x -> named_struct('q', q, 'block', x)), CAST(array() AS {kind}))"
    step = f"named_struct('l', shiftright({left}, {bits}), 'r', shiftright({right}, {bits}), 'out', CAST(concat(s.out, {piece('s.l', left)}, {piece(right, 's.r')}) AS {kind}))"
    blocks = F.expr(f"aggregate(sequence(0, {63 // bits}), named_struct('l', low, 'r', high, 'out', CAST(array() AS {kind})), (s, q) -> IF(s.l >= s.r, s, {step})).out")
    cut = ranges.select(F.col("low").cast("long").alias("low"), (F.col("high").cast("long") + 1).alias("high")).filter("low < high")
    cut = cut.select(F.inline(blocks)).distinct()
    sizes = F.broadcast(cut.select("q").distinct())  # nine at most
    keys = t.select(F.col(column).alias("_key")).distinct().crossJoin(sizes).withColumn("block", F.expr(f"shiftright(CAST(_key AS BIGINT), q * {bits})"))
    found = keys.join(cut, ["q", "block"], "left_semi").select("_key").distinct()
    return t.join(found, F.col(column) == F.col("_key"), "left_semi")


def select_cols(t: DataFrame, keys: str, column: str = "i", kind: str = "long", transposed: DataFrame | None = None) -> DataFrame:
    """Columns by a selection: a filter over the whole table, or, where a copy laid out by column is given, a pushed range of that copy."""
    return (transposed if transposed is not None else t).filter(predicate(keys, column, kind))


@dataclass
class TableSource:
    """A table to be read, perhaps from another store with its own options. Options are handed to the reader and never shown."""

    format: str = "parquet"
    path: str | None = None
    options: dict = field(default_factory=dict, repr=False)
    schema: str | None = None

    def scan(self, spark: SparkSession, rows: str | DataFrame | None = None, cols: str | None = None, kind: str = "long") -> DataFrame:
        reader = spark.read.format(self.format).options(**self.options)
        reader = reader.schema(self.schema) if self.schema else reader
        t = reader.load(self.path) if self.path else reader.load()
        t = t if rows is None else select_rows(t, rows, "k", kind)
        return t if cols is None else select_cols(t, cols, [c for c in t.columns if c in ("i", "j")][0], kind)
