"""The data model: triples, the wide form with five key parts, string-coded values, and whole-number keys."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Wide entries: a key of five parts and an uninterpreted value.
WIDE = "row string, family string, col string, visibility string, ts timestamp, val string"


@dataclass(frozen=True)
class Shape:
    rows: int | None = None
    cols: int | None = None


@dataclass
class TripleTable:
    """A matrix as (row, col, v): its entries, and its shape where the key space is closed."""

    entries: DataFrame
    shape: Shape = Shape()

    def __post_init__(self):
        missing = {"row", "col", "v"} - set(self.entries.columns)
        if missing:
            raise ValueError(f"columns missing: {sorted(missing)}")
        for name in ("row", "col"):
            if isinstance(self.entries.schema[name].dataType, (T.MapType, T.ArrayType, T.VariantType)):
                raise ValueError(f"{name} cannot be a key")
        self.entries = self.entries.select("row", "col", "v")

    def checked(self) -> TripleTable:
        """Fails, when it is read, on a null key or one outside the shape; otherwise the same table."""
        bad = F.col("row").isNull() | F.col("col").isNull()
        for name, n in (("row", self.shape.rows), ("col", self.shape.cols)):
            if n is not None:
                bad = bad | ~F.col(name).between(0, n - 1)
        row = F.when(bad, F.raise_error(F.lit("null key, or a key outside the shape")).cast(self.entries.schema["row"].dataType)).otherwise(F.col("row"))
        return TripleTable(self.entries.withColumn("row", row), self.shape)

    def left(self) -> DataFrame:
        """Laid out as a product's left operand (its transpose), by a rename."""
        return self.entries.select(F.col("col").alias("k"), F.col("row").alias("i"), "v")

    def right(self) -> DataFrame:
        return self.entries.select(F.col("row").alias("k"), F.col("col").alias("j"), "v")

    def laid_out(self, shards: int) -> TripleTable:
        """Sorted inside ranges of rows, as shards of a sorted store."""
        return TripleTable(self.entries.repartitionByRange(shards, "row").sortWithinPartitions("row", "col"), self.shape)


def to_core(wide: DataFrame, family: str | None = None, newest: bool = True, value: str = "long") -> TripleTable:
    """Wide entries as triples: of one family if named, the newest version of each cell, the value decoded (entries that do not parse go)."""
    t = wide if family is None else wide.filter(F.col("family") == family)
    got = t.select("row", "col", "ts", F.col("val").try_cast(value).alias("v")).filter("v is not null")
    if newest:
        got = got.groupBy("row", "col").agg(F.max_by("v", "ts").alias("v"))
    return TripleTable(got.select("row", "col", "v"))


def to_wide(t: TripleTable, family: str = "", ts: Column | None = None) -> DataFrame:
    now = ts if ts is not None else F.lit("1970-01-01 00:00:00").cast("timestamp")
    return t.entries.select(F.col("row").cast("string").alias("row"), F.lit(family).alias("family"), F.col("col").cast("string").alias("col"), F.lit("").alias("visibility"), now.alias("ts"), F.col("v").cast("string").alias("val"))


def encode_keys(low_first: Column, width: int = 19) -> Column:
    """Whole-number keys as strings that sort as the numbers do (non-negative)."""
    return F.lpad(low_first.cast("string"), width, "0")


class KeyIndex:
    """A dictionary of keys to whole numbers from 0, without gaps, in key order. Positions are counted by range partition: a partition's
    offset is the number of keys before it, so no task sees all keys."""

    def __init__(self, keys: DataFrame):
        name = keys.columns[0]
        spread = keys.select(F.col(name).alias("key")).filter("key is not null").distinct().repartitionByRange("key").withColumn("part", F.spark_partition_id())
        from semimul.plans.staging import written

        spread = written(spread, "keys")
        before = spread.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("first"))
        offsets = before.withColumn("offset", F.coalesce(F.sum("n").over(Window.orderBy("first").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("part", "offset")
        own = F.row_number().over(Window.partitionBy("part").orderBy("key")) - 1
        self.table = spread.withColumn("own", own).join(offsets, "part").select("key", (F.col("own") + F.col("offset")).cast("long").alias("number"))

    def apply(self, t: DataFrame, column: str) -> DataFrame:
        """`t` with the keys in `column` as numbers; rows with unknown keys go."""
        return t.join(self.table.withColumnRenamed("key", column), column).withColumn(column, F.col("number")).drop("number").select(*t.columns)

    def undo(self, t: DataFrame, column: str) -> DataFrame:
        return t.withColumnRenamed(column, "number").join(self.table, "number").withColumn(column, F.col("key")).select(*t.columns)


def live_progress(spark: SparkSession) -> list[dict]:
    """Running stages and how many of their tasks are done, from the status tracker."""
    tracker = spark.sparkContext.statusTracker()
    found = [(s, tracker.getStageInfo(s)) for s in tracker.getActiveStageIds()]
    return [{"stage": s, "tasks": i.numTasks, "done": i.numCompletedTasks, "failed": i.numFailedTasks} for s, i in found if i]
