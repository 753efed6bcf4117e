"""Split points, progress entries and resumption."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from semimul.functions.semiring import PLUS_TIMES, Semiring
from semimul.operators.multiply import outer_product
from semimul.plans import cost
from semimul.plans.staging import Files, written
from semimul.plans.store import PartialLog


def running_total(t: DataFrame, by: list[str], weight: str, shard: str | None = None) -> DataFrame:
    """`t` with `upto`: the sum of `weight` over the rows up to and with this one, in the order of `by`, for each `shard`. Rows are dealt out by
    ranges of their order; a range's start is the sum of the ranges before it, of which there are as many as partitions, so no task sees
    more than its range."""
    own = [shard] if shard else []
    laid = written(t.repartitionByRange(*own, *by).withColumn("_range", F.spark_partition_id()), "ranges")
    sums = laid.groupBy(*own, "_range").agg(F.sum(weight).alias("_sum"))
    before = sums.withColumn("_before", F.sum("_sum").over(Window.partitionBy(*own).orderBy("_range")) - F.col("_sum")).drop("_sum")
    inside = F.sum(weight).over(Window.partitionBy(*own, "_range").orderBy(*by).rowsBetween(Window.unboundedPreceding, 0))
    return laid.join(F.broadcast(before), [*own, "_range"]).withColumn("upto", F.col("_before") + inside).drop("_range", "_before")


def even_splits(weights: DataFrame, n: int = 2) -> DataFrame:
    """(shard, first): first keys of shards 2 to n, for `weights` (key, w): the first key at which the running weight has reached the shard's
    share."""
    run = running_total(weights, ["key"], "w")
    goals = run.agg(F.sum("w").alias("total")).select("total", F.explode(F.sequence(F.lit(2), F.lit(max(n, 2)))).alias("shard")).filter(F.col("shard") <= n)
    # every key is met with the shares, of which there are as many as shards
    reached = run.select("key", "upto").crossJoin(F.broadcast(goals)).filter(F.col("upto") * n >= (F.col("shard") - 1) * F.col("total"))
    return reached.groupBy("shard").agg(F.min("key").alias("first")).select(F.col("shard").cast("long").alias("shard"), "first")


def split_weights(at: DataFrame, b: DataFrame | None = None) -> DataFrame:
    """(key, w) by entries of a table, or by products with a second one."""
    if b is None:
        return at.groupBy(F.col("k").alias("key")).agg(F.count(F.lit(1)).alias("w"))
    return cost.partial_products_by_key(at, b).select(F.col("k").alias("key"), F.col("pp").alias("w"))


class SplitPlan:
    """Recorded bounds of shards, kept as a small file."""

    def __init__(self, bounds: list):
        self.bounds = sorted(bounds)

    @classmethod
    def of(cls, splits: DataFrame) -> SplitPlan:
        return cls([r["first"] for r in splits.collect()])

    def save(self, spark, path: str) -> None:
        Files(spark).write_json(path, {"bounds": self.bounds})

    @classmethod
    def load(cls, spark, path: str) -> SplitPlan:
        return cls(Files(spark).read_json(path)["bounds"])

    def shard(self, key):
        out = F.lit(1)
        for q, b in enumerate(self.bounds):
            out = F.when(F.col(key) >= F.lit(b), F.lit(q + 2)).otherwise(out)
        return out

    def rewrite(self, t: DataFrame, key: str, path: str) -> DataFrame:
        """The table laid out by shard and sorted inside it."""
        t.withColumn("shard", self.shard(key)).repartition(len(self.bounds) + 1, "shard").sortWithinPartitions(key).write.mode("overwrite").partitionBy("shard").parquet(path)
        return t.sparkSession.read.parquet(path)


def _per_key(at: DataFrame, b: DataFrame, unit: str) -> DataFrame:
    """(k, n): what a shared key counts, in products or in entries read."""
    if unit == "products":
        return cost.partial_products_by_key(at, b).select("k", F.col("pp").alias("n"))
    return cost.degrees(at).withColumnRenamed("degree", "x").join(cost.degrees(b), "k").select("k", (F.col("x") + F.col("degree")).alias("n"))


def monitor(at: DataFrame, b: DataFrame, every: int, *, plan: SplitPlan | None = None, unit: str = "products") -> DataFrame:
    """(shard, last_k, entries): the progress entries that a run will give, from degree tables: one whenever the products (or the entries read)
    of a shard have passed another multiple of `every`. A key whose product is finished is a safe point, so an entry names the key after
    which a run can be taken up. `run_monitored` gives entries of a run as it goes."""
    per = _per_key(at, b, unit).withColumn("shard", plan.shard("k") if plan else F.lit(1))
    upto = running_total(per, ["k"], "n", "shard").withColumnRenamed("upto", "entries")
    crossed = F.floor(F.col("entries") / every) > F.floor((F.col("entries") - F.col("n")) / every)
    return upto.filter(crossed).select(F.col("shard").cast("long").alias("shard"), F.col("k").alias("last_k"), F.col("entries").cast("long").alias("entries"))


def run_monitored(log: PartialLog, at: DataFrame, b: DataFrame, every: int, *, stop_after: int | None = None) -> list[dict]:
    """C += A B in steps of about `every` products, each a run of the log. When a step is committed its progress entry is known: the products
    made so far, as counted while they were made, and the richer key (k, i) of the last entry of A that is done, since a step may end within
    a key. A run that was stopped is taken up by calling this again with the same log: steps that are there are not made again. Entries come
    to the driver one a step, by the caller's choice of `every`. `stop_after` ends the run after so many steps."""
    right = cost.degrees(b).withColumnRenamed("degree", "n")
    per = at.filter("v <> 0").join(right, "k").select("k", "i", "n")
    run = running_total(per, ["k", "i"], "n")
    crossed = F.floor(F.col("upto") / every) > F.floor((F.col("upto") - F.col("n")) / every)
    ends = [(r.k, r.i) for r in run.filter(crossed).orderBy("k", "i").select("k", "i").collect()]
    after = lambda p: (F.col("k") > F.lit(p[0])) | ((F.col("k") == F.lit(p[0])) & (F.col("i") > F.lit(p[1])))
    entries, before = [], None
    done = total = 0
    for q, end in enumerate([*ends, None]):
        if stop_after is not None and q >= stop_after:
            break
        part = at
        part = part if before is None else part.filter(after(before))
        part = part if end is None else part.filter(~after(end))
        seen = Observation()
        partials = outer_product(part, b, log.s, emit="partials").observe(seen, F.count(F.lit(1)).alias("products"))
        made = log.append(partials, f"step-{q}")
        done = seen.get["products"] if made else None
        total = total + done if done is not None and total is not None else None
        if end is not None:
            entries.append({"step": q, "last_k": end[0], "last_i": end[1], "products": done, "entries": total, "resumed": not made})
        before = end
    return entries


def resume_after(at: DataFrame, b: DataFrame, last_k, s: Semiring = PLUS_TIMES, *, i_after=None, emit: str = "partials") -> DataFrame:
    """The rest of a product after key `last_k`; with `i_after`, also what is left of the next key's product beyond that row (the table's
    keys are compared, so the richer key is (k, i))."""
    rest = at.filter(F.col("k") > F.lit(last_k)) if i_after is None else at.filter((F.col("k") > F.lit(last_k)) | ((F.col("k") == F.lit(last_k)) & (F.col("i") > F.lit(i_after))))
    return outer_product(rest, b, s, emit=emit)
