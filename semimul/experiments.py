"""The experiments, each as a table of measurements: python -m semimul.experiments [name ...]"""

from __future__ import annotations

import sys
import time
from math import log2
from statistics import median

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from semimul.operators import graph, kernels, multiply
from semimul.plans import cost, progress, staging
from semimul.plans.staging import fresh
from semimul.plans.store import PartialLog, multiply_into
from semimul.sources import build, generate, select


def _graphs(spark: SparkSession, scale: int, permute: bool = False) -> tuple[DataFrame, DataFrame]:
    made = []
    for seed in (1, 2):
        path = fresh(spark, "graph")
        generate.power_law_graph(spark, scale, seed, permute=permute).write.parquet(path)
        made.append(spark.read.parquet(path))
    return made[0].select(F.col("row").alias("k"), F.col("col").alias("i"), "v"), kernels.by_row(made[1])


def _seconds(f) -> float:
    t = time.perf_counter()
    f()
    return time.perf_counter() - t


def _sink(df: DataFrame) -> int:
    seen = Observation()
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    return seen.get["n"]


def _table(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(r.values()) for r in rows], list(rows[0]))


def _streaming(spark: SparkSession, at: DataFrame, b: DataFrame, shards: int) -> tuple[float, PartialLog, int]:
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(shards))
    try:
        log = PartialLog(spark, fresh(spark, "log"))
        got: dict = {}
        s = _seconds(lambda: got.update(multiply_into(log, at, b, "r")))
        return s, log, got["products"]
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def scaled_problem(spark: SparkSession, scales=range(8, 16), runs: int = 3) -> DataFrame:
    """Rate by input size on one shard, the median of some runs: products, entries after the sum, seconds and products a second of the multiply,
    seconds of the fold; the rate over that of the first size, and the slope of its logarithm from size to size (0: flat)."""
    rows = []
    for scale in scales:
        at, b = _graphs(spark, scale)
        got = [_streaming(spark, at, b, 1) for _ in range(runs if scale < 14 else 1)]
        s, (_, log, pp) = median(x[0] for x in got), got[-1]
        n_c: dict = {}
        fold = _seconds(lambda: n_c.update(n=_sink(log.scan())))
        rate, before = pp / s, rows[-1] if rows else None
        rows.append({"scale": scale, "pp": pp, "after_sum": n_c["n"], "ratio": pp / n_c["n"], "multiply_s": s, "pp_per_s": rate, "fold_s": fold, "over_first": rate / (rows[0]["pp_per_s"] if rows else rate), "slope": log2(rate / before["pp_per_s"]) if before else 0.0})
    return _table(spark, rows)


def fixed_problem(spark: SparkSession, scale: int = 13, shards=(1, 2, 4), runs: int = 3) -> DataFrame:
    """Speed-up by shards over one shard. Inputs are laid out at even split points of their products, the result at those of a recorded run; the
    layout comes before the clock starts."""
    at, b = _graphs(spark, scale)
    _, recorded, _ = _streaming(spark, at, b, shards[0])
    weights = recorded.scan().groupBy(F.col("i").alias("key")).agg(F.count(F.lit(1)).alias("w"))
    rows, first = [], None
    for n in shards:
        plan = progress.SplitPlan.of(progress.even_splits(progress.split_weights(at, b), n))
        out = progress.SplitPlan.of(progress.even_splits(weights, n))
        left, right = (plan.rewrite(t, "k", fresh(spark, "shards")).drop("shard") for t in (at, b))
        got = [_streaming(spark, left, right, n) for _ in range(runs)]
        s, (_, log, pp) = median(x[0] for x in got), got[-1]
        laid = _seconds(lambda: out.rewrite(log.scan(), "i", fresh(spark, "result")))
        first = first or s
        rows.append({"shards": n, "splits": str(plan.bounds), "multiply_s": s, "pp_per_s": pp / s, "speedup": first / s, "fold_into_split_result_s": laid})
    return _table(spark, rows)


def resources(spark: SparkSession, scale: int = 13, shards=(1, 2, 8)) -> DataFrame:
    """Processor time over wall time, and threads of the engine's process, while a product is made on so many shards."""
    at, b = _graphs(spark, scale)
    jvm, rows = spark.sparkContext._jvm, []
    cpu = lambda: jvm.java.lang.ProcessHandle.current().info().totalCpuDuration().get().toMillis() / 1000
    for n in shards:
        _streaming(spark, at, b, n)
        before = cpu()
        s, _, pp = _streaming(spark, at, b, n)
        rows.append({"shards": n, "seconds": s, "cores_busy": (cpu() - before) / s, "threads": jvm.java.lang.management.ManagementFactory.getThreadMXBean().getThreadCount(), "pp_per_s": pp / s})
    return _table(spark, rows)


def write_ceiling(spark: SparkSession, scale: int = 13, shards=(1, 8)) -> DataFrame:
    """Entries a second that the store takes where they need not be made: the products of a finished run, read, and read and written."""
    at, b = _graphs(spark, scale)
    rows = []
    for n in shards:
        made, log, pp = _streaming(spark, at, b, n)
        entries = log.live().coalesce(n)
        read = _seconds(lambda: _sink(entries))
        write = _seconds(lambda: entries.write.parquet(fresh(spark, "copy")))
        rows.append({"shards": n, "entries": pp, "made_and_written_per_s": pp / made, "read_and_written_per_s": pp / write, "written_per_s": pp / max(write - read, 1e-3)})
    return _table(spark, rows)


def against_client(spark: SparkSession, scales=(8, 9, 10, 11, 12)) -> DataFrame:
    """The streaming multiply beside the client baseline, and where the baseline gives up."""
    rows = []
    for scale in scales:
        at, b = _graphs(spark, scale)
        s, _, pp = _streaming(spark, at, b, 1)
        try:
            client = _seconds(lambda: _sink(multiply.client_product(at, b)[0]))
        except multiply.ClientMemoryExceeded:
            client = float("nan")
        rows.append({"scale": scale, "pp": pp, "streaming_s": s, "client_s": client, "client_over_streaming": client / s})
    return _table(spark, rows)


def inner_and_outer(spark: SparkSession, scales=(6, 7, 8)) -> DataFrame:
    rows = []
    for scale in scales:
        at, b = _graphs(spark, scale)
        outer = _seconds(lambda: _sink(multiply.outer_product(at, b)))
        rows.append({"scale": scale, "outer_s": outer, "inner_ordered_s": _seconds(lambda: _sink(multiply.inner_product(at, b))), "inner_dot_s": _seconds(lambda: _sink(multiply.inner_product(at, b, form="dot")))})
    return _table(spark, rows)


def amplification(spark: SparkSession, scales=range(8, 13)) -> DataFrame:
    """Entries that the outer product writes over those that the inner product writes."""
    out = None
    for scale in scales:
        one = cost.write_amplification(*_graphs(spark, scale)).withColumn("scale", F.lit(scale))
        out = one if out is None else out.unionByName(one)
    return out


def band_sweep(spark: SparkSession, scale: int = 9, bands=(1, 2, 4, 8, 64), caches=(100, 1000, 10_000, 100_000, None)) -> DataFrame:
    """Entries written, by number of bands (each band's sums complete, one pass over B for each) and by the size of the pre-sum cache."""
    at, b = _graphs(spark, scale)
    at = at.withColumn("i", F.col("i") + 1)
    pp, n_a, n_b = cost.partial_products(at, b).first()[0], at.count(), b.count()
    rows = []
    for p in bands:
        n: list = []
        rows.append({"method": f"bands {p}", "reads": n_a + p * n_b, "seconds": _seconds(lambda p=p, n=n: n.append(_sink(multiply.hybrid_product(at, b, bands=p)))), "written": n[0], "pp": pp, "written_over_pp": n[0] / pp})
    for c in caches:
        n = []
        rows.append({"method": f"cache {c}", "reads": n_a + n_b, "seconds": _seconds(lambda c=c, n=n: n.append(_sink(multiply.outer_product(at, b, emit="presum", cache_entries=c)))), "written": n[0], "pp": pp, "written_over_pp": n[0] / pp})
    return _table(spark, rows)


def two_step(spark: SparkSession, scale: int = 7) -> DataFrame:
    """The plans of A + A B B, and the tables that each was seen to write on the way."""
    a, b = generate.power_law_graph(spark, scale, 1), generate.power_law_graph(spark, scale, 2)
    rows = []
    for plan in ("staged", "temporary", "fold_into"):
        before = len(staging.WRITTEN)
        s = _seconds(lambda plan=plan: _sink(graph.two_step_union(a, b, plan=plan)))
        rows.append({"plan": plan, "seconds": s, "intermediates": len(staging.WRITTEN) - before})
    return _table(spark, rows)


def singletons(spark: SparkSession, sf_dir: str = "/root/testdata/sf0.01", counts=(10, 1000, 10_000)) -> DataFrame:
    """Products of so many selected keys, taken as a table."""
    at, b = build.workload(spark, sf_dir, "W2")
    keys = build.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("key")).orderBy(F.xxhash64("o_orderkey"))
    return _table(spark, [{"keys": n, "seconds": _seconds(lambda n=n: got.append(_sink(multiply.outer_product(select.select_rows(at, keys.limit(n)), b)))), "entries": got[-1]} for got in ([],) for n in counts])


def monitoring(spark: SparkSession, scale: int = 11, steps=(1, 4, 16)) -> DataFrame:
    """A product appended to a log in so many steps, each of which reports its products when it is done, against one that reports nothing."""
    at, b = _graphs(spark, scale)
    pp, plain = cost.partial_products(at, b).first()[0], _streaming(spark, at, b, 8)[0]
    rows = []
    for n in steps:
        log, got = PartialLog(spark, fresh(spark, "log")), []
        s = _seconds(lambda log=log, got=got, n=n: got.extend(progress.run_monitored(log, at, b, pp // n + 1)))
        rows.append({"steps": n, "entries_reported": len(got), "last_report": got[-1]["entries"] if got else 0, "pp": pp, "plain_s": plain, "monitored_s": s})
    return _table(spark, rows)


def permutation(spark: SparkSession, scale: int = 10) -> DataFrame:
    """Permuted inputs lose the shared heavy rows, and the product gets sparser."""
    out = None
    for permute in (False, True):
        one = cost.write_amplification(*_graphs(spark, scale, permute)).withColumn("permuted", F.lit(permute))
        out = one if out is None else out.unionByName(one)
    return out


EXPERIMENTS = {f.__name__: f for f in (scaled_problem, fixed_problem, resources, write_ceiling, against_client, inner_and_outer, amplification, band_sweep, two_step, singletons, monitoring, permutation)}


def main(names: list[str]) -> None:
    spark = SparkSession.builder.config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in names or EXPERIMENTS:
        print(name)
        EXPERIMENTS[name](spark).show(50, truncate=False)


if __name__ == "__main__":
    main(sys.argv[1:])
