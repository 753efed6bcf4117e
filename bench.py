"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Products of the given tables, and products of generated power-law graphs by SCALE with the partial products a second of the streaming
multiply (partials written to a log, the sum not included; median of three runs to SCALE 13), of the fold, and of the client baseline, which
inserts its result into a table.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from semimul.operators import kernels, multiply
from semimul.plans import cost
from semimul.plans.staging import fresh
from semimul.plans.store import PartialLog, multiply_into
from semimul.sources import build, generate


def session(cpus: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", str(cpus)).config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(f) -> float:
    t = time.perf_counter()
    f()
    return round(time.perf_counter() - t, 3)


def sink(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", "8"))
    top = int(os.environ.get("BENCH_SCALE", "14"))
    spark = session(cpus)
    took, rates = {}, {}
    sink(multiply.outer_product(*build.workload(spark, sf_dir, "W7")))  # warm-up
    for w in ("W1", "W2", "W3", "W6", "W8", "W13"):
        took[f"outer_{w}"] = timed(lambda w=w: sink(multiply.outer_product(*build.workload(spark, sf_dir, w))))
    took["rowwise_W2"] = timed(lambda: sink(multiply.rowwise_product(*build.workload(spark, sf_dir, "W2"))))
    took["hybrid4_W6"] = timed(lambda: sink(multiply.hybrid_product(*build.workload(spark, sf_dir, "W6"), bands=4)))
    took["hybrid4_replicated_W6"] = timed(lambda: sink(multiply.hybrid_product(*build.workload(spark, sf_dir, "W6"), bands=4, execution="replicated")))
    took["inner_ordered_W1"] = timed(lambda: sink(multiply.inner_product(*build.workload(spark, sf_dir, "W1"))))
    for scale in range(10, top + 1):
        paths = []
        for seed in (1, 2):
            paths.append(fresh(spark, f"graph-{scale}"))
            generate.power_law_graph(spark, scale, seed).write.parquet(paths[-1])
        a, b = (spark.read.parquet(p) for p in paths)
        at, right = a.select(F.col("row").alias("k"), F.col("col").alias("i"), "v"), kernels.by_row(b)
        pp = cost.partial_products(at, right).first()[0]
        for shards in (1, 2, cpus) if scale == 12 else (cpus,):
            spark.conf.set("spark.sql.shuffle.partitions", str(shards))
            log = PartialLog(spark, fresh(spark, f"log-{scale}"))
            name = f"streaming_scale{scale}" + (f"_shards{shards}" if shards != cpus else "")
            times = [timed(lambda q=q: multiply_into(PartialLog(spark, fresh(spark, "log")) if q else log, at, right, "r")) for q in range(3 if scale <= 13 else 1)]
            took[name] = sorted(times)[len(times) // 2]
            rates[name] = round(pp / took[name])
        spark.conf.set("spark.sql.shuffle.partitions", str(cpus))
        took[f"fold_scale{scale}"] = timed(lambda: sink(log.scan()))
        took[f"summed_scale{scale}"] = timed(lambda: sink(multiply.outer_product(at, right)))
        rates[f"summed_scale{scale}"] = round(pp / took[f"summed_scale{scale}"])
        if scale <= 12:
            took[f"client_scale{scale}"] = timed(lambda: sink(multiply.client_product(at, right, max_entries=20_000_000)[0]))
            rates[f"client_scale{scale}"] = round(pp / took[f"client_scale{scale}"])
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "pp_per_sec": rates, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
