"""The log of partial products: a sum that is done when it is read, or when runs are compacted.

A log is a folder of immutable runs and numbered manifests, of which the highest lists the live runs. A run becomes live by a manifest of the
next number, which appears whole or not at all; no manifest is ever replaced, so a writer that dies leaves the log as it was, and of two
writers one fails. A run id that is live already is not written again, so a step that is tried again changes nothing.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from semimul.functions.semiring import PLUS_TIMES, Semiring
from semimul.operators.multiply import _ADD, _FOLD, fold, outer_product
from semimul.plans.staging import Files

#: Entries from which on a compaction goes by ranges of rows, entries of a range (about), and ranges in a job.
BY_RANGES, RANGE_ENTRIES, AT_ONCE = 50_000_000, 4_000_000, 24


def _cells(how: str):
    """The cells of a task, sorted: all its entries (i, j, v) are held."""
    add = _FOLD[how]

    def run(batches):
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        schema = got[0].schema
        i, j, v = (np.concatenate([b[c].to_numpy() for b in got]).astype(np.int64) for c in ("i", "j", "v"))
        del got
        low, first = int(i.min()), int(j.min())
        span = int(j.max()) - first + 1
        if (int(i.max()) - low + 1) * span < 2**62:
            order = np.argsort((i - low) * span + (j - first), kind="stable")
        else:
            order = np.lexsort((j, i))
        i, j, v = i[order], j[order], v[order]
        starts = np.flatnonzero(np.append(True, (i[1:] != i[:-1]) | (j[1:] != j[:-1])))
        i, j, v = i[starts], j[starts], add.reduceat(v, starts)
        for at in range(0, len(v), 50_000):
            yield pa.RecordBatch.from_arrays([pa.array(x[at : at + 50_000]).cast(schema.field(c).type) for c, x in (("i", i), ("j", j), ("v", v))], schema=schema)

    return run


class PartialLog:
    def __init__(self, spark: SparkSession, path: str, s: Semiring = PLUS_TIMES):
        self.spark, self.path, self.s, self.files = spark, path.rstrip("/"), s, Files(spark)

    def _generations(self) -> list[int]:
        return sorted(int(n[:-5]) for n in self.files.names(f"{self.path}/manifests") if n.endswith(".json"))

    def manifest(self) -> dict:
        found = self._generations()
        if not found:
            return {"base": None, "runs": [], "known": [], "fold": self.s.name, "schema": None, "generation": 0}
        return self.files.read_json(f"{self.path}/manifests/{found[-1]:012}.json")

    def _commit(self, manifest: dict) -> None:
        number = manifest["generation"] + 1
        self.files.write_json(f"{self.path}/manifests/{number:012}.json", manifest | {"generation": number})

    def write_run(self, partials: DataFrame, run_id: str, write: str = "c") -> None:
        """Writes (i, j, v) entries as a run that is not live yet."""
        entries = partials.select("i", "j", "v")
        if write == "both":
            # one pass over the product: each entry goes out in both orientations
            each = F.explode(F.array(F.struct(F.lit("c").alias("orient"), F.col("i").alias("i"), F.col("j").alias("j")), F.struct(F.lit("ct").alias("orient"), F.col("j").alias("i"), F.col("i").alias("j"))))
            out = entries.select(each.alias("e"), "v").select("e.i", "e.j", "v", "e.orient")
        else:
            out = (entries if write == "c" else entries.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")).withColumn("orient", F.lit(write))
        out.write.mode("overwrite").partitionBy("orient").parquet(f"{self.path}/runs/{run_id}")

    def append(self, partials: DataFrame, run_id: str, write: str = "c") -> bool:
        """Adds (i, j, v) entries as a run; False if the run is there already. write: `c`, its transpose `ct`, or `both` in one pass, told apart
        by a partition column."""
        manifest = self.manifest()
        if run_id in manifest["known"]:
            return False
        self.write_run(partials, run_id, write)
        self._commit(manifest | {"runs": [*manifest["runs"], run_id], "known": [*manifest["known"], run_id], "schema": partials.select("i", "j", "v").schema.jsonValue()})
        return True

    def commit_runs(self, run_ids: list[str], schema) -> None:
        """Makes written runs live, all at once."""
        manifest = self.manifest()
        new = [r for r in run_ids if r not in manifest["known"]]
        self._commit(manifest | {"runs": [*manifest["runs"], *new], "known": [*manifest["known"], *new], "schema": schema.jsonValue()})

    def _read(self, names: list[str], orient: str, manifest: dict) -> DataFrame | None:
        from pyspark.sql.types import StructType

        if not names or not manifest["schema"]:
            return None
        schema = StructType.fromJson(manifest["schema"])
        # one scan over all runs, not one for each
        paths = [p for p in (f"{self.path}/{n}/orient={orient}" for n in names) if self.files.exists(p)]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def live(self, orient: str = "c", manifest: dict | None = None, allow_uncommitted: bool = False) -> DataFrame | None:
        manifest = manifest or self.manifest()
        names = ([manifest["base"]] if manifest["base"] else []) + [f"runs/{r}" for r in manifest["runs"]]
        if allow_uncommitted:
            names += [f"runs/{r}" for r in self.files.names(f"{self.path}/runs") if r not in manifest["known"] and not r.startswith("minor-") and "_SUCCESS" in self.files.names(f"{self.path}/runs/{r}")]
        return self._read(names, orient, manifest)

    def scan(self, rows: Column | None = None, orient: str = "c", allow_uncommitted: bool = False) -> DataFrame:
        """(i, j, v), summed on the way out. `rows`, a predicate on i, is pushed below the sum to the scans. `allow_uncommitted` also reads
        runs that are written but not live, for an early look at an unfinished result."""
        entries = self.live(orient, allow_uncommitted=allow_uncommitted)
        if entries is None:
            raise ValueError("the log has no run")
        return fold(entries.filter(rows) if rows is not None else entries, self.s)

    def _lazy(self) -> None:
        if not self.s.lazy:
            raise ValueError(f"{self.s.name} needs all partials of a cell at once; only major_compact() and scan() may sum it")

    def _summed(self, names: list[str], manifest: dict, prune_zero: bool = False) -> DataFrame:
        """(i, j, v, orient) of the named runs, each orientation summed by itself."""
        out = None
        for orient in ("c", "ct"):
            entries = self._read(names, orient, manifest)
            if entries is None:
                raise ValueError("no run to compact")
            done = fold(entries, self.s)
            if prune_zero and self.s.zero is not None:
                done = done.filter(F.col("v") != F.lit(self.s.zero))
            done = done.withColumn("orient", F.lit(orient))
            out = done if out is None else out.unionByName(done)
        return out

    def _by_ranges(self, names: list[str], path: str, manifest: dict, prune_zero: bool = False) -> bool:
        """Writes the named runs summed and sorted by cell, range by range of rows and with no exchange: a task reads what the runs hold of its range,
        which their files' statistics find if the runs are laid out by rows. False, and nothing written, if they are small or not of whole numbers."""
        whole = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)
        found = {o: t for o in ("c", "ct") if (t := self._read(names, o, manifest)) is not None}
        many = {o: t.count() for o, t in found.items()}
        if self.s.name not in _ADD or sum(many.values()) < BY_RANGES or not all(isinstance(f.dataType, whole) for t in found.values() for f in t.schema):
            return False
        mode = "overwrite"
        for orient in (o for o in found if many[o]):
            parts = [self._range(found[orient], r, prune_zero) for r in self._ends(found[orient], many[orient])]
            for at in range(0, len(parts), AT_ONCE):
                out = parts[at]
                for part in parts[at + 1 : at + AT_ONCE]:
                    out = out.unionByName(part)
                out.write.mode(mode if at == 0 else "append").parquet(f"{path}/orient={orient}")
        return True

    def _range(self, entries: DataFrame, rows: Column, prune_zero: bool) -> DataFrame:
        done = entries.filter(rows).coalesce(1).mapInArrow(_cells(_ADD[self.s.name]), entries.schema)
        return done.filter(F.col("v") != F.lit(self.s.zero)) if prune_zero and self.s.zero is not None else done

    def _ends(self, entries: DataFrame, many: int) -> Iterator[Column]:
        """Predicates of ranges of rows that hold about RANGE_ENTRIES entries each and all rows together. Only where they end is taken from a sample."""
        n = math.ceil(many / RANGE_ENTRIES)
        sampled = entries.sample(min(1.0, 1000 * n / many), 1) if n > 1 else entries.limit(0)
        ends = sorted(set(sampled.agg(F.percentile_approx("i", [q / n for q in range(1, n)] or [0.5], 10_000)).first()[0] or []))
        i = F.col("i")
        for low, high in zip([None, *ends], [*ends, None]):
            yield F.lit(True) if low is high is None else i <= high if low is None else i > low if high is None else (i > low) & (i <= high)

    def minor_compact(self, runs: list[str]) -> str:
        """Some runs become one; the sum may be done in parts."""
        self._lazy()
        manifest = self.manifest()
        name = f"minor-{manifest['generation']}"
        if not self._by_ranges([f"runs/{r}" for r in runs], f"{self.path}/runs/{name}", manifest):
            self._summed([f"runs/{r}" for r in runs], manifest).write.mode("overwrite").partitionBy("orient").parquet(f"{self.path}/runs/{name}")
        self._commit(manifest | {"runs": [r for r in manifest["runs"] if r not in runs] + [name]})
        return name

    def major_compact(self, prune_zero: bool = False) -> None:
        """Base and runs become a new base, sorted by cell over ranges."""
        manifest = self.manifest()
        names = ([manifest["base"]] if manifest["base"] else []) + [f"runs/{r}" for r in manifest["runs"]]
        name = f"base/{manifest['generation']}"
        if not self._by_ranges(names, f"{self.path}/{name}", manifest, prune_zero):
            done = self._summed(names, manifest, prune_zero)
            done.repartitionByRange("orient", "i").sortWithinPartitions("orient", "i", "j").write.mode("overwrite").partitionBy("orient").parquet(f"{self.path}/{name}")
        self._commit(manifest | {"base": name, "runs": []})

    def vacuum(self, run_ids: list[str]) -> None:
        """Deletes runs that no manifest lists any more, and all manifests but the last."""
        live, found = set(self.manifest()["runs"]), self._generations()
        for r in run_ids:
            if r not in live:
                self.files.delete(f"{self.path}/runs/{r}")
        for number in found[:-1]:
            self.files.delete(f"{self.path}/manifests/{number:012}.json")


def multiply_into(log: PartialLog, at: DataFrame, b: DataFrame, run_id: str, *, write: str = "c", metrics: Callable[[dict], None] | None = None) -> dict:
    """C += A B: partials go to the log, and only counts come back."""
    from pyspark.sql import Observation

    seen = Observation()
    partials = outer_product(at, b, log.s, emit="partials").observe(seen, F.count(F.lit(1)).alias("products"))
    wrote = log.append(partials, run_id, write)
    got = {"run": run_id, "written": wrote, "products": seen.get["products"] if wrote else 0}
    if metrics:
        metrics(got)
    return got
