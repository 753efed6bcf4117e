"""What the operators of this subpackage share: staging in the shared folder, row keys, hashing of words."""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space that parts words in the contracts: space and the five controls from tab to carriage return.
WORD_SPACE = " \t\n\x0b\x0c\r"

_ROOTS: dict[str, SparkSession] = {}


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Where it is unset, a local master (tests) gets a temporary one; a
    cluster is refused, since its executors would not see it."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if not known:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="semimul-"))
        known = spark.sparkContext.getCheckpointDir()
    return known.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


@atexit.register
def _remove_all() -> None:
    for root, spark in list(_ROOTS.items()):
        try:
            _remove(spark, root)
        except Exception:  # noqa: BLE001  the session has ended already
            pass


#: Runtime settings while a step is written: its shuffle files go when it ends, and the driver keeps little of its plan's text.
_STEP = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.maxPlanStringLength": "4096"}
#: Bytes of an operator's largest written table for each file of its small results.
BYTES_A_FILE = 32 << 20
#: A key with more than one in so many of all rows is hot; fewer than so many keys can be.
HOT_SHARE = 20_000


class Scratch:
    """Tables written to the shared folder between the steps of one operator, so that no step is computed twice and a lost executor costs
    no more than the step at hand. `drop` removes a table that no later step reads; what the returned DataFrame still reads goes when the
    driver ends. The shuffle files of a step go with the step, and its broadcast tables soon after."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.largest = spark, 0
        self.root = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        _ROOTS[self.root] = spark

    def save(self, df: DataFrame, name: str, few: bool = False) -> DataFrame:
        """Writes a table and reads it again. `few`: in few files, for results of a shuffle that are small against their operator's largest
        table: two a core, or one for every `BYTES_A_FILE` of that table where that is more."""
        path = f"{self.root}/{name}"
        most = max(2 * self.spark.sparkContext.defaultParallelism, -(-self.largest // BYTES_A_FILE))
        before = {k: v for k in _STEP if (v := self.spark.conf.get(k, None)) is not None}
        for k in before:
            self.spark.conf.set(k, _STEP[k])
        try:
            (df.coalesce(most) if few else df).write.mode("overwrite").parquet(path)
        finally:
            for k, v in before.items():
                self.spark.conf.set(k, v)
        # broadcast tables of finished steps stay in the driver's memory until it collects its garbage; many small steps would fill it
        self.spark.sparkContext._jvm.System.gc()
        if not few:
            jvm = self.spark.sparkContext._jvm
            target = jvm.org.apache.hadoop.fs.Path(path)
            held = target.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(target)
            self.largest = max(self.largest, held.getLength())
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, name: str) -> None:
        _remove(self.spark, f"{self.root}/{name}")


def release() -> None:
    """Gives memory that training has used on the driver, or a task in its worker, back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def spread_join(rows: DataFrame, table: DataFrame, keys: list[str], weights: DataFrame, total: int, by: list[str], how: str = "inner") -> DataFrame:
    """`rows` joined with `table` on `keys`, with hot keys dealt over many tasks. `weights` has a row (keys, weight) for each key: how many of
    the `total` rows hold it. Keys of more than one in HOT_SHARE of the rows, fewer than HOT_SHARE by their definition, are broadcast with
    a number of salts; their rows are dealt over the salts by the columns `by`, and the table's row is copied for each. `how` may be left."""
    share = F.lit(HOT_SHARE / max(1, total))
    hot = F.broadcast(weights.filter(F.col("weight") * share > 1).select(*keys, F.ceil(F.col("weight") * share).cast("int").alias("_of")))
    dealt = rows.join(hot, keys, "left").withColumn("_salt", F.coalesce(F.pmod(F.xxhash64(*by), F.col("_of")).cast("int"), F.lit(0))).drop("_of")
    copied = table.join(hot, keys, "left").withColumn("_salt", F.explode(F.sequence(F.lit(0), F.coalesce("_of", F.lit(1)) - 1))).drop("_of")
    return dealt.join(copied, [*keys, "_salt"], how).drop("_salt")


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else; the plain lower() does the same where all characters are ASCII, and faster."""
    upper = "".join(map(chr, range(65, 91)))
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, upper, upper.lower()))


def hash128(value: Column) -> list[Column]:
    """Two independent 64-bit hashes."""
    return [F.xxhash64(value), F.xxhash64(F.lit(7), value)]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser over uint64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class WordHashes(dict):
    """64-bit hash of each word, remembered up to a bounded number of words."""

    BOUND = 200_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.BOUND:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def chunks(texts: list, limit: int = 4_000_000):
    """Ranges of a batch holding about `limit` bytes each, so that what is built for one range stays bounded."""
    start, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t) if t else 0
        if size >= limit:
            yield start, i + 1
            start, size = i + 1, 0
    if start < len(texts):
        yield start, len(texts)


def with_text(docs: DataFrame, rest: list[str], text_col: str) -> tuple[DataFrame, int]:
    """The columns `rest` for an Arrow function, and the place of the text in them. A text that is not among them as a string or as bytes is
    appended as bytes; no batch holds a text twice."""
    if text_col in rest and docs.schema[text_col].dataType.typeName() in ("string", "binary"):
        return docs.select(*rest), rest.index(text_col)
    return docs.select(*rest, F.col(text_col).cast("binary").alias("__in")), len(rest)


def text_chunks(column: pa.Array):
    """(start, end, texts as bytes) of the ranges that `chunks` makes of a column; only one range at a time is taken out of Arrow's memory."""
    large = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    raw = column.cast(pa.large_binary() if large else pa.binary())
    for start, end in chunks([range(n or 0) for n in pc.binary_length(raw).to_pylist()]):
        yield start, end, raw.slice(start, end - start).to_pylist()
