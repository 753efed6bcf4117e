"""Written tables between steps, and small files in the store."""

from __future__ import annotations

import json
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a local master (tests) gets a temporary folder and a cluster is refused."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="semimul-"))
        folder = spark.sparkContext.getCheckpointDir()
    return folder.rstrip("/")


def fresh(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


#: Names of the tables that `written` has made in this process, for measurements.
WRITTEN: list[str] = []


def written(df: DataFrame, name: str = "step") -> DataFrame:
    """The table written to the shared folder and read again, which cuts its lineage and survives lost executors."""
    path = fresh(df.sparkSession, name)
    df.write.parquet(path)
    WRITTEN.append(name)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame, name: str) -> None:
    """Deletes the tables called `name` that `written` made and `df` reads, which nothing may read any more."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if re.fullmatch(name + "-[0-9a-f]{32}", folder.rsplit("/", 1)[-1]):
            Files(df.sparkSession).delete(folder)


class Files:
    """Whole small files by path in any store that Hadoop reads."""

    def __init__(self, spark: SparkSession):
        self.jvm, self.conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()

    def _at(self, path: str):
        p = self.jvm.org.apache.hadoop.fs.Path(path)
        return p, p.getFileSystem(self.conf)

    def exists(self, path: str) -> bool:
        p, fs = self._at(path)
        return fs.exists(p)

    def read_json(self, path: str) -> dict:
        p, fs = self._at(path)
        stream = fs.open(p)
        try:
            return json.loads(self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def write_json(self, path: str, value: dict) -> None:
        """Written beside and renamed. A file that is there already is never touched: that is an error, so of two writers one fails."""
        p, fs = self._at(path)
        side = self.jvm.org.apache.hadoop.fs.Path(f"{path}.{uuid.uuid4().hex}.part")
        stream = fs.create(side, True)
        stream.write(bytearray(json.dumps(value, sort_keys=True).encode()))
        stream.close()
        if fs.exists(p) or not fs.rename(side, p):
            fs.delete(side, False)
            raise OSError(f"could not write {path}")

    def names(self, path: str) -> list[str]:
        """Names in a folder; none where there is no folder."""
        p, fs = self._at(path)
        return [f.getPath().getName() for f in fs.listStatus(p)] if fs.exists(p) else []

    def rename(self, old: str, new: str) -> bool:
        p, fs = self._at(old)
        q, _ = self._at(new)
        return fs.rename(p, q)

    def delete(self, path: str) -> None:
        p, fs = self._at(path)
        fs.delete(p, True)
