"""Matrices as triples from ordinary tables. Duplicate entries are summed, so every builder ends in one aggregate."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_columns(t: DataFrame, key: Column, other: Column, value: Column | None = None, name: str = "i", how=F.sum) -> DataFrame:
    """(k, i or j, v) from a fact table; rows with a null key are left out."""
    got = t.select(key.alias("k"), other.alias(name), (value if value is not None else F.lit(1).cast("long")).alias("v"))
    return got.filter(f"k is not null and {name} is not null").groupBy("k", name).agg(how("v").alias("v"))


def from_wide(t: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """One entry a row and column, by unpivot."""
    return t.unpivot(key, columns, "j", "v").select(F.col(key).alias("k"), "j", "v").filter("v is not null")


def from_vectors(t: DataFrame, key: str, vector: str, scale: int = 1000, name: str = "i", keep_zero: bool = False) -> DataFrame:
    """(k = dimension, i, v = rounded and scaled component)."""
    got = t.select(F.col(key).alias(name), F.posexplode(vector).alias("k", "x")).select("k", name, F.round(F.col("x").cast("double") * scale).cast("long").alias("v"))
    return got if keep_zero else got.filter("v <> 0")


def from_text(t: DataFrame, key: str, text: str, name: str = "i") -> DataFrame:
    """(k = term, i, v = count) over the terms [a-z]+ of the lower-cased text."""
    got = t.select(F.col(key).alias(name), F.explode(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))).alias("k"))
    return got.groupBy("k", name).agg(F.count(F.lit(1)).alias("v"))


def from_json(t: DataFrame, key: str, text: str, path: str, name: str = "i") -> DataFrame:
    return from_columns(t, F.get_json_object(text, path), F.col(key), name=name)


def from_links(t: DataFrame, key: str, html: str, name: str = "i") -> DataFrame:
    """(k = target, i, v = 1) over the distinct href values of pages."""
    got = t.select(F.col(key).alias(name), F.explode(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1))).alias("k")).distinct()
    return got.withColumn("v", F.lit(1).cast("long"))


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Both operands of a workload on the given tables."""
    t = lambda x: table(spark, sf_dir, x)
    line = t("lineitem") if name in ("W1", "W2", "W3", "W4", "W5", "W6") else None
    quantity = F.col("l_quantity").cast("long")
    if name in ("W4", "W5", "W6"):
        line = line.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    make = lambda f, k, x, v=None: (from_columns(f, F.col(k), F.col(x), v, "i"), from_columns(f, F.col(k), F.col(x), v, "j"))
    if name == "W1":
        return from_columns(line, F.col("l_orderkey"), F.col("l_partkey"), quantity), from_columns(line, F.col("l_orderkey"), F.col("l_suppkey"), quantity, "j")
    if name == "W2":
        return make(line, "l_orderkey", "l_partkey", quantity)
    if name == "W3":
        return make(line, "l_partkey", "l_suppkey")
    if name == "W4":
        return make(line, "o_custkey", "l_partkey", quantity)
    if name == "W5":
        return make(line, "l_partkey", "o_custkey")
    if name == "W6":
        return from_columns(line, F.col("l_partkey"), F.col("l_suppkey")), from_columns(line, F.col("l_partkey"), F.col("o_custkey"), name="j")
    if name in ("W7", "W8", "W9"):
        events = t("events").withColumn("hour", F.date_trunc("hour", "ts")).withColumn("minute", F.date_trunc("minute", "ts"))
        return make(events, *{"W7": ("user_id", "event_type"), "W8": ("hour", "user_id"), "W9": ("minute", "user_id")}[name])
    if name in ("W10", "W10c"):
        at = from_text(t("documents"), "doc_id", "text")
        if name == "W10c":
            at = at.join(at.groupBy("k").agg(F.count(F.lit(1)).alias("df")).filter("df <= 20"), "k", "left_semi")
        return at, at.withColumnRenamed("i", "j")
    if name in ("W11", "W11c"):
        vectors = t("embeddings").filter("vec_id < 100") if name == "W11c" else t("embeddings")
        at = from_vectors(vectors, "vec_id", "embedding", keep_zero=True).withColumn("v", F.lit(1).cast("long"))
        return at, at.withColumnRenamed("i", "j")
    if name == "W12":
        return from_columns(t("customer"), F.col("c_nationkey"), F.col("c_custkey")), from_columns(t("nation"), F.col("n_nationkey"), F.col("n_regionkey"), name="j")
    if name == "W13":
        at = from_links(t("pages"), "page_id", "html")
        return at, at.withColumnRenamed("i", "j")
    if name == "W14":
        return from_text(t("documents"), "doc_id", "text"), from_text(t("benchmark"), "item_id", "text", "j")
    if name == "W15":
        return from_columns(t("conversations"), F.col("conv_id"), F.col("role")), from_columns(t("conversations"), F.col("conv_id"), F.col("turn"), name="j")
    raise ValueError(name)
