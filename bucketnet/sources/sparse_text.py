"""Sparse text, the usual layout of large multi-label sets: `label,label idx:val idx:val ...`, and other formats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_sparse_text(spark: SparkSession, path: str) -> DataFrame:
    """labels array<int>, feats array<int>, vals array<double>, line by line; a line without features has empty arrays."""
    parts = F.split(F.trim("value"), r"\s+")
    pairs = F.filter(parts, lambda x: F.instr(x, ":") > 0)
    labels = F.filter(F.split(F.when(F.instr(parts[0], ":") > 0, "").otherwise(parts[0]), ","), lambda x: x != "")
    return spark.read.text(path).select(
        F.transform(labels, lambda x: x.cast("int")).alias("labels"),
        F.transform(pairs, lambda x: F.split_part(x, F.lit(":"), F.lit(1)).cast("int")).alias("feats"),
        F.transform(pairs, lambda x: F.split_part(x, F.lit(":"), F.lit(2)).cast("double")).alias("vals"))


def write_sparse_text(df: DataFrame, path: str) -> None:
    pairs = F.zip_with("feats", "vals", lambda i, v: F.concat_ws(":", i.cast("string"), v.cast("string")))
    line = F.concat_ws(" ", F.array_join(F.transform("labels", lambda x: x.cast("string")), ","), F.array_join(pairs, " "))
    df.select(line.alias("value")).write.mode("overwrite").text(path)


def read_any(spark: SparkSession, kind: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """csv, json, orc, parquet, text or binaryFile; csv and json need a schema, so that nothing is read twice to guess one."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    r = spark.read.format(kind).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def write_index(bucket: DataFrame, path: str, tables_per_file: int = 1) -> None:
    """Buckets by table, sorted by code, so that a probe reads the tables and row groups it needs."""
    spread = bucket.repartition(F.col("table_id"), F.pmod(F.xxhash64("code"), F.lit(tables_per_file)))
    spread.sortWithinPartitions("table_id", "code").write.mode("overwrite").partitionBy("table_id").parquet(path)


def timed(df: DataFrame) -> float:
    """Seconds to compute all of df, into nothing."""
    import time

    t = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - t


def sample_rows(df: DataFrame, share: float, key: str, seed: int = 11) -> DataFrame:
    """A repeatable share of the rows by their key."""
    from bucketnet.functions.seeds import h32

    return df.where(h32(seed, F.col(key)) < int(share * 2**32))
