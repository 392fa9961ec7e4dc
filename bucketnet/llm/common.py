"""What the corpus operators share: table loading, durable cuts of lineage, ranks without one big task."""

from __future__ import annotations

import gc
import re
import tempfile
import time
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables, by a path that Spark alone needs to understand."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the session's spark.checkpoint.dir; a private folder only where none is set and all of Spark is one process."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared = spark.conf.get("spark.checkpoint.dir", None)
        if not shared and not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="bucketnet-"))


def cut(df: DataFrame) -> DataFrame:
    """Writes df to the shared checkpoint folder; later reads survive the loss of any executor."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def free_shuffles(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffles of plans that are done with: it learns of them when the driver's JVM collects garbage, which may be long after."""
    for _ in range(2):  # what the first frees holds more that only the second can free
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.3)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """The names, with more underscores before where df has such a column, in any case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for x in names:
        while x.lower() in taken:
            x = f"_{x}"
        taken.add(x.lower())
        out.append(x)
    return out


def columns_of(df: DataFrame) -> list[Column]:
    """The columns of df by name, whatever signs are in the names."""
    return [F.col("`" + c.replace("`", "``") + "`") for c in df.columns]


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def hash_sample(df: DataFrame, keys: list[str], rows: int) -> DataFrame:
    """The rows of df with the smallest hashes of keys, at most rows of them: the same ones whatever the partitions.

    A first cut by the hash leaves about twice as many before they are sorted, so tasks do not send rows each.
    """
    h = F.xxhash64(*keys).bitwiseAND(F.lit((1 << 62) - 1))
    many = df.count()
    below = min(1.0, 2 * rows / max(1, many) + 100 / max(1, many))
    near = df if below >= 1 else df.where(h < F.lit(int(below * (1 << 62))))
    return near.withColumn("__h", h).orderBy("__h", *keys).limit(rows).drop("__h")


def text_or_empty(col: str = "text") -> Column:
    return F.coalesce(F.col(col).cast("string"), F.lit(""))


def doc_crc(doc_id) -> int:
    """crc32 of the decimal text of an id, as F.crc32(cast as string) gives it."""
    return zlib.crc32(str(doc_id).encode())


def dense_rank_by(df: DataFrame, keys: list[str], order: list[str], out: str, buckets: int) -> DataFrame:
    """Adds out: 0, 1, 2, ... within each combination of keys, gapless, in hashed-bucket order.

    A key may hold any share of the rows: rows are numbered inside (keys, bucket), where the bucket
    is a hash of order, and each bucket starts where the ones before it end. order must tell rows
    of one key apart well enough to spread them; full ties get their numbers in any order.
    """
    b, base = f"__{out}_bucket", f"__{out}_base"
    spread = df.withColumn(b, F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    sizes = spread.groupBy(*keys, b).agg(F.count(F.lit(1)).alias("__n"))
    before = Window.partitionBy(*keys).orderBy(b).rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(*[F.col(k).alias(f"__k_{k}") for k in keys], F.col(b).alias("__k_bucket"),
                          F.coalesce(F.sum("__n").over(before), F.lit(0)).alias(base))
    inside = Window.partitionBy(*keys, b).orderBy(*order)
    numbered = spread.withColumn(out, F.row_number().over(inside) - 1)
    on = [F.col(k).eqNullSafe(F.col(f"__k_{k}")) for k in keys] + [F.col(b) == F.col("__k_bucket")]
    cond = on[0]
    for c in on[1:]:
        cond = cond & c
    return (numbered.join(starts, cond)
            .withColumn(out, (F.col(out) + F.col(base)).cast("long"))
            .drop(b, base, "__k_bucket", *[f"__k_{k}" for k in keys]))


DOC_ID = T.StructField("doc_id", T.LongType())
