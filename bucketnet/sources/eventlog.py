"""Spark's own event log as a source: where the time of a run goes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_INFO = "struct<`Launch Time`: long, `Finish Time`: long, `Getting Result Time`: long>"
_METRICS = """struct<`Executor Deserialize Time`: long, `Executor Run Time`: long, `Executor CPU Time`: long, `JVM GC Time`: long, `Result Serialization Time`: long,
`Peak Execution Memory`: long, `Memory Bytes Spilled`: long, `Disk Bytes Spilled`: long, `Shuffle Read Metrics`: struct<`Fetch Wait Time`: long>, `Shuffle Write Metrics`: struct<`Shuffle Write Time`: long>>"""
SCHEMA = f"`Event` string, `Stage ID` int, `Task Info` {_INFO}, `Task Metrics` {_METRICS}"


def read_event_log(spark: SparkSession, path: str) -> DataFrame:
    """A row per ended task, times in ms."""
    e = spark.read.schema(SCHEMA).json(path).where("Event = 'SparkListenerTaskEnd'")
    m = lambda name: F.coalesce(F.col(f"`Task Metrics`.`{name}`"), F.lit(0))
    return e.select(
        F.col("`Stage ID`").alias("stage"), F.col("`Task Info`.`Launch Time`").alias("begin"), F.col("`Task Info`.`Finish Time`").alias("end"),
        m("Executor Run Time").alias("run_ms"), (m("Executor CPU Time") / 1e6).alias("cpu_ms"), m("JVM GC Time").alias("gc_ms"),
        m("Executor Deserialize Time").alias("deserialize_ms"), m("Result Serialization Time").alias("serialize_ms"),
        F.coalesce(F.col("`Task Metrics`.`Shuffle Read Metrics`.`Fetch Wait Time`"), F.lit(0)).alias("fetch_wait_ms"),
        (F.coalesce(F.col("`Task Metrics`.`Shuffle Write Metrics`.`Shuffle Write Time`"), F.lit(0)) / 1e6).alias("shuffle_write_ms"),
        m("Peak Execution Memory").alias("peak_bytes"), (m("Memory Bytes Spilled") + m("Disk Bytes Spilled")).alias("spilled_bytes"))


def core_utilisation(tasks: DataFrame, cores: int) -> DataFrame:
    """Task run time over wall time x cores, and the JVM's CPU share of it."""
    return tasks.agg(
        (F.sum("run_ms") / ((F.max("end") - F.min("begin")) * cores)).alias("busy"),
        F.try_divide(F.sum("cpu_ms"), F.sum("run_ms")).alias("jvm_cpu_share"))


def stage_breakdown(tasks: DataFrame) -> DataFrame:
    """By stage: CPU, collection, waiting for shuffles, (de)serialising, and scheduler delay, in ms."""
    life = F.col("end") - F.col("begin")
    delay = F.greatest(F.lit(0), life - F.col("run_ms") - F.col("deserialize_ms") - F.col("serialize_ms"))
    return tasks.groupBy("stage").agg(
        F.count(F.lit(1)).alias("tasks"), *[F.sum(c).alias(c) for c in ("cpu_ms", "gc_ms", "fetch_wait_ms", "shuffle_write_ms", "deserialize_ms", "serialize_ms")],
        F.sum(delay).alias("scheduler_ms"), F.max("peak_bytes").alias("peak_bytes"), F.sum("spilled_bytes").alias("spilled_bytes"))
