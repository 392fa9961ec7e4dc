"""Hash tables as relations: bucket(table_id, code, id, prio, seq), bounded buckets, moves, merges, refresh calendars.

A table holds ids alone. Buckets are bounded by one of two policies. Reservoir: the cap ids of smallest random
priority stay, which is a uniform sample, does not depend on order, and merges. FIFO: the cap newest stay.
Both are a rank filter, which Spark applies before the shuffle as well (WindowGroupLimit), so a hot
bucket leaves each task with cap rows at most.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bucketnet.functions.seeds import h32

KEY = ["table_id", "code"]


def build_index(codes: DataFrame, cap: int | None = None, policy: str = "reservoir", seed: int = 11, seq: Column | None = None) -> DataFrame:
    """bucket rows of codes (id, table_id, code); seq, the order of insertion, is by default the id."""
    prio = h32(seed, F.col("id"), F.col("table_id"))
    rows = codes.select("table_id", "code", "id", prio.alias("prio"), (F.col("id") if seq is None else seq).cast("long").alias("seq"))
    if cap is None:
        return rows
    return {"reservoir": cap_reservoir, "fifo": cap_fifo}[policy](rows, cap)


def _first(rows: DataFrame, cap: int, *order: Column) -> DataFrame:
    w = Window.partitionBy(*KEY).orderBy(*order)
    return rows.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= cap).drop("__r")


def cap_reservoir(rows: DataFrame, cap: int) -> DataFrame:
    return _first(rows, cap, F.col("prio"), F.col("id"))


def cap_fifo(rows: DataFrame, cap: int) -> DataFrame:
    return _first(rows, cap, F.col("seq").desc(), F.col("id").desc())


def cap_reservoir_sequential(rows: DataFrame, cap: int, seed: int = 11) -> DataFrame:
    """The sequential sampler: the n-th arrival takes a random place below n if that is below cap.

    One bucket is one stream, read in order of seq, so a task holds cap ids and a batch; the order within
    a bucket makes it one task's work. cap_reservoir has the same law without that.
    """
    from bucketnet.functions.seeds import h32_of

    ordered = rows.select("table_id", "code", "id", "seq").repartition(*KEY).sortWithinPartitions(*KEY, "seq", "id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        key, held, n = None, [], 0
        done: list[tuple] = []
        for b in batches:
            for t, c, i in zip(b["table_id"].tolist(), b["code"].tolist(), b["id"].tolist(), strict=True):
                if (t, c) != key:
                    done += [(*key, x) for x in held] if key else []
                    key, held, n = (t, c), [], 0
                n += 1
                place = h32_of(seed, t, c, n) % n
                if len(held) < cap:
                    held.append(i)
                elif place < cap:
                    held[place] = i
            yield pd.DataFrame(done, columns=["table_id", "code", "id"]).astype("int64")
            done = []
        if key:
            yield pd.DataFrame([(*key, x) for x in held], columns=["table_id", "code", "id"]).astype("int64")

    return ordered.mapInPandas(run, "table_id int, code long, id long")


def apply_moves(bucket: DataFrame, new_codes: DataFrame, seed: int = 11) -> DataFrame:
    """bucket after the ids of new_codes have those codes: entries whose code differs go, new ones come; others are not touched."""
    fresh = build_index(new_codes, seed=seed)
    here = [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in ("id", "table_id")]
    old = bucket.alias("a").join(new_codes.alias("b"), here[0] & here[1] & (F.col("a.code") != F.col("b.code")), "left_anti")
    known = bucket.select("id", "table_id", "code")
    return old.unionByName(fresh.join(known, ["id", "table_id", "code"], "left_anti").select(*bucket.columns))


def merge_index(a: DataFrame, b: DataFrame, cap: int | None = None, policy: str = "reservoir") -> DataFrame:
    """The index of both shards' ids. With reservoir buckets equal to one built over all ids."""
    both = a.unionByName(b).dropDuplicates(["table_id", "code", "id"])
    if cap is None:
        return both
    return {"reservoir": cap_reservoir, "fifo": cap_fifo}[policy](both, cap)


def index_stats(bucket: DataFrame) -> DataFrame:
    """By table: buckets in use, ids, largest, mean and 90th percentile load."""
    load = bucket.groupBy(*KEY).agg(F.count(F.lit(1)).alias("n"))
    return load.groupBy("table_id").agg(
        F.count(F.lit(1)).alias("buckets"), F.sum("n").alias("ids"), F.max("n").alias("largest"),
        F.avg("n").alias("mean_load"), F.percentile("n", F.lit(0.9)).alias("p90_load"))


def rehash_schedule(spark: SparkSession, n0: float, decay: float, count: int) -> DataFrame:
    """t, exact, at_iteration: the t-th refresh is due at the first iteration not below the sum of n0 * e**(decay * i), i < t."""
    steps = spark.range(count).select((F.col("id") + 1).alias("t"))
    sums = F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("t") - 1), F.lit(0.0), lambda a, i: a + F.lit(float(n0)) * F.exp(F.lit(float(decay)) * i))
    return steps.select("t", sums.alias("exact")).withColumn("at_iteration", F.ceil(F.col("exact") - 1e-9).cast("long"))


def schedules(starts: DataFrame, decay: float, count: int) -> DataFrame:
    """run_id, n0, t, at_iteration: the first count refreshes of each run of starts (run_id, n0), as in rehash_schedule."""
    steps = starts.select("run_id", F.col("n0").cast("double").alias("n0"), F.explode(F.sequence(F.lit(1).cast("long"), F.lit(count).cast("long"))).alias("t"))
    due = F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("t") - 1), F.lit(0.0), lambda a, i: a + F.col("n0") * F.exp(F.lit(float(decay)) * i))
    return steps.select("run_id", F.col("n0").cast("long").alias("n0"), "t", F.ceil(due - 1e-9).cast("long").alias("at_iteration"))


class Refresh:
    """When to refresh, on the driver: decaying, fixed, every or never."""

    def __init__(self, kind: str = "decay", n0: float = 50, decay: float = 0.1):
        self.kind, self.n0, self.decay, self.done, self.due = kind, n0, decay, 0, float(n0)

    def next_after(self, iteration: int) -> float:
        """The first iteration after this one at which a refresh is due."""
        if self.kind == "never":
            return math.inf
        if self.kind == "every":
            return iteration + 1
        if self.kind == "fixed":
            return (iteration // int(self.n0) + 1) * int(self.n0)
        return max(iteration + 1, math.ceil(self.due - 1e-9))

    def fires(self, iteration: int) -> bool:
        if self.kind == "never":
            return False
        if self.kind == "every":
            return True
        if self.kind == "fixed":
            return iteration % int(self.n0) == 0
        if iteration < math.ceil(self.due - 1e-9):
            return False
        while iteration >= math.ceil(self.due - 1e-9):
            self.done += 1
            self.due += self.n0 * math.exp(self.decay * self.done)
        return True


def schedule_variants(spark: SparkSession, n0: int, decay: float, last: int) -> DataFrame:
    """kind, t, at_iteration of the calendars up to an iteration."""
    count = 1
    while sum(n0 * math.exp(decay * i) for i in range(count)) < last and count < 10_000:
        count += 1
    decaying = rehash_schedule(spark, n0, decay, count).where(F.col("at_iteration") <= last).select(F.lit("decay").alias("kind"), "t", "at_iteration")
    every = spark.range(1, last + 1).select(F.lit("every").alias("kind"), F.col("id").alias("t"), F.col("id").alias("at_iteration"))
    fixed = spark.range(1, last // n0 + 1).select(F.lit("fixed").alias("kind"), F.col("id").alias("t"), (F.col("id") * n0).alias("at_iteration"))
    return decaying.unionByName(every).unionByName(fixed)


def schedule_kinds(starts: DataFrame, decay: float, times: int) -> DataFrame:
    """run_id, kind, t, at_iteration of the calendars of each run of starts (run_id, n0) up to iteration n0 * times."""
    count = 1
    while sum(math.exp(decay * i) for i in range(count)) < times:
        count += 1
    last = F.col("n0") * times
    decaying = schedules(starts, decay, count).where(F.col("at_iteration") <= last).select("run_id", F.lit("decay").alias("kind"), "t", "at_iteration")
    each = starts.where("n0 > 0").select("run_id", F.lit("every").alias("kind"), F.explode(F.sequence(F.lit(1).cast("long"), last)).alias("t"))
    fixed = starts.select("run_id", F.lit("fixed").alias("kind"), F.explode(F.sequence(F.lit(1).cast("long"), F.lit(times).cast("long"))).alias("t"), "n0")
    return decaying.unionByName(each.withColumn("at_iteration", F.col("t"))).unionByName(fixed.select("run_id", "kind", "t", (F.col("t") * F.col("n0")).alias("at_iteration")))
