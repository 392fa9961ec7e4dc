"""Structured Streaming forms: online training, buckets and clocks as state, windows, late rows, joins and dedup."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from bucketnet.functions.seeds import h32_of
from bucketnet.plans import blocks
from bucketnet.plans.kernel import NetConf, Snapshot


def stream_table(spark: SparkSession, path: str, schema: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


class OnlineTrainer:
    """A foreachBatch sink that trains on each micro-batch once: a batch id that was done is passed over when it comes again.

    path: a shared folder for the model. It is written after each batch, and its mark after it, so a new trainer on the same
    folder and stream checkpoint goes on where the last whole batch ended; of a batch cut off in between nothing stays. The two last models are kept.
    Without a path the model lives with the object alone. Tables are built anew for each micro-batch.
    """

    def __init__(self, conf: NetConf, start: Snapshot | None = None, local_steps: int = 1, path: str | None = None):
        self.conf, self.snapshot, self.local_steps, self.path = conf, start or Snapshot.start(conf), local_steps, path
        self.last, self.known = -1, path is None
        self.log: list[dict] = []

    def _folder(self, spark: SparkSession, name: str) -> tuple:
        place = spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return place.getFileSystem(spark._jsc.hadoopConfiguration()), place

    def recover(self, spark: SparkSession) -> None:
        """The model of the newest mark, if there is any."""
        self.known = True
        fs, place = self._folder(spark, "marks")
        if fs.exists(place):
            newest = spark.read.schema("batch_id long").parquet(f"{self.path}/marks").agg(F.max("batch_id")).first()[0]
            if newest is not None:
                self.last, self.snapshot = newest, blocks.Model.load(spark, f"{self.path}/model-{newest}", self.conf).snapshot

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        if not self.known:
            self.recover(spark)
        if batch_id <= self.last:
            return
        rows = batch.select("instance_id", "feats", "vals", "labels").coalesce(1)  # a micro-batch is one learner's batch
        model, _ = blocks.train(rows, self.conf, rounds=1, local_steps=self.local_steps, start=self.snapshot)
        if self.path is not None:
            model.save(spark, f"{self.path}/model-{batch_id}")
            spark.range(1).select(F.lit(batch_id).cast("long").alias("batch_id")).coalesce(1).write.mode("append").parquet(f"{self.path}/marks")
            fs, old = self._folder(spark, f"model-{batch_id - 2}")
            fs.delete(old, True)
        self.snapshot, self.last = model.snapshot, batch_id
        self.log.append({"batch_id": batch_id, "step": self.snapshot.step})


def train_stream(stream: DataFrame, trainer: OnlineTrainer, checkpoint: str) -> StreamingQuery:
    return stream.writeStream.foreachBatch(trainer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def bucket_stream(codes: DataFrame, cap: int, policy: str = "fifo", seed: int = 11) -> DataFrame:
    """table_id, code, n, ids: each bucket's bounded content after each micro-batch (update mode).

    State of a bucket: how many arrived, and at most cap (priority or order, id). Reservoir keeps the smallest
    seeded priorities, as the batch operator does, so both agree whatever the order of arrival.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, held = (state.get[0], [tuple(map(int, x.split(":"))) for x in state.get[1].split(",") if x]) if state.exists else (0, [])
        for b in batches:
            for i, seq in zip(b["id"].tolist(), b["seq"].tolist(), strict=True):
                held.append((h32_of(seed, i, key[0]) if policy == "reservoir" else -seq, i))
                n += 1
            held = sorted(set(held))[:cap]
        state.update((n, ",".join(f"{p}:{i}" for p, i in held)))
        yield pd.DataFrame({"table_id": [key[0]], "code": [key[1]], "n": [n], "ids": [[i for _, i in held]]})

    return codes.groupBy("table_id", "code").applyInPandasWithState(step, "table_id int, code long, n long, ids array<long>", "n long, held string", "update", GroupStateTimeout.NoTimeout)


def refresh_clock(iterations: DataFrame, n0: float, decay: float) -> DataFrame:
    """run_id, iteration of each refresh that is due, from a stream (run_id, iteration) in order: the calendar as state."""
    import math

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        done, due = state.get if state.exists else (0, float(n0))
        fired = []
        for b in batches:
            for i in sorted(b["iteration"].tolist()):
                if i >= math.ceil(due - 1e-9):
                    fired.append(i)
                    while i >= math.ceil(due - 1e-9):
                        done += 1
                        due += n0 * math.exp(decay * done)
        state.update((done, due))
        yield pd.DataFrame({"run_id": [key[0]] * len(fired), "iteration": fired})

    return iterations.groupBy("run_id").applyInPandasWithState(step, "run_id string, iteration long", "done long, due double", "append", GroupStateTimeout.NoTimeout)


def window_features(stream: DataFrame, kind: str, width: str = "1 hour", slide: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Counts by tumbling, sliding or session windows with a watermark; later rows are dropped and counted by Spark's progress report."""
    w = {"tumbling": lambda: F.window("ts", width), "sliding": lambda: F.window("ts", width, slide), "session": lambda: F.session_window("ts", width)}[kind]()
    key = "user_id" if kind == "session" else "event_type"
    return stream.withWatermark("ts", late).groupBy(w.alias("w"), key).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("begins"), key, "n")


def probe_stream(query_codes: DataFrame, bucket: DataFrame) -> DataFrame:
    """A stream of query codes against a fixed index."""
    from bucketnet.operators.sampling import probe

    return probe(query_codes, bucket)


def join_streams(a: DataFrame, b: DataFrame, within: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Events of b of the same user within the span after one of a; watermarks bound what is kept."""
    left = a.select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts")).withWatermark("a_ts", late)
    right = b.select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts")).withWatermark("b_ts", late)
    return left.join(right, F.expr(f"a_user = b_user AND b_ts > a_ts AND b_ts <= a_ts + interval {within}")).select("a_id", "b_id")


def dedup_stream(stream: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def run_to_memory(df: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs all that is there and returns the sink's table."""
    w = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    q = (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()
    q.awaitTermination()
    return df.sparkSession.table(name)

