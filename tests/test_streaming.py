import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketnet.operators import hashing, index, sampling
from bucketnet.plans.kernel import NetConf
from bucketnet.queries import relational
from bucketnet.sources import synthetic
from bucketnet.sources.tables import SCHEMAS, every, load, vectors
from bucketnet.streaming import online

SMALL = "/root/testdata/sf0.001"
FAM = hashing.SimHash(4, 3, 64, 11)
CODES = "id long, table_id int, code long, seq long"


@pytest.fixture(scope="module")
def code_files(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("codes") / "c")
    FAM.codes(vectors(spark, SMALL), "id", "vec").withColumn("seq", F.col("id")).repartition(3).write.parquet(path)
    return path


@pytest.mark.parametrize("policy", ["reservoir", "fifo"])
def test_bucket_state_equals_batch(spark, code_files, policy):
    out = online.run_to_memory(online.bucket_stream(online.stream_table(spark, code_files, CODES), 4, policy), f"b_{policy}", "update")
    last = out.groupBy("table_id", "code").agg(F.max_by("ids", "n").alias("ids")).select("table_id", "code", F.explode("ids").alias("id"))
    want = index.build_index(FAM.codes(vectors(spark, SMALL), "id", "vec"), 4, policy).select("table_id", "code", "id")
    assert last.count() == want.count() and want.exceptAll(last).count() == 0


def test_probe_of_a_stream(spark, code_files):
    bucket = index.build_index(FAM.codes(vectors(spark, SMALL), "id", "vec"))
    q = online.stream_table(spark, code_files, CODES).where("id % 50 = 0").select("id", "table_id", "code")
    got = online.run_to_memory(online.probe_stream(q, bucket), "probe")
    want = sampling.probe(every(FAM.codes(vectors(spark, SMALL), "id", "vec")), bucket)
    assert got.count() == want.count() and want.exceptAll(got).count() == 0


def test_clock_equals_calendar(spark, tmp_path):
    for i in range(4):
        spark.range(1 + 100 * i, 101 + 100 * i).select(F.lit("r").alias("run_id"), F.col("id").alias("iteration")).coalesce(1).write.mode("append").parquet(str(tmp_path / "i"))
    s = online.stream_table(spark, str(tmp_path / "i"), "run_id string, iteration long")
    got = sorted(r.iteration for r in online.run_to_memory(online.refresh_clock(s, 50, 0.1), "clock").collect())
    want = [r.at_iteration for r in index.rehash_schedule(spark, 50, 0.1, 8).where("at_iteration <= 400").orderBy("t").collect()]
    assert got == want


@pytest.fixture(scope="module")
def event_files(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events") / "e")
    load(spark, SMALL, "events").withColumn("ts", F.col("ts").cast("timestamp")).repartitionByRange(4, "ts").write.parquet(path)
    return path


SCHEMA = SCHEMAS["events"].replace("timestamp_ntz", "timestamp")


def test_tumbling_equals_batch(spark, event_files):
    e = online.stream_table(spark, event_files, SCHEMA, 100)
    got = online.run_to_memory(online.window_features(e, "tumbling", late="100 days"), "tumbling", "complete")
    want = relational.QUERIES["q_events_tumbling"](spark, SMALL)
    assert {(str(r.begins), r.event_type, r.n) for r in got.collect()} == {(str(r.begins), r.event_type, r.n) for r in want.collect()}


def test_late_rows_are_dropped(spark, tmp_path):
    row = lambda i, ts: spark.createDataFrame([(i, ts, "a")], "event_id long, ts string, event_type string").withColumn("ts", F.to_timestamp("ts")).coalesce(1)
    path = str(tmp_path / "l")
    # a watermark drops rows from the second batch after the one that moved it
    for i, ts in enumerate(("2024-01-01 00:10:00", "2024-01-01 05:00:00", "2024-01-01 05:01:00", "2024-01-01 00:20:00", "2024-01-01 04:55:00")):
        row(i, ts).write.mode("append").parquet(path)
        time.sleep(1.1)  # files are taken by their time
    s = online.stream_table(spark, path, "event_id long, ts timestamp, event_type string")
    got = online.run_to_memory(online.window_features(s, "tumbling", late="10 minutes"), "late", "update")
    n = {str(r.begins): r.n for r in got.groupBy("begins").agg(F.max("n").alias("n")).collect()}
    assert n == {"2024-01-01 00:00:00": 1, "2024-01-01 05:00:00": 2, "2024-01-01 04:00:00": 1}


def test_stream_join_equals_batch(spark, event_files):
    a, b = (online.stream_table(spark, event_files, SCHEMA, 100) for _ in range(2))
    got = online.run_to_memory(online.join_streams(a, b), "joined")
    want = relational.QUERIES["q_events_interval"](spark, SMALL).agg(F.sum("following")).first()[0]
    assert got.count() == (want or 0)


def test_dedup(spark, event_files):
    s = online.stream_table(spark, event_files, SCHEMA, 100)
    twice = s.unionByName(online.stream_table(spark, event_files, SCHEMA, 100))
    got = online.run_to_memory(online.dedup_stream(twice, ["event_id"], "100 days").select("event_id"), "dedup")
    assert got.count() == load(spark, SMALL, "events").count()


def test_online_training_and_repeated_batches(spark, tmp_path):
    spark.dataSource.register(synthetic.SyntheticSparse)
    d = spark.read.format("synthetic_sparse").options(rows=200, dims=100, labels=8, nonzeros=10, partitions=2).load()
    d.write.parquet(str(tmp_path / "t"))
    trainer = online.OnlineTrainer(NetConf(100, 8, 8, strategy="dense", batch=50), local_steps=5)
    s = online.stream_table(spark, str(tmp_path / "t"), "instance_id long, feats array<int>, vals array<float>, labels array<int>")
    online.train_stream(s, trainer, str(tmp_path / "cp")).awaitTermination()
    assert trainer.snapshot.step == 10
    w = trainer.snapshot.w_out.copy()
    trainer(d, 0)  # comes again after a failure
    assert (trainer.snapshot.w_out == w).all() and np.isfinite(w).all()


def test_online_model_survives_a_restart(spark, tmp_path):
    spark.dataSource.register(synthetic.SyntheticSparse)
    conf, schema = NetConf(100, 8, 8, strategy="dense", batch=50), "instance_id long, feats array<int>, vals array<float>, labels array<int>"
    d = spark.read.format("synthetic_sparse").options(rows=200, dims=100, labels=8, nonzeros=10, partitions=2).load().persist()

    def go(trainer, cp):
        online.train_stream(online.stream_table(spark, str(tmp_path / "t"), schema), trainer, str(tmp_path / cp)).awaitTermination()
        return trainer

    d.where("instance_id % 2 = 0").coalesce(1).write.parquet(str(tmp_path / "t"))
    go(online.OnlineTrainer(conf, local_steps=3, path=str(tmp_path / "m")), "cp")
    d.where("instance_id % 2 = 1").coalesce(1).write.mode("append").parquet(str(tmp_path / "t"))
    second = go(online.OnlineTrainer(conf, local_steps=3, path=str(tmp_path / "m")), "cp")
    assert [x["batch_id"] for x in second.log] == [1] and second.snapshot.step == 6
    third = online.OnlineTrainer(conf, local_steps=3, path=str(tmp_path / "m"))
    third(d, 1)  # the batch comes again to a trainer that has just begun
    assert third.log == [] and third.snapshot.step == 6
    assert np.array_equal(third.snapshot.w_out, second.snapshot.w_out) and np.array_equal(third.snapshot.moments["w_in.v"], second.snapshot.moments["w_in.v"])
