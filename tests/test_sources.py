import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketnet.functions import udfs
from bucketnet.operators import hashing, network
from bucketnet.sources import eventlog, sparse_text, synthetic
from bucketnet.sources.tables import SCHEMAS, load, vectors

SMALL = "/root/testdata/sf0.001"


def test_declared_schemas_hold(spark):
    for name, ddl in SCHEMAS.items():
        have = dict(load(spark, SMALL, name).dtypes)
        want = {c.split(" ")[0]: c.split(" ")[1] for c in ddl.split(", ")}
        want = {c: {"long": "bigint"}.get(t, t) for c, t in want.items()}
        assert have.keys() == want.keys(), name
        assert {c: t.replace("timestamp_ntz", "timestamp") for c, t in have.items()} == {c: t.replace("timestamp_ntz", "timestamp") for c, t in want.items()}, name


def test_sparse_text_round_trip(spark, tmp_path):
    d = spark.createDataFrame([([1, 2], [4, 7], [0.5, 2.0]), ([], [3], [1.0]), ([9], [], [])], "labels array<int>, feats array<int>, vals array<double>")
    sparse_text.write_sparse_text(d, str(tmp_path / "t"))
    back = sparse_text.read_sparse_text(spark, str(tmp_path / "t"))
    assert {(tuple(r.labels), tuple(r.feats), tuple(r.vals)) for r in back.collect()} == {(tuple(r.labels), tuple(r.feats), tuple(r.vals)) for r in d.collect()}


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "parquet"])
def test_formats(spark, tmp_path, kind):
    d = spark.createDataFrame([(1, "a"), (2, None)], "x long, y string")
    d.write.format(kind).save(str(tmp_path / kind))
    assert {tuple(r) for r in sparse_text.read_any(spark, kind, str(tmp_path / kind), "x long, y string").collect()} == {(1, "a"), (2, None)}
    if kind in ("csv", "json"):
        with pytest.raises(ValueError):
            sparse_text.read_any(spark, kind, str(tmp_path / kind))


def test_synthetic_source(spark):
    spark.dataSource.register(synthetic.SyntheticSparse)
    read = lambda parts: {(r.instance_id, tuple(r.feats)) for r in spark.read.format("synthetic_sparse").options(rows=50, partitions=parts).load().collect()}
    assert read(1) == read(3) and len(read(2)) == 50


def test_filter_reaches_the_scan(spark):
    from bucketnet.queries.relational import QUERIES

    plan = QUERIES["q_filter_lineitem_shipdate"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull" in plan and "l_tax" not in plan.split("ReadSchema")[1]


def test_index_on_disk_is_pruned(spark, tmp_path):
    from bucketnet.operators.index import build_index

    b = build_index(hashing.SimHash(4, 3, 64).codes(vectors(spark, SMALL), "id", "vec"))
    sparse_text.write_index(b, str(tmp_path / "i"))
    one = spark.read.parquet(str(tmp_path / "i")).where("table_id = 1")
    assert "PartitionFilters: [isnotnull(table_id" in one._jdf.queryExecution().executedPlan().toString()
    assert one.count() == b.where("table_id = 1").count()


def test_sql_functions(spark):
    fam = hashing.SimHash(4, 3, 64, 11)
    udfs.register(spark, fam)
    v = vectors(spark, SMALL)
    v.createOrReplaceTempView("v")
    assert udfs.agree(v, fam, "id", "vec").count() == 0
    lateral = spark.sql("SELECT id, table_id, code FROM v, LATERAL lsh_codes(vec)")
    assert lateral.exceptAll(fam.codes(v, "id", "vec")).count() == 0
    r = spark.sql("SELECT prob_union(0.5D, 9, 50) p, hamming64(7, 1) h, vec_dot(array(1D, 2D), array(3D, 4D)) d").first()
    assert abs(r.p - 0.09313) < 1e-5 and r.h == 2 and r.d == 11
    assert abs(spark.sql("SELECT logsumexp(x) y FROM VALUES (1D), (2D) t(x)").first().y - np.log(np.exp(1) + np.exp(2))) < 1e-9


def test_event_log_measures(spark, tmp_path):
    line = '{"Event":"SparkListenerTaskEnd","Stage ID":3,"Task Info":{"Launch Time":1000,"Finish Time":%d},"Task Metrics":{"Executor Run Time":%d,"Executor CPU Time":%d,"JVM GC Time":5,"Executor Deserialize Time":10,"Result Serialization Time":0,"Peak Execution Memory":7,"Memory Bytes Spilled":0,"Disk Bytes Spilled":2}}\n'
    (tmp_path / "log").write_text('{"Event":"SparkListenerStageCompleted"}\n' + line % (2000, 900, 450_000_000) + line % (2000, 700, 350_000_000))
    t = eventlog.read_event_log(spark, str(tmp_path / "log"))
    u = eventlog.core_utilisation(t, 2).first()
    assert abs(u.busy - 0.8) < 1e-9 and abs(u.jvm_cpu_share - 0.5) < 1e-9
    s = eventlog.stage_breakdown(t).first()
    assert (s.stage, s.tasks, s.gc_ms, s.scheduler_ms, s.spilled_bytes) == (3, 2, 10, 90 + 290, 4)


def test_exact_batches(spark):
    d = spark.range(25).withColumnRenamed("id", "instance_id")
    sizes = sorted(r["count"] for r in network.batches(d, 10, 1, exact=True).groupBy("batch_id").count().collect())
    assert sizes == [5, 10, 10]
    assert network.batches(d, 10, 1).agg(F.count_distinct("batch_id")).first()[0] <= 3


def test_workers_elsewhere_get_the_package():
    """A driver that runs in another folder, without PYTHONPATH, can still use Python workers."""
    import os
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent
    code = f"import sys; sys.path.insert(0, {str(root)!r}); from bucketnet.session import local_session; s = local_session(1, 1, '1g'); import __spark_entry__ as e; assert e.entry(s).count() > 0"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    assert subprocess.run([sys.executable, "-c", code], cwd="/tmp", env=env, timeout=120, check=False).returncode == 0


def test_h32_of_many_texts_is_h32():
    import numpy as np

    from bucketnet.functions.md5 import h32_many
    from bucketnet.functions.seeds import h32_of

    texts = ["", "a", "wört", *("x" * n for n in (43, 44, 54, 55, 56, 64, 300)), *(f"w{i}" for i in range(9000))]
    raw = [x.encode() for x in texts]
    data, size = np.frombuffer(b"".join(raw), np.uint8), np.array([len(x) for x in raw])
    at = np.cumsum(size) - size
    assert h32_many(data, at, size).tolist() == [h32_of(x) for x in texts]
    prefix = np.frombuffer(b"".join(f"11|-1|{i % 90 + 10}|".encode() for i in range(len(raw))), np.uint8).reshape(len(raw), -1)
    assert h32_many(data, at, size, prefix).tolist() == [h32_of(11, -1, i % 90 + 10, x) for i, x in enumerate(texts)]


def test_known_item_instances_of_odd_texts(spark, tmp_path):
    """Empty and null texts, ids of other lengths and words longer than a block; no word goes through a lambda of a row."""
    from pyspark.sql import functions as F

    from bucketnet import workloads

    odd = [(7, "A b a b"), (123456, "c " + "long" * 40), (8, ""), (9, None), (None, "x y"), (10, "  ...x, X! ünï 东京"), (11, " ".join(f"w{i}" for i in range(3000))), (70, "A b a b")]
    spark.createDataFrame(odd, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    made = workloads.known_item_instances(spark, str(tmp_path), 64)
    want = workloads.known_item(spark, str(tmp_path), 64).groupBy("instance_id", "view").agg(F.sort_array(F.collect_set("idx")).alias("feats"), F.min("label").alias("label")).collect()
    got = {(r.instance_id, r.view): r for r in made.collect()}
    assert len(got) == len(want) > 0
    for r in want:
        x = got[r.instance_id, r.view]
        assert x.feats == r.feats and x.labels == [r.label] and len(x.vals) == len(x.feats)
    assert "lambdafunction" not in spark._jvm.PythonSQLUtils.explainString(made._jdf.queryExecution(), "simple")
