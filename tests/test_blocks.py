import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketnet.plans import blocks, shards
from bucketnet.plans.choose import Sizes, choose, sampling_strategy
from bucketnet.plans.kernel import NetConf, Snapshot, Trainer
from bucketnet.sources import synthetic


@pytest.fixture(scope="module")
def data(spark):
    spark.dataSource.register(synthetic.SyntheticSparse)
    d = spark.read.format("synthetic_sparse").options(rows=600, dims=400, labels=40, nonzeros=20).load()
    return d.persist()


def test_one_learner_is_plain_training(data):
    conf = NetConf(400, 8, 40, strategy="dense", batch=10**6)
    rows = data.coalesce(1).sortWithinPartitions("instance_id")
    model, _ = blocks.train(rows, conf, rounds=3)
    plain = Trainer(conf, Snapshot.start(conf))
    whole = blocks.Rows(rows.select("feats", "vals", "labels").toArrow().to_batches())
    for _ in range(3):
        plain.step(*whole.take(np.arange(whole.n)))
    assert np.allclose(model.snapshot.w_out, plain.at.w_out, atol=1e-4)
    assert np.allclose(model.snapshot.w_in, plain.at.w_in, atol=1e-4)


@pytest.mark.parametrize("resolve", ["mean", "sum", "random_one"])
def test_learners_converge(data, resolve):
    conf = NetConf(400, 16, 40, strategy="topk", k=3, tables=8, beta=12, batch=32, rate=1e-2)
    model, log = blocks.train(data.repartition(2, "instance_id"), conf, rounds=4, local_steps=15, resolve=resolve, test=data, eval_every=4)
    assert log[-1]["p_at_1"] > 0.5
    assert 0 < log[-1]["active_frac"] < 0.5
    exact, sampled = (blocks.accuracy(blocks.predict(data, model, 1, m), data) for m in ("exact", "sampled"))
    assert sampled <= exact + 0.1


def test_save_and_load(spark, data, tmp_path):
    conf = NetConf(400, 8, 40, strategy="dense")
    m = blocks.Model(conf, Snapshot.start(conf))
    m.save(spark, str(tmp_path / "m"))
    again = blocks.Model.load(spark, str(tmp_path / "m"), conf)
    assert (again.snapshot.w_out == m.snapshot.w_out).all() and (again.snapshot.w_in == m.snapshot.w_in).all()


def test_too_large_a_snapshot_is_refused(data, monkeypatch):
    monkeypatch.setattr(blocks, "SNAPSHOT_LIMIT", 10)
    with pytest.raises(ValueError, match="plans.shards"):
        blocks.train(data, NetConf(400, 8, 40), rounds=1)


@pytest.mark.parametrize("parts", [1, 3])
def test_shards_equal_a_dense_step(spark, parts):
    rng = np.random.default_rng(0)
    w, h = rng.normal(size=(30, 5)).astype(np.float32), np.abs(rng.normal(size=(4, 5))).astype(np.float32)
    labels = [[1], [2, 9], [29], [0]]
    conf = NetConf(1, 5, 30, strategy="dense", rate=0.1, optimizer="sgd")
    flat = np.concatenate(labels), np.array([0, 1, 3, 4, 5])
    new, back, _ = shards.shard_step(shards.as_params(spark, w, parts, conf), conf, h, *flat)
    z = h @ w.T
    p = np.exp(z - z.max(axis=1, keepdims=True))
    p /= p.sum(axis=1, keepdims=True)
    for i, ls in enumerate(labels):
        p[i, ls] -= 1 / len(ls)
    p /= 4
    got = {r.label: r.w for r in new.collect()}
    assert np.allclose(np.array([got[i] for i in range(30)]), w - 0.1 * p.T @ h, atol=1e-5)
    assert np.allclose(back, p @ w, atol=1e-5)
    with pytest.raises(ValueError):
        shards.shard_step(shards.as_params(spark, w, 1, conf), NetConf(1, 5, 30, strategy="topk"), h, *flat)


@pytest.mark.parametrize("parts,conf", [
    (3, NetConf(100, 8, 60, strategy="dense", batch=32, rate=0.01)),
    (1, NetConf(100, 8, 60, strategy="threshold", k=2, tables=6, batch=32, rate=0.01, n0=3, incremental=False)),
    (3, NetConf(100, 8, 60, strategy="union", k=3, tables=4, batch=32, rate=0.5, optimizer="sgd", n0=3, incremental=False)),
])
def test_training_in_shards_equals_one_learner(spark, parts, conf):
    spark.dataSource.register(synthetic.SyntheticSparse)
    d = spark.read.format("synthetic_sparse").options(rows=150, dims=100, labels=60, nonzeros=10, partitions=2).load().persist()
    model, log = shards.train(d, conf, 8, parts, cut_every=5)
    one = Snapshot.start(conf)
    one.w_out[:] = shards.first_weights(conf, np.arange(60))
    learner = Trainer(conf, one)
    losses = []
    while one.step < 8:
        rows = shards.draw(d, conf, one.step, min(shards.AHEAD, 8 - one.step))
        losses += [learner.step(*rows.take(np.arange(a, min(a + 32, rows.n)))) for a in range(0, rows.n, 32)]
    got = {r.label: r.w for r in model.params.collect()}
    assert sorted(got) == list(range(60)) and len(log) == 8 == model.inner.at.step
    assert np.allclose([x["loss"] for x in log], losses, atol=1e-4)
    assert np.abs(np.array([got[i] for i in range(60)]) - one.w_out).max() < 2e-3
    assert np.abs(model.inner.at.w_in - one.w_in).max() < 2e-3
    assert [x["iteration"] for x in log if x["refreshed"]] == ([] if conf.strategy == "dense" else [3, 7])
    rows = shards.draw(d, conf, 0, 2)
    best = {(r.i, r.rank): r.label for r in model.top(rows, 2).collect()}
    feats, vals, off, _, _ = rows.take(np.arange(rows.n))
    top, _ = learner.predict(feats, vals, off, 2)
    assert np.mean([best[i, j + 1] == top[i, j] for i in range(rows.n) for j in range(2)]) > 0.97
    assert 0 <= model.p_at_1(rows) <= 1
    assert shards.train(d.where("false"), conf, 3, 2)[1] == []


def test_first_weights_do_not_depend_on_shards(spark):
    conf = NetConf(1, 4, 9000, strategy="dense")
    for parts in (1, 7):
        got = {r.label: r.w for r in shards.start(spark, conf, parts).collect()}
        assert np.array_equal(np.array([got[i] for i in range(9000)], dtype=np.float32), shards.first_weights(conf, np.arange(9000)))


def test_choice_of_plan():
    assert choose(Sizes(256, 8, 64, 10, 8)) == "relational"
    assert choose(Sizes(135_909, 128, 670_091, 256, 3000)) == "blocks"
    assert choose(Sizes(10**6, 128, 10**8, 256, 3000)) == "shards"
    assert sampling_strategy(50, 500, True) == "topk" and sampling_strategy(50, 60, True) == "threshold" and sampling_strategy(50, 500, False) == "vanilla"


def test_instances_from_rows(spark):
    f = spark.createDataFrame([(1, 4, 3.0), (1, 2, 4.0), (2, 0, 1.0)], "instance_id long, idx int, val double")
    lab = spark.createDataFrame([(1, 7), (1, 7), (1, 3), (3, 1)], "instance_id long, label int")
    (r,) = blocks.as_instances(f, lab).collect()
    assert (r.instance_id, r.feats, r.labels) == (1, [2, 4], [3, 7])
    assert np.allclose(r.vals, [0.8, 0.6])
    assert blocks.as_instances(f.where(F.lit(False)), lab).count() == 0


def test_a_run_leaves_no_snapshots_on_the_disk(spark, data, monkeypatch):
    import os

    made, sc = [], spark.sparkContext
    send = sc.broadcast
    monkeypatch.setattr(sc, "broadcast", lambda x: made.append(send(x)) or made[-1])
    blocks.train(data.coalesce(1), NetConf(400, 8, 40, strategy="dense", batch=64), rounds=2, test=data, eval_every=1)
    assert len(made) == 4 and not any(os.path.exists(b._path) for b in made)


@pytest.mark.parametrize("change", [{"strategy": "topk", "beta": 12, "n0": 4}, {"strategy": "static", "beta": 9, "weighted": True}])
def test_a_single_learner_is_one_task(spark, data, change, monkeypatch):
    """The run log of train on one partition; what a task is sent are the rows of its batches, what the driver holds are weights without moments."""
    conf = NetConf(400, 8, 40, k=3, tables=8, batch=16, rate=1e-2, **change)
    rows = data.repartition(1).sortWithinPartitions("instance_id").persist()
    model, want = blocks.train(rows, conf, rounds=4, local_steps=3, test=data, eval_every=2)
    made, sc, picked, pick = [], spark.sparkContext, [], blocks.pick
    send = sc.broadcast
    monkeypatch.setattr(sc, "broadcast", lambda x: made.append(x) or send(x))
    monkeypatch.setattr(blocks, "pick", lambda *a: picked.append(pick(*a)) or picked[0])
    ((name, log, done),) = blocks.train_one(rows, {"run": conf}, 4, 3, data, 2)
    assert name == "run" and [x["iteration"] for x in log] == [6, 12]
    for a, b in zip(log, want, strict=True):
        assert all(abs(a[k] - b[k]) < 1e-3 for k in ("p_at_1", "loss", "active_mean", "active_frac"))
    assert [r["iteration"] for r in done["refreshes"]] == [r["iteration"] for r in model.kept.log]
    if model.kept.tables:
        assert (done["moved"], done["hash_operations"]) == (model.kept.tables.moved, model.kept.tables.hashed)
    assert not any(isinstance(x, Snapshot) or any(isinstance(y, Snapshot) for y in x if not isinstance(x, bytes)) for x in made)
    assert max(len(x) for x in made if isinstance(x, bytes)) <= blocks.CHUNK
    assert 0 < picked[0].count() <= 12 * 16 < data.count()


def test_rows_are_picked_by_their_number(spark, data):
    rows = data.repartition(5, "instance_id").where("instance_id % 3 != 0").persist()
    sizes = blocks.sizes_of(rows)
    assert sizes.sum() == rows.count() and len(sizes) <= 5
    every = blocks.pick(rows, sizes, np.arange(sizes.sum()))
    one = {(tuple(r.feats), tuple(r.labels)) for r in every.collect()}
    assert one == {(tuple(r.feats), tuple(r.labels)) for r in rows.collect()}
    some = blocks.pick(rows, sizes, np.array([0, 7, sizes.sum() - 1]))
    assert sorted(r.place for r in some.collect()) == [0, 7, sizes.sum() - 1] and some.rdd.getNumPartitions() == 1
    assert list(blocks.train_one(rows.where("false"), {"x": NetConf(400, 8, 40)}, 1)) == []


def test_hit_rate_is_accuracy_of_predictions(spark, data):
    conf = NetConf(400, 8, 40, strategy="dense", batch=64, rate=1e-2)
    model, _ = blocks.train(data.coalesce(1), conf, rounds=1, local_steps=20)
    shared = spark.sparkContext.broadcast((model.snapshot.w_in, model.snapshot.w_out))
    assert abs(blocks.hit_rate(data, conf, shared) - blocks.accuracy(blocks.predict(data, model, 1), data)) < 1e-9
    assert blocks.hit_rate(data.where("false"), conf, shared) == 0


@pytest.mark.parametrize("strategy", ["dense", "threshold", "union"])
def test_a_shard_looks_at_few_pairs_together(strategy, monkeypatch):
    """Blocks of instances give the step of the whole batch, and no product is larger than a block's."""
    conf = NetConf(10, 6, 500, strategy=strategy, k=2, tables=6, rate=0.01)
    rng = np.random.default_rng(2)
    h, labels, off = np.abs(rng.normal(size=(40, 6))).astype(np.float32), rng.integers(0, 500, 80), np.arange(0, 81, 2)
    w, seen, logits = rng.normal(size=(500, 6)).astype(np.float32), [], shards.Layer.logits
    monkeypatch.setattr(shards.Layer, "logits", lambda *a: seen.append(z := logits(*a)) or z)
    got = []
    for most in (1 << 20, 3000):
        monkeypatch.setattr(shards, "PAIRS", most)
        seen.clear()
        layer = shards.Layer.fresh(conf, np.arange(500), w.copy())
        i, top, s = shards._measure(conf, layer, h, labels, off, 0)
        highest, norm = np.zeros(40), np.ones(40)
        highest[i], norm[i] = top, s
        got.append((i, top, s, *shards._move(conf, layer, h, labels, off, 0, highest, norm), layer.w, layer.m, layer.v))
        assert max(z.size for z in seen) <= max(most, 3000) and (len(seen) > 8) == (most == 3000)
    for a, b in zip(*got, strict=True):
        assert np.allclose(a, b, atol=1e-5)


@pytest.mark.parametrize("resolve", ["mean", "sum", "random_one"])
@pytest.mark.parametrize("change", [{"strategy": "topk", "beta": 12, "n0": 4}, {"strategy": "dense"}])
def test_stale_learners_are_one_task(spark, data, resolve, change, monkeypatch):
    """The run log of train on a partition a learner; the driver gets no snapshot, no tables and no change of a row."""
    conf = NetConf(400, 8, 40, k=3, tables=8, batch=16, rate=1e-2, **change)
    rows = data.repartition(1).sortWithinPartitions("instance_id").persist()
    rows.count()
    model, want = blocks.train(rows.repartition(3, "instance_id"), conf, rounds=4, local_steps=3, resolve=resolve, test=data, eval_every=2)
    made, sc = [], spark.sparkContext
    send = sc.broadcast
    monkeypatch.setattr(sc, "broadcast", lambda x: made.append(x) or send(x))
    ((name, log, done),) = blocks.train_apart(rows, {"run": blocks.Run(conf, 3, resolve)}, 4, 3, data, 2)
    assert name == "run" and [x["iteration"] for x in log] == [6, 12]
    for a, b in zip(log, want, strict=True):
        assert all(abs(a[k] - b[k]) < 1e-4 for k in ("p_at_1", "loss", "active_mean", "active_frac"))
    assert [r["iteration"] for r in done["refreshes"]] == [r["iteration"] for r in model.kept.log]
    if model.kept.tables:
        assert (done["moved"], done["hash_operations"]) == (model.kept.tables.moved, model.kept.tables.hashed)
    assert all(isinstance(x, bytes) or isinstance(x[0], dict) for x in made) and made


def test_runs_side_by_side_are_those_alone(spark, data, monkeypatch):
    """As many runs in a job as their weights and tables leave room for, with the same results."""
    rows = data.repartition(1).sortWithinPartitions("instance_id").persist()
    confs = {s: NetConf(400, 8, 40, strategy=s, k=3, tables=8, batch=16, rate=1e-2) for s in ("topk", "dense", "static")}
    alone = {n: (log, done) for n, log, done in blocks.train_one(rows, confs, 2, 3, data, 1)}
    made, learner = [], blocks._learner
    monkeypatch.setattr(blocks, "_learner", lambda *a: made.append(a[0].conf.strategy) or learner(*a))
    size = max(blocks.Run(c).size for c in confs.values())
    for most, first in ((3 * size, 3), (2 * size, 2), (size // 2, 1)):
        monkeypatch.setattr(blocks, "ABREAST", most)
        made.clear()
        got = {}
        for n, log, done in blocks.train_one(rows, confs, 2, 3, data, 1, abreast=True):
            assert got or len(made) == first
            got[n] = log, done
        assert list(got) == list(confs)
        for n, (log, done) in got.items():
            assert done == alone[n][1]
            assert [{k: v for k, v in x.items() if k != "wall_ms"} for x in log] == [{k: v for k, v in x.items() if k != "wall_ms"} for x in alone[n][0]]
