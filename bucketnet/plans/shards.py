"""Plan C: the output layer lives in shards of labels; hidden vectors of a batch travel, weights stay.

A shard finds its active labels in its own tables and returns (largest logit, sum of exponentials) per instance. Merged on
the executors these are the normaliser, with which the shard updates its rows and returns messages of the batch's size. Union and
threshold need no other merge, since a label is in one shard; top-k and vanilla would be merged over shards and are left to plan B.

A row of the layer is (label, w, m, v, code): Adam's moments and the label's codes go with it, so a shard's tables are sorted
from codes and nothing is hashed but where the calendar says. A shard must fit a task. The input layer stays on the driver, its size checked.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bucketnet.functions.seeds import h32, h32_of
from bucketnet.operators.index import Refresh
from bucketnet.plans.blocks import SNAPSHOT_LIMIT, Rows
from bucketnet.plans.kernel import Functions, NetConf, Snapshot, Tables, Trainer, _sum_rows, choose, descend

STATE = "label long, w array<float>, m array<float>, v array<float>, code array<long>"
STRATEGIES = ("union", "threshold", "dense")
BLOCK = 4096  # labels whose first weights come from one seed
AHEAD = 16  # batches drawn by one look at the instances
ROWS = 1 << 16
PAIRS = 1 << 20  # of instances and labels that a shard looks at together


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(np.ascontiguousarray(x).ravel()))


class Layer:
    """A shard's rows as arrays."""

    def __init__(self, ids: np.ndarray, w: np.ndarray, m: np.ndarray, v: np.ndarray, code: np.ndarray):
        self.ids, self.w, self.m, self.v, self.code = ids, w, m, v, code

    @classmethod
    def read(cls, batches: list[pa.RecordBatch]) -> Layer:
        n = sum(b.num_rows for b in batches)
        parts = [np.concatenate([np.array(b.column(c).flatten()) for b in batches]).reshape(n, -1) for c in ("w", "m", "v", "code")]
        return cls(np.concatenate([b.column("label").to_numpy() for b in batches]), *parts)

    @classmethod
    def fresh(cls, conf: NetConf, ids: np.ndarray, w: np.ndarray) -> Layer:
        code = Functions(conf)(w) if conf.strategy != "dense" else np.zeros((len(w), 0), np.int64)
        return cls(ids, w, np.zeros_like(w), np.zeros_like(w), code.astype(np.int64))

    def batches(self) -> Iterator[pa.RecordBatch]:
        for a in range(0, len(self.ids), ROWS):
            at = slice(a, a + ROWS)
            yield pa.RecordBatch.from_arrays([pa.array(self.ids[at]), *[_lists(x[at]) for x in (self.w, self.m, self.v, self.code)]], ["label", "w", "m", "v", "code"])

    def active(self, conf: NetConf, h: np.ndarray, labels: np.ndarray, offsets: np.ndarray, step: int) -> Iterator[tuple[int, np.ndarray, tuple | None, tuple]]:
        """By blocks of instances, each of about PAIRS pairs at most: the first instance, their hidden vectors, active pairs (None: all) and the (instance, place, share) of true labels that are here."""
        order = np.argsort(self.ids, kind="stable")
        ids = self.ids[order]
        inst = np.repeat(np.arange(len(h)), np.diff(offsets))
        at = np.minimum(np.searchsorted(ids, labels), len(ids) - 1)
        here = ids[at] == labels
        inst, place = inst[here], order[at[here]]
        share = 1.0 / np.diff(offsets)[inst]
        local, n = replace(conf, labels=len(ids)), len(ids)
        tables = None if conf.strategy == "dense" else Tables(local, self.w, self.code)
        seen = n if tables is None else n * conf.tables // tables.functions.buckets  # entries that an instance meets
        size = max(1, PAIRS // max(1, seen))
        for a in range(0, len(h), size):
            part, mine = h[a : a + size], (inst >= a) & (inst < a + size)
            own = inst[mine] - a, place[mine], share[mine]
            yield a, part, None if tables is None else choose(local, tables, part, self.w, own[:2], step, None, True)[:2], own

    def logits(self, h: np.ndarray, pairs: tuple | None) -> np.ndarray:
        return (h @ self.w.T if pairs is None else np.einsum("pd,pd->p", self.w[pairs[1]], h[pairs[0]])).astype(np.float64)


def _held(batches: Iterator[pa.RecordBatch]) -> Layer | None:
    held = [x for x in batches if x.num_rows]
    return Layer.read(held) if held else None


def _measure(conf: NetConf, layer: Layer, h: np.ndarray, labels: np.ndarray, offsets: np.ndarray, step: int) -> list[np.ndarray]:
    """Instances, their largest logit here and the sum of exponentials under it."""
    out = [[np.zeros(0, np.int64), np.zeros(0), np.zeros(0)]]
    for a, part, pairs, _ in layer.active(conf, h, labels, offsets, step):
        z = layer.logits(part, pairs)
        if pairs is None:
            top = z.max(axis=1)
            out.append([np.arange(a, a + len(part)), top, np.exp(z - top[:, None]).sum(axis=1)])
        elif len(z):
            at = np.flatnonzero(np.diff(pairs[0], prepend=-1))
            top = np.maximum.reduceat(z, at)
            size = np.diff(np.append(at, len(z)))
            out.append([pairs[0][at] + a, top, np.add.reduceat(np.exp(z - np.repeat(top, size)), at)])
    return [np.concatenate(x) for x in zip(*out, strict=True)]


def _move(conf: NetConf, layer: Layer, h: np.ndarray, labels: np.ndarray, offsets: np.ndarray, step: int, highest: np.ndarray, norm: np.ndarray) -> tuple[np.ndarray, np.ndarray, float, int]:
    """The layer takes its step; instances reached, their back-messages, the part of the loss and the number of pairs."""
    b, n = len(h), len(layer.ids)
    g, met, loss, count = np.zeros_like(layer.w), np.zeros(n, dtype=bool), 0.0, 0
    reached, back = [np.zeros(0, np.int64)], [np.zeros((0, h.shape[1]), np.float32)]
    for a, part, pairs, (inst, place, share) in layer.active(conf, h, labels, offsets, step):
        z, high, total = layer.logits(part, pairs), highest[a : a + len(part)], norm[a : a + len(part)]
        if pairs is None:
            p = np.exp(z - high[:, None]) / total[:, None]
            loss -= (share * np.log(p[inst, place] + 1e-30)).sum() / b
            p[inst, place] -= share
            p = (p / b).astype(np.float32)
            reached.append(np.arange(a, a + len(part)))
            back.append(p @ layer.w)
            g += p.T @ part
            met[:] = True
            count += len(part) * n
        elif len(z):
            i, lab = pairs
            p = np.exp(z - high[i]) / total[i]
            key, mine = i * n + lab, inst * n + place
            at = np.minimum(np.searchsorted(key, mine), len(key) - 1)
            there = key[at] == mine
            loss -= (share[there] * np.log(p[at[there]] + 1e-30)).sum() / b
            p[at[there]] -= share[there]
            p = (p / b).astype(np.float32)
            first = np.flatnonzero(np.diff(i, prepend=-1))
            reached.append(i[first] + a)
            back.append(np.add.reduceat(p[:, None] * layer.w[lab], first, axis=0))
            rows, sums = _sum_rows(p[:, None] * part[i], lab)
            g[rows] += sums
            met[rows] = True
            count += len(i)
    rows = np.flatnonzero(met)
    g = g if len(rows) == n else g[rows]
    reached, back = np.concatenate(reached), np.concatenate(back)
    descend(conf, step + 1, layer.w, layer.m, layer.v, rows, g)
    return reached, back, float(loss), count


def shard_step(params: DataFrame, conf: NetConf, h: np.ndarray, labels: np.ndarray, offsets: np.ndarray, step: int = 0, rehash: bool = False) -> tuple[DataFrame, np.ndarray, dict]:
    """params (STATE; partitions are shards) after a step on a batch of hidden vectors, the batch's back-messages, and
    what to know: loss, active pairs, held (the persisted frame under the new params, to be freed once those are no longer read).

    rehash: all labels get new codes from their new weights.
    """
    if conf.strategy not in STRATEGIES:
        raise ValueError("a shard knows only its own labels: use union, threshold or dense")
    sc = params.sparkSession.sparkContext
    shared = sc.broadcast((h, labels, offsets))  # a batch: its size is the caller's choice
    b, width = h.shape

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layer = _held(batches)
        if layer is not None:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in _measure(conf, layer, *shared.value, step)], ["i", "top", "s"])

    parts = params.mapInArrow(measure, "i long, top double, s double").groupBy("i").agg(F.max("top").alias("top"), F.collect_list(F.struct(F.col("top").alias("t"), "s")).alias("p"))  # a pair a shard
    merged = parts.select("i", "top", F.aggregate("p", F.lit(0.0), lambda a, x: a + x["s"] * F.exp(x["t"] - F.col("top"))).alias("s")).toArrow()  # batch rows
    highest, norm = np.zeros(b), np.ones(b)
    i = merged.column("i").to_numpy()
    highest[i], norm[i] = merged.column("top").to_numpy(), merged.column("s").to_numpy()
    scale = sc.broadcast((highest, norm))

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layer = _held(batches)
        if layer is None:
            return
        reached, back, loss, count = _move(conf, layer, *shared.value, step, *scale.value)
        if rehash and conf.strategy != "dense":
            layer.code = Functions(conf)(layer.w).astype(np.int64)
        for rows in layer.batches():
            yield pa.RecordBatch.from_arrays([pa.array(["w"] * rows.num_rows), *rows.columns], ["kind", *rows.schema.names])
        notes = [("back", reached, back.astype(np.float32)), ("note", np.zeros(1, np.int64), np.array([[loss, count]], dtype=np.float32))]
        for kind, ids, x in notes:
            if len(ids):
                nothing = [pa.nulls(len(ids), t) for t in (pa.list_(pa.float32()), pa.list_(pa.float32()), pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays([pa.array([kind] * len(ids)), pa.array(ids), _lists(x), *nothing], ["kind", "label", "w", "m", "v", "code"])

    both = params.mapInArrow(move, "kind string, " + STATE).persist()
    size = max(2, width)
    sums = [F.sum(F.get("w", F.lit(j)).cast("double")).alias(f"d{j}") for j in range(size)]
    t = both.where("kind != 'w'").groupBy("kind", "label").agg(*sums).toArrow()  # batch rows and one
    kind, row = np.array(t.column("kind").to_pylist()), t.column("label").to_numpy()
    d = np.stack([np.nan_to_num(t.column(f"d{j}").to_numpy()) for j in range(size)], axis=1)
    back = np.zeros((b, width), dtype=np.float32)
    back[row[kind == "back"]] = d[kind == "back", :width]
    note = d[kind == "note"].sum(axis=0)
    shared.unpersist()
    scale.unpersist()
    return both.where("kind = 'w'").drop("kind"), back, {"loss": float(note[0]), "active_mean": float(note[1]) / b, "held": both}


def as_params(spark: SparkSession, w: np.ndarray, shards: int, conf: NetConf) -> DataFrame:
    """A given layer as shards."""

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                yield from Layer.fresh(conf, x.column("label").to_numpy(), np.array(x.column("w").flatten()).reshape(x.num_rows, -1)).batches()

    t = pa.table({"label": pa.array(np.arange(len(w))), "w": pa.array(list(w), pa.list_(pa.float32()))})
    return spark.createDataFrame(t).repartition(shards, F.col("label")).mapInArrow(fill, STATE)


def first_weights(conf: NetConf, ids: np.ndarray) -> np.ndarray:
    """Rows of the layer that the seed gives, the same whoever asks; ids ascend."""
    out = []
    for block in np.unique(ids // BLOCK):
        rng = np.random.default_rng((conf.seed, h32_of("layer"), int(block)))
        w = rng.normal(0, 1 / np.sqrt(conf.hidden), (BLOCK, conf.hidden)).astype(np.float32)
        out.append(w[ids[ids // BLOCK == block] % BLOCK])
    return np.concatenate(out) if out else np.zeros((0, conf.hidden), np.float32)


def start(spark: SparkSession, conf: NetConf, shards: int) -> DataFrame:
    """The output layer at step 0, made on the executors."""

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                ids = x.column("id").to_numpy()
                yield from Layer.fresh(conf, ids, first_weights(conf, ids)).batches()

    return spark.range(0, conf.labels, 1, shards).mapInArrow(fill, STATE)


def draw(df: DataFrame, conf: NetConf, step: int, batches: int) -> Rows:
    """The instances of the next batches, in an order by a seeded hash of step and instance: at most batches x batch rows."""
    order = df.orderBy(h32(conf.seed, F.lit(step), F.col("instance_id")), "instance_id")
    return Rows(order.select("feats", "vals", "labels").limit(batches * conf.batch).toArrow().to_batches())


@dataclass
class Sharded:
    """inner: the input layer with its moments and step; params: the output layer (STATE)."""

    conf: NetConf
    inner: Trainer
    params: DataFrame

    def top(self, rows: Rows, k: int) -> DataFrame:
        """i, rank, label, score: the k best of all labels for each row of a block (its hidden vectors are broadcast)."""
        feats, vals, off, _, _ = rows.take(np.arange(rows.n))
        shared = self.params.sparkSession.sparkContext.broadcast(self.inner.hidden(feats, vals, off))

        def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            layer = _held(batches)
            if layer is None:
                return
            h = shared.value
            for a in range(0, len(h), 64):
                z = h[a : a + 64] @ layer.w.T
                near = np.argpartition(-z, min(k, z.shape[1]) - 1, axis=1)[:, :k]
                i = np.repeat(np.arange(len(z)) + a, near.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(layer.ids[near.ravel()]), pa.array(np.take_along_axis(z, near, axis=1).ravel().astype(np.float64))], ["i", "label", "score"])

        rank = F.row_number().over(Window.partitionBy("i").orderBy(F.desc("score"), "label"))
        return self.params.mapInArrow(best, "i long, label long, score double").withColumn("rank", rank).where(F.col("rank") <= k).select("i", "rank", "label", "score")

    def p_at_1(self, rows: Rows) -> float:
        """Over a block of instances that the driver holds."""
        if rows.n == 0:
            return 0.0
        _, _, _, labels, off = rows.take(np.arange(rows.n))
        true = {i: set(labels[a:b].tolist()) for i, (a, b) in enumerate(zip(off[:-1], off[1:], strict=True))}
        return sum(r.label in true[r.i] for r in self.top(rows, 1).collect()) / rows.n


def train(df: DataFrame, conf: NetConf, steps: int, shards: int, cut_every: int = 50) -> tuple[Sharded, list[dict]]:
    """Steps of the whole net, batch by batch, and a log row each step.

    df: instances (instance_id, feats, vals, labels), kept while this runs. Each step passes the layer twice through Python, so batches
    should be large. Lineage is cut by a checkpoint each cut_every steps (it needs spark.checkpoint.dir by then); these copies stay
    in that folder unless Spark is set to clean checkpoints. An empty df trains nothing.
    """
    if conf.strategy not in STRATEGIES:
        raise ValueError("a shard knows only its own labels: use union, threshold or dense")
    inside = replace(conf, strategy="dense", labels=1)
    inner = Trainer(inside, Snapshot.start(inside))
    if inner.at.size > SNAPSHOT_LIMIT:
        raise ValueError(f"an input layer of {inner.at.size} bytes is too large for the driver")
    clock = Refresh(conf.refresh, conf.n0, conf.decay)
    df = df.persist()
    params, held, log = start(df.sparkSession, conf, shards), None, []
    while inner.at.step < steps:
        rows = draw(df, conf, inner.at.step, min(AHEAD, steps - inner.at.step))
        if rows.n == 0:
            break
        for a in range(0, rows.n, conf.batch):
            feats, vals, off, labels, lab_off = rows.take(np.arange(a, min(a + conf.batch, rows.n)))
            h = inner.hidden(feats, vals, off)
            step = inner.at.step
            refreshed = conf.strategy != "dense" and clock.fires(step + 1)
            params, back, info = shard_step(params, conf, h, labels, lab_off, step, refreshed)
            back *= h > 0
            owner = np.repeat(np.arange(len(h)), np.diff(off))
            inner.apply({"w_in": _sum_rows(back[owner] * vals[:, None], feats)})
            old, held = held, info.pop("held")
            if old is not None:
                old.unpersist()
            if inner.at.step % cut_every == 0:
                params = params.checkpoint()
                held.unpersist()
                held = None
            log.append({"iteration": inner.at.step, "refreshed": refreshed, **info})
    df.unpersist()
    return Sharded(conf, inner, params), log
