"""Plan B: data-parallel training. A snapshot goes to the executors, tasks train on their rows, deltas of touched rows come back.

Instances: instance_id, feats array<int>, vals array<float>, labels array<int>. What is shuffled is at most a row
per touched weight row and task; what reaches the driver is bounded by the model, whose size is checked.

One learner needs no merging: train_one runs it as a single task over the rows that its batches draw, and the driver sees weights only
to hand them to an evaluation. train_apart does so for stale learners too: one task emulates them one after the other.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketnet.functions.seeds import h32, h32_of
from bucketnet.operators.index import Refresh
from bucketnet.plans.kernel import HASHED, NetConf, Snapshot, Tables, Trainer, room

SNAPSHOT_LIMIT = 8 << 30


def as_instances(features: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows (instance_id, idx, val) and (instance_id, label) as instances; values are scaled to length 1."""
    f = features.groupBy("instance_id").agg(F.sort_array(F.collect_list(F.struct("idx", "val"))).alias("f"), F.sqrt(F.sum(F.col("val") * F.col("val"))).alias("norm"))
    lab = labels.groupBy("instance_id").agg(F.sort_array(F.collect_set(F.col("label").cast("int"))).alias("labels"))
    rows = f.join(lab, "instance_id")
    return rows.select("instance_id", F.transform("f", lambda x: x["idx"]).alias("feats"), F.transform("f", lambda x: (x["val"] / F.col("norm")).cast("float")).alias("vals"), "labels")


def slots_as_instances(slots: DataFrame, labels: DataFrame) -> DataFrame:
    """as_instances of rows (instance_id, feats: distinct slots), each slot of value 1; rows of one id become one instance."""
    every = F.sort_array(F.array_distinct(F.flatten(F.collect_list("feats"))))
    f = slots.groupBy("instance_id").agg(every.alias("feats"))
    lab = labels.groupBy("instance_id").agg(F.sort_array(F.collect_set(F.col("label").cast("int"))).alias("labels"))
    one = F.transform("feats", lambda i: (F.lit(1.0) / F.sqrt(F.size("feats").cast("double"))).cast("float"))
    return f.join(lab, "instance_id").select("instance_id", "feats", one.alias("vals"), "labels")


def flat(batch: pa.RecordBatch, names: tuple[str, str]) -> tuple[np.ndarray, ...]:
    """feats, vals, offsets of an Arrow batch of instances."""
    col = batch.column(names[0])
    offsets = col.offsets.to_numpy().astype(np.int64)
    out = [col.flatten().to_numpy(zero_copy_only=False).astype(np.int64)]
    if names[1]:
        out.append(batch.column(names[1]).flatten().to_numpy(zero_copy_only=False).astype(np.float32))
    return (*out, offsets - offsets[0])


class Rows:
    """A partition's instances as flat arrays, read batch by batch."""

    def __init__(self, batches: list[pa.RecordBatch]):
        self.n = sum(b.num_rows for b in batches)
        if self.n:
            b = pa.Table.from_batches(batches).combine_chunks().to_batches()[0]
            self.feats, self.vals, self.off = flat(b, ("feats", "vals"))
            self.labels, self.lab_off = flat(b, ("labels", ""))

    def take(self, rows: np.ndarray) -> tuple[np.ndarray, ...]:
        def ragged(off, *flats):
            n = off[rows + 1] - off[rows]
            at = np.repeat(off[rows] - np.cumsum(n) + n, n) + np.arange(n.sum())
            return *[x[at] for x in flats], np.concatenate([[0], np.cumsum(n)])

        feats, vals, off = ragged(self.off, self.feats, self.vals)
        labels, lab_off = ragged(self.lab_off, self.labels)
        return feats, vals, off, labels, lab_off


class Kept:
    """The tables of a whole run and their calendar: refreshed between rounds, at the very iterations that are due."""

    def __init__(self, conf: NetConf, snapshot: Snapshot):
        self.tables = Tables(conf, snapshot.w_out) if conf.strategy in HASHED else None
        self.clock = Refresh(conf.refresh, conf.n0, conf.decay)
        self.touched = np.zeros(conf.labels, dtype=bool)
        self.log: list[dict] = []

    def steps(self, step: int, wanted: int) -> int:
        """How many of the wanted steps come before the next refresh."""
        return wanted if self.tables is None else int(min(wanted, self.clock.next_after(step) - step))

    def after(self, snapshot: Snapshot, touched: np.ndarray) -> None:
        if self.tables is None:
            return
        self.touched[touched] = True
        if self.clock.fires(snapshot.step):
            moved, hashed = self.tables.moved, self.tables.hashed
            self.tables.refresh(snapshot.w_out, np.flatnonzero(self.touched))
            self.log.append({"iteration": snapshot.step, "touched": int(self.touched.sum()), "moved": self.tables.moved - moved, "hash_operations": self.tables.hashed - hashed})
            self.touched[:] = False


@dataclass
class Model:
    conf: NetConf
    snapshot: Snapshot
    kept: Kept | None = None

    def save(self, spark, path: str) -> None:
        """One Parquet row a weight row, with its Adam moments, and the step."""
        for name in ("w_in", "w_out"):
            parts = {"w": getattr(self.snapshot, name), **{x: self.snapshot.moments[f"{name}.{x}"] for x in ("m", "v")}}
            t = pa.table({"row": pa.array(np.arange(len(parts["w"]))), "step": pa.array(np.full(len(parts["w"]), self.snapshot.step)), **{k: pa.array(list(x), pa.list_(pa.float32())) for k, x in parts.items()}})
            spark.createDataFrame(t).write.mode("overwrite").parquet(f"{path}/{name}")

    @classmethod
    def load(cls, spark, path: str, conf: NetConf) -> Model:
        w, moments, step = {}, {}, 0
        for name in ("w_in", "w_out"):
            t = spark.read.parquet(f"{path}/{name}").orderBy("row").toArrow()
            part = {k: np.array(t.column(k).to_pylist(), dtype=np.float32) for k in ("w", "m", "v")}
            w[name], step = part["w"], int(t.column("step")[0].as_py())
            moments |= {f"{name}.{k}": part[k] for k in ("m", "v")}
        return cls(conf, Snapshot(w["w_in"], w["w_out"], moments, step))


def _round(df: DataFrame, conf: NetConf, snapshot: Snapshot, local_steps: int, resolve: str, weights: np.ndarray | None, turn: int, tables: Tables | None = None, alone: bool = False) -> tuple[Snapshot, dict]:
    """Every partition takes local_steps steps from the snapshot, with the tables given; deltas of touched rows are merged."""
    size = snapshot.size + (tables.nbytes if tables is not None else 0)
    if size > SNAPSHOT_LIMIT:
        raise ValueError(f"a snapshot of {size} bytes is too large to broadcast; use plans.shards")
    spark = df.sparkSession
    shared = spark.sparkContext.broadcast((snapshot, weights, tables))
    width = conf.hidden
    cols = [f"d{i}" for i in range(width)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        held = list(batches)
        rows = Rows(held) if held else None
        names = ["layer", "row", "writer", *cols]
        if rows is None or rows.n == 0:
            return
        start, label_weights, given = shared.value
        trainer = Trainer(conf, start.copy(), label_weights, given)
        rng = np.random.default_rng((conf.seed, turn, part))
        loss, touched = 0.0, {"w_in": [], "w_out": []}
        for _ in range(local_steps):
            pick = np.sort(rng.choice(rows.n, size=min(conf.batch, rows.n), replace=False))
            loss += trainer.step(*rows.take(pick)) / local_steps
            for name, r in trainer.rows_touched.items():
                touched[name].append(r)
        for layer, name in enumerate(("w_in", "w_out")):
            r = np.unique(np.concatenate(touched[name])) if touched[name] else np.zeros(0, np.int64)
            for kind, new, old in ((0, getattr(trainer.at, name), getattr(start, name)), (2, trainer.at.moments[f"{name}.m"], start.moments[f"{name}.m"]), (4, trainer.at.moments[f"{name}.v"], start.moments[f"{name}.v"])):
                d = new[r] - old[r]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), layer + kind, dtype=np.int32)), pa.array(r), pa.array(np.full(len(r), part, dtype=np.int32)), *[pa.array(d[:, i].astype(np.float64)) for i in range(width)]], names)
        note = np.zeros(width)
        note[: min(4, width)] = [loss, trainer.active, trainer.instances, 1.0][: min(4, width)]
        yield pa.RecordBatch.from_arrays([pa.array(np.array([9], dtype=np.int32)), pa.array(np.array([0])), pa.array(np.array([part], dtype=np.int32)), *[pa.array([float(x)]) for x in note]], names)

    deltas = df.mapInArrow(run, "layer int, row long, writer int, " + ", ".join(f"{c} double" for c in cols))
    if alone:  # one learner: nothing to merge
        merged = deltas
    elif resolve == "random_one":
        pick = F.max_by(F.struct(*cols), F.struct(h32(conf.seed, turn, F.col("writer"), F.col("row")), "writer")).alias("s")
        sums = [F.sum(c).alias(f"s{i}") for i, c in enumerate(cols)]
        merged = deltas.groupBy("layer", "row").agg(pick, *sums)
        merged = merged.select("layer", "row", *[F.when(F.col("layer") == 9, F.col(f"s{i}")).otherwise(F.col(f"s.{c}")).alias(c) for i, c in enumerate(cols)])
    else:
        # weights by the wanted rule; moments by their mean, which keeps their scale
        merged = deltas.groupBy("layer", "row").agg(*[(F.sum(c) if resolve == "sum" else F.when(F.col("layer") == 9, F.sum(c)).otherwise(F.avg(c))).alias(c) for c in cols], F.count(F.lit(1)).alias("n"))
        if resolve == "sum":
            merged = merged.select("layer", "row", *[F.when(F.col("layer").between(2, 5), F.col(c) / F.col("n")).otherwise(F.col(c)).alias(c) for c in cols])
    t = merged.select("layer", "row", *cols).toArrow()
    new = snapshot.copy()
    layer, row = t.column("layer").to_numpy(), t.column("row").to_numpy()
    note = np.array([t.column(c).to_numpy()[layer == 9].sum() for c in cols] + [0.0] * max(0, 4 - width))
    for i, name in enumerate(("w_in", "w_out")):
        for kind, target in ((0, getattr(new, name)), (2, new.moments[f"{name}.m"]), (4, new.moments[f"{name}.v"])):
            at = layer == i + kind
            for c, col in enumerate(cols):  # a column at a time: no second copy of all deltas
                target[row[at], c] += t.column(col).to_numpy()[at].astype(np.float32)
    for i in ("w_in", "w_out"):
        np.maximum(new.moments[f"{i}.v"], 0, out=new.moments[f"{i}.v"])
    new.step += local_steps
    tasks = max(1.0, note[3])
    shared.destroy()  # with its files; unpersist leaves those on the disk until the run ends
    return new, {"loss": note[0] / tasks, "active_mean": note[1] / max(1.0, note[2]), "touched": np.unique(row[layer == 1])}


def train(df: DataFrame, conf: NetConf, rounds: int, local_steps: int = 1, resolve: str = "mean", start: Snapshot | None = None, test: DataFrame | None = None, eval_every: int = 0, run_id: str = "run") -> tuple[Model, list[dict]]:
    """Rounds of _round over the partitions of df, which are kept (memory and disk); the run log has a row each eval_every rounds.

    local_steps 1 with one partition is plain batch training; more partitions or steps are stale, unsynchronised updates. Tables,
    projections and calendar live as long as the run (Model.kept): a round ends where a refresh is due, and then entries of touched labels move.
    """
    df = df.persist()
    snapshot = start or Snapshot.start(conf)
    kept, alone = Kept(conf, snapshot), df.rdd.getNumPartitions() == 1
    weights = None
    if conf.weighted:
        freq = df.select(F.explode("labels").alias("l")).groupBy("l").count().toArrow()
        weights = np.ones(conf.labels)
        weights[freq.column("l").to_numpy()] += freq.column("count").to_numpy()
    log, began, spent = [], time.time(), 0.0
    part = 0
    for turn in range(rounds):
        left = local_steps
        while left:
            n = kept.steps(snapshot.step, left)
            snapshot, info = _round(df, conf, snapshot, n, resolve, weights, part, kept.tables, alone)
            kept.after(snapshot, info.pop("touched"))
            left, part = left - n, part + 1
        if eval_every and test is not None and (turn + 1) % eval_every == 0:
            t = time.time()
            shared = test.sparkSession.sparkContext.broadcast((snapshot.w_in, snapshot.w_out))
            p = hit_rate(test, conf, shared)
            shared.destroy()
            spent += time.time() - t
            log.append({"run_id": run_id, "iteration": snapshot.step, "wall_ms": int(1000 * (time.time() - began - spent)), "p_at_1": p, "active_frac": info["active_mean"] / conf.labels, **info})
    df.unpersist()
    return Model(conf, snapshot, kept), log


def predict(df: DataFrame, model: Model, k: int, mode: str = "exact", shared: Broadcast | None = None) -> DataFrame:
    """instance_id, rank, label, score. mode: exact (all labels) or sampled (those that the tables give). shared: the model's broadcast, if the caller ends it."""
    shared = df.sparkSession.sparkContext.broadcast(model) if shared is None else shared

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        conf = m.conf if mode == "sampled" else replace(m.conf, strategy="dense")  # all labels: no tables
        trainer = Trainer(conf, m.snapshot, None, m.kept.tables if m.kept else None)
        for b in batches:
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                top, value = trainer.predict(*flat(part, ("feats", "vals")), k, mode == "sampled")
                n, width = top.shape
                keep = top.ravel() >= 0
                ids = np.repeat(part.column("instance_id").to_numpy(zero_copy_only=False), width)[keep]
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.tile(np.arange(1, width + 1, dtype=np.int32), n)[keep]), pa.array(top.ravel()[keep].astype(np.int32)), pa.array(value.ravel()[keep].astype(np.float64))], ["instance_id", "rank", "label", "score"])

    return df.select("instance_id", "feats", "vals").mapInArrow(run, "instance_id long, rank int, label int, score double")


def accuracy(pred: DataFrame, truth: DataFrame) -> float:
    """P@1."""
    t = truth.select(F.col("instance_id").alias("t_id"), "labels")
    hit = pred.where("rank = 1").join(t, F.col("instance_id") == F.col("t_id")).select(F.array_contains("labels", F.col("label")).cast("int").alias("hit"))
    got = hit.agg(F.sum("hit"), F.count(F.lit(1))).first()
    return float(got[0] or 0) / max(1, t.count())


def hit_rate(test: DataFrame, conf: NetConf, shared: Broadcast | Weights) -> float:
    """P@1 over all rows of test; shared: (w_in, w_out). Counted in the tasks, without a row for an instance."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trainer = Trainer(replace(conf, strategy="dense"), Snapshot(*shared.value))
        hits = n = 0
        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                hits += trainer.hits(*flat(part, ("feats", "vals")), *flat(part, ("labels", "")))
                n += part.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([hits]), pa.array([n])], ["hits", "n"])

    rows = test.select("feats", "vals", "labels").coalesce(test.sparkSession.sparkContext.defaultParallelism)  # a task puts the weights together once
    hits, n = rows.mapInArrow(run, "hits long, n long").agg(F.sum("hits"), F.sum("n")).first()
    return (hits or 0) / max(1, n or 0)


def parts_of(conf: NetConf, rounds: int, local_steps: int) -> Iterator[tuple[int, int, int]]:
    """(number, steps, rounds done by its end) of each part of a run: a part ends with its round, or before where a refresh is due."""
    clock, step, part = Refresh(conf.refresh, conf.n0, conf.decay), 0, 0
    for turn in range(rounds):
        left = local_steps
        while left:
            n = left if conf.strategy not in HASHED else int(min(left, clock.next_after(step) - step))
            step, left = step + n, left - n
            clock.fires(step)
            yield part, n, turn + (left == 0)
            part += 1


def batches_of(conf: NetConf, rows: int, rounds: int, local_steps: int, writer: int = 0) -> list[np.ndarray]:
    """The rows (0 .. rows - 1) of each step's batch of a learner, as _round draws them."""
    out = []
    for part, n, _ in parts_of(conf, rounds, local_steps):
        rng = np.random.default_rng((conf.seed, part, writer))
        out += [np.sort(rng.choice(rows, size=min(conf.batch, rows), replace=False)) for _ in range(n)]
    return out


def sizes_of(df: DataFrame) -> np.ndarray:
    """Rows of each partition of a persisted df."""
    got = {r["p"]: r["n"] for r in df.groupBy(F.spark_partition_id().alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}
    return np.array([got.get(i, 0) for i in range(max(got, default=-1) + 1)], dtype=np.int64)


def pick(df: DataFrame, sizes: np.ndarray, wanted: np.ndarray, first: int = 0) -> DataFrame:
    """place, feats, vals, labels of the wanted rows of a persisted df, in one partition; a row's place is first and its number over all partitions."""
    start = np.concatenate([[0], np.cumsum(sizes)])
    part = np.searchsorted(start, wanted, side="right") - 1
    t = pa.table({"place": pa.array(wanted + first), "at": pa.array((part << 33) + wanted - start[part])})
    numbered = df.select("feats", "vals", "labels", F.monotonically_increasing_id().alias("row"))  # partition << 33, and the row's number in it
    found = numbered.join(F.broadcast(df.sparkSession.createDataFrame(t)), F.col("row") == F.col("at")).select("place", "feats", "vals", "labels")
    return found.repartition(1)


CHUNK = 1 << 20
ABREAST = 2 << 30  # bytes of weights and tables of runs that go side by side


@dataclass(frozen=True)
class Run:
    """learners stale learners, whose changes are merged by resolve (as train does)."""

    conf: NetConf
    learners: int = 1
    resolve: str = "mean"

    @property
    def size(self) -> int:
        """Bytes of weights and tables; with several learners also the weights that they start from, and the sums of their changes."""
        tables = 20 * self.conf.tables * self.conf.labels if self.conf.strategy in HASHED else 0
        return Snapshot.bytes_of(self.conf) * (1 if self.learners == 1 else 4) + tables


def train_one(df: DataFrame, confs: dict[str, NetConf], rounds: int, local_steps: int = 1, test: DataFrame | None = None, eval_every: int = 0, abreast: bool = False) -> Iterator[tuple[str, list[dict], dict]]:
    """train_apart of a single learner for each of confs."""
    yield from train_apart(df, {name: Run(conf) for name, conf in confs.items()}, rounds, local_steps, test, eval_every, abreast)


def train_apart(df: DataFrame, runs: dict[str, Run], rounds: int, local_steps: int = 1, test: DataFrame | None = None, eval_every: int = 0, abreast: bool = False) -> Iterator[tuple[str, list[dict], dict]]:
    """(name, run log, what its tables did) of each of runs. abreast: as many side by side as ABREAST allows (wall times then are not those of runs alone).

    A run is what train gives: the same batches of a row order, the same calendar, the same merging of learners, each of which has the rows whose instance_id
    falls to it. It is one task, which is sent the rows of its batches alone (of all rows of df each has its chance), however many there are. Learners take
    their turns there, and wall_ms counts the slowest of them and the merging. df must be persisted: rows are found by their number in it.
    """
    spark = df.sparkSession
    shares = {n: [df.where(F.pmod(F.hash("instance_id"), F.lit(n)) == i) for i in range(n)] if n > 1 else [df] for n in {r.learners for r in runs.values()}}
    sizes = {n: [sizes_of(x) for x in of] for n, of in shares.items()}
    if not any(x.sum() for of in sizes.values() for x in of):
        return
    drawn, chosen = {}, {}
    for n, of in sizes.items():
        first = np.concatenate([[0], np.cumsum([x.sum() for x in of])]).astype(np.int64)
        mine = {name: r.conf for name, r in runs.items() if r.learners == n}
        for name, conf in mine.items():
            drawn[name] = {i: [first[i] + b for b in batches_of(conf, int(x.sum()), rounds, local_steps, i)] for i, x in enumerate(of) if x.sum()}
        rows = [np.unique(np.concatenate([b for name in mine for b in drawn[name][i]])) - first[i] if x.sum() else None for i, x in enumerate(of)]
        parts = [pick(share, x, w, int(a)) for share, x, w, a in zip(shares[n], of, rows, first[:-1], strict=True) if w is not None]
        chosen[n] = parts[0] if len(parts) == 1 else reduce(DataFrame.unionByName, parts).repartition(1)
        if not abreast:  # a kept partition would draw all runs to the executor that has it
            chosen[n] = chosen[n].persist()
    freq = None
    if any(r.conf.weighted for r in runs.values()):
        freq = df.select(F.explode("labels").alias("l")).groupBy("l").count().toArrow()
    side = max(1, min(len(runs), spark.sparkContext.defaultParallelism, ABREAST // max(r.size for r in runs.values()))) if abreast else 1
    names = list(runs)
    for group in (names[i : i + side] for i in range(0, len(names), side)):
        shared, out = [], None
        for name in group:
            r, weights = runs[name], None
            if r.conf.weighted:
                weights = np.ones(r.conf.labels)
                weights[freq.column("l").to_numpy()] += freq.column("count").to_numpy()
            shared.append(spark.sparkContext.broadcast((drawn[name], weights)))
            one = chosen[r.learners].mapInArrow(_learner(r, shared[-1], rounds, local_steps, eval_every if test is not None else 0), "kind string, iteration long, at long, note array<double>, data binary").withColumn("run", F.lit(name))
            out = one if out is None else out.unionByName(one)
        out = out.persist()
        notes = out.where("kind in ('log', 'refresh', 'end')").select("run", "kind", "iteration", "note").orderBy("run", "iteration").collect()
        for name in group:
            yield _outcome(name, runs[name].conf, [r for r in notes if r["run"] == name], out.where(F.col("run") == name), test)
        out.unpersist()
        for x in shared:
            x.destroy()
    for x in chosen.values() if not abreast else ():
        x.unpersist()


def _outcome(name: str, conf: NetConf, notes: list, out: DataFrame, test: DataFrame | None) -> tuple[str, list[dict], dict]:
    """A run's part of what train_apart gives, after its evaluations."""
    log = []
    for r in notes:
        if r["kind"] != "log":
            continue
        iteration, (wall, loss, active, instances) = r["iteration"], r["note"]
        shared = Weights(out.where(F.col("iteration") == iteration), conf)
        p = hit_rate(test, conf, shared)
        shared.destroy()
        mean = active / max(1.0, instances)
        log.append({"run_id": name, "iteration": iteration, "wall_ms": int(wall), "p_at_1": p, "active_frac": mean / conf.labels, "loss": loss, "active_mean": mean})
    end = next(r["note"] for r in notes if r["kind"] == "end")
    return name, log, {"moved": int(end[0]), "hash_operations": int(end[1]), "refreshes": [{"iteration": r["iteration"], **{k: int(x) for k, x in zip(("touched", "moved", "hash_operations"), r["note"], strict=True)}} for r in notes if r["kind"] == "refresh"]}


class Joint:
    """Several learners of a run in one task, one after the other: in each part all begin with the same weights and tables, and their changes of touched rows are merged as _round merges them."""

    PART = 16_384

    def __init__(self, run: Run, weights: np.ndarray | None):
        self.conf, self.resolve, self.weights = run.conf, run.resolve, weights
        self.at = Snapshot.start(run.conf)
        self.kept = Kept(run.conf, self.at)
        self.layers = {name: [getattr(self.at, name), *(self.at.moments[f"{name}.{x}"] for x in ("m", "v"))] for name in ("w_in", "w_out")}
        self.old = {name: [room(x.shape, x.dtype) for x in xs] for name, xs in self.layers.items()}
        self.sums = {name: [room(x.shape, np.float64) for x in xs] for name, xs in self.layers.items()}
        for name, xs in self.layers.items():
            for old, x in zip(self.old[name], xs, strict=True):
                old[:] = x

    def part(self, number: int, batches: dict[int, Iterator[tuple]]) -> tuple[float, float, int, int]:
        """(seconds, loss, active, instances) of one part: batches of each learner."""
        begun, took, loss, active, instances = self.at.step, [], 0.0, 0, 0
        writers = {name: np.zeros(len(xs[0]), np.int32) for name, xs in self.layers.items()}
        best = {name: np.full(len(xs[0]), -1, np.int64) for name, xs in self.layers.items()}
        for writer, of in batches.items():
            self.at.step, t = begun, time.perf_counter()
            trainer, touched, losses = Trainer(self.conf, self.at, self.weights, self.kept.tables), {name: np.zeros(len(n), bool) for name, n in writers.items()}, []
            for batch in of:
                losses.append(trainer.step(*batch))
                for name, rows in trainer.rows_touched.items():
                    touched[name][rows] = True
            took.append(time.perf_counter() - t)
            loss, active, instances, end = loss + sum(losses) / len(losses), active + trainer.active, instances + trainer.instances, self.at.step
            for name in self.layers:
                self._take(name, np.flatnonzero(touched[name]), writers[name], best[name], number, writer)
        t = time.perf_counter()
        for name in self.layers:
            self._merge(name, writers[name])
        self.at.step = end
        self.kept.after(self.at, np.flatnonzero(writers["w_out"]))
        return max(took) + time.perf_counter() - t, loss / len(took), active, instances

    def _take(self, name: str, touched: np.ndarray, writers: np.ndarray, best: np.ndarray, number: int, writer: int) -> None:
        """Adds a learner's changes to the sums (random_one: puts them there, where it is the row's chosen one so far) and undoes them."""
        writers[touched] += 1
        for i in range(0, len(touched), self.PART):
            rows = touched[i : i + self.PART]
            won = slice(None)
            if self.resolve == "random_one":
                drawn = np.array([h32_of(self.conf.seed, number, writer, r) for r in rows.tolist()])
                won = drawn >= best[rows]  # of equal ones the last learner
                best[rows[won]] = drawn[won]
            for new, old, sums in zip(self.layers[name], self.old[name], self.sums[name], strict=True):
                before = old[rows]
                change = (new[rows] - before).astype(np.float64)
                if self.resolve == "random_one":
                    sums[rows[won]] = change[won]
                else:
                    sums[rows] += change
                new[rows] = before

    def _merge(self, name: str, writers: np.ndarray) -> None:
        touched = np.flatnonzero(writers)
        for i in range(0, len(touched), self.PART):
            rows = touched[i : i + self.PART]
            for kind, (new, old, sums) in enumerate(zip(self.layers[name], self.old[name], self.sums[name], strict=True)):
                change = sums[rows]
                if self.resolve == "mean" or (self.resolve == "sum" and kind):  # moments by their mean, which keeps their scale
                    change /= writers[rows][:, None]
                value = new[rows] + change.astype(np.float32)
                new[rows] = old[rows] = value if kind < 2 else np.maximum(value, 0)
                sums[rows] = 0


def _learner(run_of: Run, given: Broadcast, rounds: int, local_steps: int, eval_every: int):
    """The task of a run: notes, and the weights in chunks wherever an evaluation is due."""
    conf = run_of.conf

    def row(kind: str, iteration: int, at: int, note: list[float], data: bytes | None = None) -> pa.RecordBatch:
        cols = [pa.array([kind]), pa.array([iteration]), pa.array([at]), pa.array([note], pa.list_(pa.float64())), pa.array([data], pa.binary())]
        return pa.RecordBatch.from_arrays(cols, ["kind", "iteration", "at", "note", "data"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows, place = Rows(held), np.concatenate([b.column("place").to_numpy() for b in held])
        del held
        order = np.argsort(place)
        place = place[order]
        steps, weights = given.value
        size = Snapshot.bytes_of(conf)
        if size > SNAPSHOT_LIMIT:
            raise ValueError(f"a snapshot of {size} bytes is too large for a task; use plans.shards")
        joint = Joint(run_of, weights) if run_of.learners > 1 else None
        trainer = Trainer(conf, Snapshot.start(conf), weights) if joint is None else None
        at, tables = (trainer.at, trainer.tables) if joint is None else (joint.at, joint.kept.tables)
        step, wall = 0, 0.0

        def taken_by(of: list[np.ndarray]) -> Iterator[tuple]:
            return (rows.take(order[np.searchsorted(place, at)]) for at in of)

        for number, n, done in parts_of(conf, rounds, local_steps):
            taken = {writer: taken_by(of[step : step + n]) for writer, of in steps.items()}
            if joint is None:
                t = time.perf_counter()
                trainer.active, trainer.instances, loss = 0, 0, 0.0
                for batch in taken[0]:
                    loss += trainer.step(*batch) / n
                took, active, instances = time.perf_counter() - t, trainer.active, trainer.instances
            else:
                took, loss, active, instances = joint.part(number, taken)
            ended, step = done * local_steps == step + n, step + n
            wall += took
            if eval_every and ended and done % eval_every == 0:
                yield row("log", step, 0, [1000 * wall, loss, active, instances])
                for name in ("w_in", "w_out"):
                    w = getattr(at, name)
                    for a in range(0, len(w), most := max(1, CHUNK // (4 * conf.hidden))):
                        yield row(name, step, a, [], w[a : a + most].tobytes())
        for r in trainer.refreshes if joint is None else joint.kept.log:
            yield row("refresh", r["iteration"], 0, [r["touched"], r["moved"], r["hash_operations"]])
        yield row("end", step, 0, [tables.moved, tables.hashed] if tables else [0, 0])

    return run


class Weights:
    """(w_in, w_out) of one evaluation as a broadcast a chunk: the driver holds a few chunks at a time, a task puts them together."""

    def __init__(self, out: DataFrame, conf: NetConf):
        self.shape, self.parts = {"w_in": (conf.dims, conf.hidden), "w_out": (conf.labels, conf.hidden)}, []
        some = 8 * max(1, CHUNK // (4 * conf.hidden))
        for kind, (n, _) in self.shape.items():
            for a in range(0, n, some):  # a job for a few chunks: what it reads of out are those alone
                for r in out.where((F.col("kind") == kind) & (F.col("at") >= a) & (F.col("at") < a + some)).select("at", "data").collect():
                    self.parts.append((kind, r["at"], out.sparkSession.sparkContext.broadcast(bytes(r["data"]))))

    @property
    def value(self) -> tuple[np.ndarray, np.ndarray]:
        w = {kind: room(shape, np.float32) for kind, shape in self.shape.items()}
        for kind, at, part in self.parts:
            x = np.frombuffer(part.value, np.float32).reshape(-1, w[kind].shape[1])
            w[kind][at : at + len(x)] = x
            if part._path is not None:
                part.__dict__.pop("_value", None)  # a worker keeps no chunk: it has its file
        return w["w_in"], w["w_out"]

    def destroy(self) -> None:
        for _, _, part in self.parts:
            part.destroy()


def sweep(df: DataFrame, conf: NetConf, rates: list[float], rounds: int, test: DataFrame) -> list[tuple[float, float]]:
    """(rate, P@1) of independent runs."""
    from dataclasses import replace

    out = []
    for r in rates:
        model, _ = train(df, replace(conf, rate=r), rounds)
        out.append((r, accuracy(predict(test, model, 1), test)))
    return out

