"""Plan A of training: one step of a sparse network as relations, each step a small operator.

Relations: features (instance_id, idx, val); w_in (unit, idx, w); hidden (instance_id, unit, a);
w_out (neuron_id, unit, w); active (instance_id, neuron_id); labels (instance_id, neuron_id).
A row that is absent is an inactive neuron: it is neither computed nor updated. Meant for checks and small
nets; plans/blocks.py keeps the pairs inside tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def batches(instances: DataFrame, size: int, seed: int, epoch: int = 0, exact: bool = False) -> DataFrame:
    """instances with batch_id, in a random order of the epoch.

    exact: all batches but one have size rows, at the price of one task that numbers all rows (tests). Else a
    batch is a hash bucket, of about size rows, without any sort.
    """
    from bucketnet.functions.seeds import h32

    order = h32(seed, epoch, F.col("instance_id"))
    if exact:
        w = Window.orderBy(order, "instance_id")
        return instances.withColumn("batch_id", F.floor((F.row_number().over(w) - 1) / size).cast("long"))
    count = max(1, -(-instances.count() // size))
    return instances.withColumn("batch_id", (order % count).cast("long"))


def forward_input(features: DataFrame, w_in: DataFrame, bias: DataFrame | None = None) -> DataFrame:
    """instance_id, unit, z: only weights of present features are read; sums combine before the shuffle."""
    z = features.join(w_in, "idx").groupBy("instance_id", "unit").agg(F.sum(F.col("val") * F.col("w")).alias("z"))
    if bias is not None:
        z = z.join(bias.select("unit", "b"), "unit", "left").select("instance_id", "unit", (F.col("z") + F.coalesce("b", F.lit(0.0))).alias("z"))
    return z


def relu(z: DataFrame) -> DataFrame:
    """Units with a positive sum; the others are inactive, so they have no row."""
    return z.where("z > 0").withColumnRenamed("z", "a")


def with_labels(active: DataFrame, labels: DataFrame) -> DataFrame:
    """active and each instance's own labels, which training needs to be there."""
    return active.select("instance_id", "neuron_id").unionByName(labels.select("instance_id", "neuron_id")).distinct()


def forward_active(active: DataFrame, hidden: DataFrame, w_out: DataFrame) -> DataFrame:
    """instance_id, neuron_id, z of active neurons alone (0 where no unit is active)."""
    pairs = active.join(hidden, "instance_id", "left").join(w_out, ["neuron_id", "unit"], "left")
    return pairs.groupBy("instance_id", "neuron_id").agg(F.coalesce(F.sum(F.col("a") * F.col("w")), F.lit(0.0)).alias("z"))


def active_softmax(logits: DataFrame) -> DataFrame:
    """prob over the active neurons of each instance."""
    w = Window.partitionBy("instance_id")
    e = logits.withColumn("e", F.exp(F.col("z") - F.max("z").over(w)))
    return e.select("instance_id", "neuron_id", (F.col("e") / F.sum("e").over(w)).alias("prob"))


def output_delta(probs: DataFrame, labels: DataFrame) -> DataFrame:
    """delta = prob - y, with uniform mass over an instance's labels; labels that are not active have no row."""
    share = labels.withColumn("y", 1.0 / F.count(F.lit(1)).over(Window.partitionBy("instance_id")))
    joined = probs.join(share.select("instance_id", "neuron_id", "y"), ["instance_id", "neuron_id"], "left")
    return joined.select("instance_id", "neuron_id", (F.col("prob") - F.coalesce("y", F.lit(0.0))).alias("delta"))


def cross_entropy(probs: DataFrame, labels: DataFrame) -> DataFrame:
    """instance_id, loss over the labels that are active."""
    share = labels.withColumn("y", 1.0 / F.count(F.lit(1)).over(Window.partitionBy("instance_id")))
    return probs.join(share, ["instance_id", "neuron_id"]).groupBy("instance_id").agg((-F.sum(F.col("y") * F.log("prob"))).alias("loss"))


def backward_hidden(delta: DataFrame, hidden: DataFrame, w_out: DataFrame) -> DataFrame:
    """instance_id, unit, delta: messages go to active units only (relu's slope there is 1)."""
    paths = delta.join(w_out, "neuron_id").join(hidden.select("instance_id", "unit"), ["instance_id", "unit"])
    return paths.groupBy("instance_id", "unit").agg(F.sum(F.col("delta") * F.col("w")).alias("delta"))


def output_gradient(delta: DataFrame, hidden: DataFrame, count: int | Column = 1) -> DataFrame:
    """neuron_id, unit, g: the mean over a batch of count instances, touched weights only."""
    return delta.join(hidden, "instance_id").groupBy("neuron_id", "unit").agg((F.sum(F.col("delta") * F.col("a")) / count).alias("g"))


def input_gradient(delta_hidden: DataFrame, features: DataFrame, count: int | Column = 1) -> DataFrame:
    """unit, idx, g."""
    return delta_hidden.join(features, "instance_id").groupBy("unit", "idx").agg((F.sum(F.col("delta") * F.col("val")) / count).alias("g"))


def sgd(params: DataFrame, grad: DataFrame, keys: list[str], rate: float) -> DataFrame:
    """params with w moved where there is a gradient."""
    joined = params.join(grad, keys, "left")
    return joined.select(*keys, (F.col("w") - rate * F.coalesce("g", F.lit(0.0))).alias("w"))


def adam(params: DataFrame, grad: DataFrame, keys: list[str], step: int, rate: float, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8, lazy: bool = True) -> DataFrame:
    """keys, w, m, v after a step. lazy: rows without a gradient stay as they are; else their moments decay and move them."""
    joined = params.join(grad, keys, "left")
    g = F.coalesce("g", F.lit(0.0))
    m, v = b1 * F.col("m") + (1 - b1) * g, b2 * F.col("v") + (1 - b2) * g * g
    w = F.col("w") - rate * (m / (1 - b1**step)) / (F.sqrt(v / (1 - b2**step)) + eps)
    if lazy:
        touched = F.col("g").isNotNull()
        m, v, w = (F.when(touched, new).otherwise(F.col(old)) for new, old in ((m, "m"), (v, "v"), (w, "w")))
    return joined.select(*keys, w.alias("w"), m.alias("m"), v.alias("v"))


def merge_deltas(deltas: DataFrame, keys: list[str], resolve: str, seed: int = 11) -> DataFrame:
    """keys, delta of several writers (writer, delta): sum, mean, or the one of random_one writer, as where the last of racing writes stays."""
    from bucketnet.functions.seeds import h32

    d = F.col("delta")
    how = {"sum": F.sum(d), "mean": F.avg(d), "random_one": F.max_by(d, F.struct(h32(seed, F.col("writer"), *[F.col(k) for k in keys]), "writer"))}
    return deltas.groupBy(*keys).agg(how[resolve].alias("delta"))


def sampled_neurons(spark_neurons: DataFrame, count: int, seed: int, weight: str | None = None) -> DataFrame:
    """neuron_id, incl: a static sample shared by a batch, by uniform or weighted exponential keys; incl: how often such a neuron is expected in a sample.

    weight: a column of positive weights (label frequencies).
    """
    from bucketnet.functions.seeds import h32

    u = (h32(seed, F.col("neuron_id")) + 1) / float(1 << 32)
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    total = spark_neurons.agg(F.sum(w).alias("tw"))
    keyed = spark_neurons.select("neuron_id", w.alias("w"), (-F.log(u) / w).alias("key")).orderBy("key", "neuron_id").limit(count)
    return keyed.join(F.broadcast(total)).select("neuron_id", F.least(F.lit(1.0), count * F.col("w") / F.col("tw")).alias("incl"))


def correct_logits(logits: DataFrame, sample: DataFrame) -> DataFrame:
    """Logits less the log of the expected count of their neuron, so that a sampled softmax is unbiased in the limit; neurons outside the sample (own labels) stay."""
    s = sample.select(F.col("neuron_id").alias("s_id"), "incl")
    return logits.join(F.broadcast(s), F.col("neuron_id") == F.col("s_id"), "left").select("instance_id", "neuron_id", (F.col("z") - F.coalesce(F.log("incl"), F.lit(0.0))).alias("z"))


def exact_topk(logits: DataFrame, beta: int) -> DataFrame:
    """The beta neurons of largest logit: the ceiling of what sampling can choose."""
    w = Window.partitionBy("instance_id").orderBy(F.desc("z"), "neuron_id")
    return logits.withColumn("__r", F.row_number().over(w)).where(F.col("__r") <= beta).drop("__r")


def sharded_softmax(logits: DataFrame, shards: int) -> DataFrame:
    """Plan C: neurons in shards, of which only (largest, sum of exponentials) per instance travel; equal to active_softmax."""
    part = logits.withColumn("shard", F.pmod(F.col("neuron_id"), F.lit(shards)))
    local = part.groupBy("instance_id", "shard").agg(F.max("z").alias("top"), F.collect_list("z").alias("zs"))
    local = local.select("instance_id", "shard", "top", F.aggregate("zs", F.lit(0.0), lambda a, z: a + F.exp(z - F.col("top"))).alias("s"))
    every = local.groupBy("instance_id").agg(F.max("top").alias("t"), F.collect_list(F.struct("top", "s")).alias("parts"))
    norm = every.select("instance_id", "t", F.aggregate("parts", F.lit(0.0), lambda a, x: a + x["s"] * F.exp(x["top"] - F.col("t"))).alias("n"))
    return logits.join(norm, "instance_id").select("instance_id", "neuron_id", (F.exp(F.col("z") - F.col("t")) / F.col("n")).alias("prob"))


def forward_cogrouped(active: DataFrame, hidden: DataFrame, w_out: DataFrame, shards: int) -> DataFrame:
    """forward_active with each shard's pairs and weights met in one task (a cogrouped Arrow map): pairs are not joined into rows.

    A shard's weights and pairs must fit a task; shards is chosen for that.
    """
    import pyarrow as pa

    h = hidden.groupBy("instance_id").agg(F.map_from_entries(F.collect_list(F.struct("unit", "a"))).alias("h"))
    pairs = active.join(h, "instance_id", "left").withColumn("shard", F.pmod(F.col("neuron_id"), F.lit(shards)))
    weights = w_out.groupBy("neuron_id").agg(F.map_from_entries(F.collect_list(F.struct("unit", "w"))).alias("ws")).withColumn("shard", F.pmod(F.col("neuron_id"), F.lit(shards)))

    def run(key, left: pa.Table, right: pa.Table) -> pa.Table:
        w = {n: dict(m) for n, m in zip(right.column("neuron_id").to_pylist(), right.column("ws").to_pylist(), strict=True)}
        ids, neurons = left.column("instance_id").to_pylist(), left.column("neuron_id").to_pylist()
        z = [sum(a * w.get(n, {}).get(u, 0.0) for u, a in (m or [])) for n, m in zip(neurons, left.column("h").to_pylist(), strict=True)]
        return pa.table({"instance_id": pa.array(ids, pa.int64()), "neuron_id": pa.array(neurons, pa.int32()), "z": pa.array(z, pa.float64())})

    return pairs.groupBy("shard").cogroup(weights.groupBy("shard")).applyInArrow(run, "instance_id long, neuron_id int, z double")
