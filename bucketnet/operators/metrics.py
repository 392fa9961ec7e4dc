"""Accuracy, cost and agreement measures over relations of predictions, active sets, gradients and run logs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def _hits(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """pred (instance_id, rank, label) with hit 1 or 0; truth (instance_id, label)."""
    t = truth.select(F.col("instance_id").alias("t_i"), F.col("label").alias("t_l"), F.lit(1).alias("h")).distinct()
    return pred.join(t, (F.col("instance_id") == F.col("t_i")) & (F.col("label") == F.col("t_l")), "left").select("instance_id", "rank", F.coalesce("h", F.lit(0)).alias("hit"))


def precision_at_k(pred: DataFrame, truth: DataFrame, ks: list[int]) -> DataFrame:
    """k, value: mean over instances with a prediction of the share of true labels among the first k."""
    hits = _hits(pred, truth)
    by = hits.groupBy("instance_id").agg(*[(F.sum(F.when(F.col("rank") <= k, F.col("hit")).otherwise(0)) / k).alias(f"p{k}") for k in ks])
    return by.agg(*[F.avg(f"p{k}").alias(f"p{k}") for k in ks]).select(F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"p{k}").alias("value")) for k in ks])).alias("x")).select("x.*")


def recall_at_k(pred: DataFrame, truth: DataFrame, ks: list[int]) -> DataFrame:
    hits = _hits(pred, truth)
    size = truth.distinct().groupBy("instance_id").agg(F.count(F.lit(1)).alias("n"))
    by = hits.groupBy("instance_id").agg(*[F.sum(F.when(F.col("rank") <= k, F.col("hit")).otherwise(0)).alias(f"h{k}") for k in ks]).join(size, "instance_id")
    return by.agg(*[F.avg(F.col(f"h{k}") / F.col("n")).alias(f"h{k}") for k in ks]).select(F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"h{k}").alias("value")) for k in ks])).alias("x")).select("x.*")


def ndcg_at_k(pred: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    hits = _hits(pred, truth).where(F.col("rank") <= k)
    size = truth.distinct().groupBy("instance_id").agg(F.count(F.lit(1)).cast("int").alias("n"))
    gain = hits.groupBy("instance_id").agg(F.sum(F.col("hit") / F.log2(F.col("rank") + 1.0)).alias("g")).join(size, "instance_id")
    ideal = F.aggregate(F.sequence(F.lit(1), F.least(F.lit(k), F.col("n"))), F.lit(0.0), lambda a, i: a + 1.0 / F.log2(i + 1.0))
    return gain.agg(F.avg(F.col("g") / ideal).alias("value")).select(F.lit(k).alias("k"), "value")


def log_loss(scored: DataFrame) -> DataFrame:
    """value over rows (y 0 or 1, p)."""
    p = F.least(F.lit(1 - 1e-12), F.greatest(F.lit(1e-12), F.col("p")))
    return scored.agg((-F.avg(F.when(F.col("y") == 1, F.log(p)).otherwise(F.log(1 - p)))).alias("value"))


def auc(scored: DataFrame, bins: int = 4096) -> DataFrame:
    """Chance that a positive row outranks a negative one, ties as a half; rows are first counted by score (p in 0 .. 1).

    Negatives below a score are those of lower bins (a window over the bins' sums) and lower ones in its own bin.
    """
    one = lambda cond: F.sum(F.when(cond, 1).otherwise(0))
    by = scored.groupBy("p").agg(one(F.col("y") == 1).alias("pos"), one(F.col("y") != 1).alias("neg"))
    by = by.withColumn("bin", F.floor(F.least(F.lit(1.0), F.greatest(F.lit(0.0), F.col("p"))) * bins).cast("int"))
    earlier = Window.unboundedPreceding, -1
    sums = by.groupBy("bin").agg(F.sum("neg").alias("bin_neg"))
    sums = sums.select(F.col("bin").alias("b"), F.coalesce(F.sum("bin_neg").over(Window.orderBy("bin").rowsBetween(*earlier)), F.lit(0)).alias("lower"))
    own = F.coalesce(F.sum("neg").over(Window.partitionBy("bin").orderBy("p").rowsBetween(*earlier)), F.lit(0))
    w = by.withColumn("own", own).join(F.broadcast(sums), F.col("bin") == F.col("b"))  # bins + 1 rows at most
    return w.agg(F.try_divide(F.sum(F.col("pos") * (F.col("lower") + F.col("own") + F.col("neg") / 2.0)), F.sum("pos") * F.sum("neg")).alias("value"))


def time_to_accuracy(runlog: DataFrame, targets: list[float]) -> DataFrame:
    """run_id, target, wall_ms, iteration: when a run first has at least the target (null: never)."""
    t = runlog.withColumn("target", F.explode(F.array(*[F.lit(float(x)) for x in targets])))
    ok = F.col("p_at_1") >= F.col("target")
    return t.groupBy("run_id", "target").agg(F.min(F.when(ok, F.col("wall_ms"))).alias("wall_ms"), F.min(F.when(ok, F.col("iteration"))).alias("iteration"))


def speedup(times: DataFrame, baseline: str) -> DataFrame:
    """run_id, target, ratio of the baseline's time to each run's."""
    b = times.where(F.col("run_id") == baseline).select(F.col("target").alias("b_t"), F.col("wall_ms").alias("b_w"))
    return times.join(b, F.col("target") == F.col("b_t")).select("run_id", "target", F.try_divide(F.col("b_w"), F.col("wall_ms")).alias("ratio"))


def early_stop(runlog: DataFrame, patience: int, min_delta: float) -> DataFrame:
    """run_id, stop_at: the first iteration after patience log rows without a gain of min_delta over the best before them."""
    w = Window.partitionBy("run_id").orderBy("iteration")
    best = runlog.withColumn("best", F.max("p_at_1").over(w)).withColumn("was", F.lag("best", patience).over(w))
    return best.where(F.col("was").isNotNull() & (F.col("best") < F.col("was") + min_delta)).groupBy("run_id").agg(F.min("iteration").alias("stop_at"))


def active_stats(active: DataFrame, neurons: int) -> DataFrame:
    """Mean, largest and share of active neurons per instance."""
    n = active.groupBy("instance_id").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.count(F.lit(1)).alias("instances"), F.avg("n").alias("active_mean"), F.max("n").alias("active_max"), (F.avg("n") / neurons).alias("active_frac"))


def update_share(touched: DataFrame, weights: int, active_share: DataFrame) -> DataFrame:
    """measured: touched weights over all; expected: the square of the active share (one row, active_frac)."""
    t = touched.agg((F.count(F.lit(1)) / weights).alias("measured"))
    return t.join(F.broadcast(active_share)).select("measured", (F.col("active_frac") * F.col("active_frac")).alias("expected"))


def conflict_rate(contributions: DataFrame, keys: list[str]) -> DataFrame:
    """Share of touched weights to which at least two instances contribute."""
    n = contributions.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    return n.agg(F.count(F.lit(1)).alias("touched"), F.sum(F.when(F.col("n") > 1, 1).otherwise(0)).alias("shared")).select("touched", "shared", F.try_divide("shared", "touched").alias("rate"))


def cap_loss(bucket_sizes: DataFrame, cap: int) -> DataFrame:
    """ids, lost: what a bound of cap drops; bucket_sizes has n."""
    return bucket_sizes.agg(F.sum("n").alias("ids"), F.sum(F.greatest(F.col("n") - cap, F.lit(0))).alias("lost"))


def inclusion_frequency(samples: DataFrame, runs: int) -> DataFrame:
    """query_id, id, freq over runs of samples (run, query_id, id)."""
    return samples.groupBy("query_id", "id").agg((F.count(F.lit(1)) / runs).alias("freq"))


def sampling_quality(chosen: DataFrame, best: DataFrame, scored: DataFrame, beta: int) -> DataFrame:
    """query_id, recall of the beta best (best: query_id, id) and mean score of the chosen (scored: query_id, id, score)."""
    b = best.select(F.col("query_id").alias("b_q"), F.col("id").alias("b_i"))
    s = scored.select(F.col("query_id").alias("s_q"), F.col("id").alias("s_i"), "score")
    rows = chosen.join(b, (F.col("query_id") == F.col("b_q")) & (F.col("id") == F.col("b_i")), "left").join(s, (F.col("query_id") == F.col("s_q")) & (F.col("id") == F.col("s_i")))
    return rows.groupBy("query_id").agg((F.count("b_i") / beta).alias("recall"), F.avg("score").alias("mean_score"))


def sensitivity(rates: DataFrame, s0: float, c: float) -> DataFrame:
    """p1: rate of equal codes (same, 0 or 1) at a similarity (sim) of s0 or more; p2: at c * s0 or less. A family suits the data if p1 > p2."""
    return rates.agg(F.avg(F.when(F.col("sim") >= s0, F.col("same"))).alias("p1"), F.avg(F.when(F.col("sim") <= c * s0, F.col("same"))).alias("p2"))


def label_hit_rate(active: DataFrame, labels: DataFrame) -> DataFrame:
    """Share of instances whose own label is among their active neurons."""
    a = active.select(F.col("instance_id").alias("a_i"), F.col("neuron_id").alias("a_n"), F.lit(1).alias("h")).distinct()
    return labels.join(a, (F.col("instance_id") == F.col("a_i")) & (F.col("neuron_id") == F.col("a_n")), "left").agg(F.avg(F.coalesce("h", F.lit(0))).alias("value"))
