"""Steps of training, baselines and measures on a small net over all documents.

256 hashed word features, 8 hidden units, 64 classes (a hash of the document's id). Weights are whole numbers from
md5 and inputs are 1, so hidden sums and the codes of hidden vectors are exact in any engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketnet import workloads
from bucketnet.functions.seeds import h32, h32_sql
from bucketnet.functions.vector import r6, r6_sql
from bucketnet.operators import hashing, index, metrics, network, sampling
from bucketnet.queries.retrieval import codes_sql, fns_sql
from bucketnet.sources.tables import load

QUERIES, ORACLES = {}, {}
DIMS, UNITS, CLASSES, K, L, SEED = 256, 8, 64, 3, 4, 11
RATE = 0.05
FAM = hashing.SimHash(K, L, UNITS, SEED)


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f
    return keep


NET = f"""WITH wd AS (SELECT DISTINCT doc_id AS instance_id, unnest(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+')) AS word FROM documents),
feats AS MATERIALIZED (SELECT DISTINCT instance_id, CAST({h32_sql('word')} % {DIMS} AS INTEGER) AS idx FROM wd WHERE word <> ''),
w_in AS (SELECT CAST(u.range AS INTEGER) AS unit, CAST(i.range AS INTEGER) AS idx, CAST({h32_sql("'in'", 'u.range', 'i.range')} % 2001 - 1000 AS DOUBLE) AS w FROM range({UNITS}) u, range({DIMS}) i),
w_out AS (SELECT CAST(n.range AS INTEGER) AS neuron_id, CAST(u.range AS INTEGER) AS unit, CAST({h32_sql("'out'", 'n.range', 'u.range')} % 2001 - 1000 AS DOUBLE) / 1000 AS w FROM range({CLASSES}) n, range({UNITS}) u),
hid AS MATERIALIZED (SELECT instance_id, unit, sum(w) / 10000 AS a FROM feats JOIN w_in USING (idx) GROUP BY 1, 2 HAVING sum(w) > 0),
lab AS (SELECT doc_id AS instance_id, CAST({h32_sql("'label'", 'doc_id')} % {CLASSES} AS INTEGER) AS neuron_id FROM documents),
{fns_sql(functions=K * L, dim=UNITS, seed=SEED)},
ne AS (SELECT neuron_id AS id, unit AS idx, CAST(floor(w * 1048576) AS BIGINT) AS q FROM w_out), {codes_sql('nc', 'ne', k=K)},
he AS (SELECT instance_id AS id, unit AS idx, CAST(floor(a * 1048576) AS BIGINT) AS q FROM hid), {codes_sql('hc', 'he', k=K)},
act AS MATERIALIZED (SELECT DISTINCT hc.id AS instance_id, nc.id AS neuron_id FROM hc JOIN nc USING (table_id, code) UNION SELECT instance_id, neuron_id FROM lab),
z AS MATERIALIZED (SELECT act.instance_id, act.neuron_id, coalesce(sum(a * w), 0.0) AS z FROM act LEFT JOIN hid USING (instance_id) LEFT JOIN w_out USING (neuron_id, unit) GROUP BY 1, 2)"""


def softmax_sql(name: str, z: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT instance_id, neuron_id, e / sum(e) OVER (PARTITION BY instance_id) AS prob FROM (SELECT *, exp(z - max(z) OVER (PARTITION BY instance_id)) AS e FROM {z}))"


STEP = f"""{NET}, {softmax_sql('pr', 'z')},
dl AS MATERIALIZED (SELECT instance_id, neuron_id, prob - CASE WHEN lab.instance_id IS NULL THEN 0.0 ELSE 1.0 END AS delta FROM pr LEFT JOIN lab USING (instance_id, neuron_id)),
dh AS MATERIALIZED (SELECT instance_id, unit, sum(delta * w) AS delta FROM dl JOIN w_out USING (neuron_id) JOIN hid USING (instance_id, unit) GROUP BY 1, 2),
n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM documents),
go AS MATERIALIZED (SELECT neuron_id, unit, sum(delta * a) / any_value(n) AS g FROM dl JOIN hid USING (instance_id), n GROUP BY 1, 2),
gi AS MATERIALIZED (SELECT unit, idx, sum(delta) / any_value(n) AS g FROM dh JOIN feats USING (instance_id), n GROUP BY 1, 2)"""


class Net:
    """The relations of the small net."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        docs = load(spark, sf_dir, "documents")
        self.count = docs.count()
        self.features = workloads.hashed(workloads.words(docs, "doc_id").select("instance_id", "word").distinct(), DIMS)
        grid = lambda n, m, a, b: spark.range(n * m).select((F.col("id") / m).cast("int").alias(a), (F.col("id") % m).cast("int").alias(b))
        self.w_in = grid(UNITS, DIMS, "unit", "idx").withColumn("w", (h32("in", F.col("unit"), F.col("idx")) % 2001 - 1000).cast("double"))
        self.w_out = grid(CLASSES, UNITS, "neuron_id", "unit").withColumn("w", (h32("out", F.col("neuron_id"), F.col("unit")) % 2001 - 1000).cast("double") / 1000)
        self.labels = docs.select(F.col("doc_id").alias("instance_id"), (h32("label", F.col("doc_id")) % CLASSES).cast("int").alias("neuron_id"))
        self.hidden = network.relu(network.forward_input(self.features, F.broadcast(self.w_in))).withColumn("a", F.col("a") / 10000)

    def active(self, forced: bool = True) -> DataFrame:
        neurons = FAM.codes_of(FAM.project_sparse(self.w_out.select(F.col("neuron_id").alias("id"), F.col("unit").alias("idx"), F.col("w").alias("val"))))
        inputs = FAM.codes_of(FAM.project_sparse(self.hidden.select(F.col("instance_id").alias("id"), F.col("unit").alias("idx"), F.col("a").alias("val"))))
        met = sampling.sample_union(sampling.probe(inputs, index.build_index(neurons)))
        found = met.select(F.col("query_id").alias("instance_id"), F.col("id").alias("neuron_id"))
        return network.with_labels(found, self.labels) if forced else found

    def logits(self, active: DataFrame | None = None) -> DataFrame:
        return network.forward_active(self.active() if active is None else active, self.hidden, F.broadcast(self.w_out))

    def delta(self) -> DataFrame:
        return network.output_delta(network.active_softmax(self.logits()), self.labels)

    def all_neurons(self) -> DataFrame:
        every = self.w_out.select("neuron_id").distinct()
        return self.labels.select("instance_id").join(F.broadcast(every))  # dense training looks at all classes

    def grad_out(self) -> DataFrame:
        return network.output_gradient(self.delta(), self.hidden, self.count)

    def grad_in(self) -> DataFrame:
        return network.input_gradient(network.backward_hidden(self.delta(), self.hidden, F.broadcast(self.w_out)), self.features, self.count)


@query(f"{NET} SELECT instance_id, unit, {r6_sql('a')} AS a FROM hid")
def q_forward_hidden(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).hidden.select("instance_id", "unit", r6(F.col("a")).alias("a"))


# sums of products with 7 decimals: as whole numbers, since rounding them to fewer would meet ties
@query(f"{NET} SELECT instance_id, neuron_id, CAST(round(z * 1e7) AS BIGINT) AS z7 FROM z")
def q_forward_active(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).logits().select("instance_id", "neuron_id", F.round(F.col("z") * 1e7).cast("long").alias("z7"))


@query(f"{NET} SELECT instance_id, neuron_id, CAST(round(z * 1e7) AS BIGINT) AS z7 FROM z")
def q_forward_cogrouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return network.forward_cogrouped(n.active(), n.hidden, n.w_out, 4).select("instance_id", "neuron_id", F.round(F.col("z") * 1e7).cast("long").alias("z7"))


@query(f"{NET}, a AS (SELECT DISTINCT hc.id AS instance_id, nc.id AS neuron_id FROM hc JOIN nc USING (table_id, code)) SELECT {r6_sql('avg(CASE WHEN a.instance_id IS NULL THEN 0.0 ELSE 1.0 END)')} AS value FROM lab LEFT JOIN a USING (instance_id, neuron_id)")
def q_label_hit_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often tables of untrained weights give the own label: near chance."""
    n = Net(spark, sf_dir)
    return metrics.label_hit_rate(n.active(forced=False), n.labels).select(r6(F.col("value")).alias("value"))


@query(f"{NET} SELECT instance_id, count(DISTINCT neuron_id) AS active FROM act GROUP BY 1")
def q_active_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).active().groupBy("instance_id").agg(F.count_distinct("neuron_id").alias("active"))


@query(f"{NET} SELECT count(DISTINCT idx) AS used, count(*) AS nonzeros FROM feats")
def q_feature_dim(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).features.agg(F.count_distinct("idx").alias("used"), F.count(F.lit(1)).alias("nonzeros"))


@query(f"{NET}, {softmax_sql('pr', 'z')} SELECT instance_id, neuron_id, {r6_sql('prob')} AS prob FROM pr")
def q_active_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.active_softmax(Net(spark, sf_dir).logits()).select("instance_id", "neuron_id", r6(F.col("prob")).alias("prob"))


@query(f"{NET}, {softmax_sql('pr', 'z')} SELECT instance_id, {r6_sql('-ln(prob)')} AS loss FROM pr JOIN lab USING (instance_id, neuron_id)")
def q_cross_entropy(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return network.cross_entropy(network.active_softmax(n.logits()), n.labels).select("instance_id", r6(F.col("loss")).alias("loss"))


@query(f"{STEP} SELECT instance_id, neuron_id, {r6_sql('delta')} AS delta FROM dl")
def q_output_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).delta().select("instance_id", "neuron_id", r6(F.col("delta")).alias("delta"))


@query(f"{STEP} SELECT instance_id, unit, {r6_sql('delta')} AS delta FROM dh")
def q_backward_hidden(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return network.backward_hidden(n.delta(), n.hidden, F.broadcast(n.w_out)).select("instance_id", "unit", r6(F.col("delta")).alias("delta"))


@query(f"{STEP} SELECT 'out' AS layer, neuron_id AS row_id, unit AS col_id, {r6_sql('g')} AS g FROM go UNION ALL SELECT 'in', unit, idx, {r6_sql('g')} FROM gi")
def q_gradients(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    out = n.grad_out().select(F.lit("out").alias("layer"), F.col("neuron_id").alias("row_id"), F.col("unit").alias("col_id"), r6(F.col("g")).alias("g"))
    return out.unionByName(n.grad_in().select(F.lit("in").alias("layer"), F.col("unit").alias("row_id"), F.col("idx").alias("col_id"), r6(F.col("g")).alias("g")))


# every third class gets no gradient, so that lazy and dense differ
_PART = "go AS MATERIALIZED (SELECT * FROM go0 WHERE neuron_id % 3 <> 0)"
ADAM = STEP.replace("go AS MATERIALIZED", "go0 AS MATERIALIZED") + f", {_PART}, pm AS (SELECT neuron_id, unit, w, w / 10 AS m, w * w / 10 AS v FROM w_out)"
_NEW = "(0.9 * m + 0.1 * {g}) AS m1, (0.999 * v + 0.001 * {g} * {g}) AS v1"


def _adam(spark: SparkSession, sf_dir: str, lazy: bool) -> DataFrame:
    n = Net(spark, sf_dir)
    p = n.w_out.withColumns({"m": F.col("w") / 10, "v": F.col("w") * F.col("w") / 10})
    out = network.adam(p, n.grad_out().where("neuron_id % 3 != 0"), ["neuron_id", "unit"], 5, RATE, lazy=lazy)
    return out.select("neuron_id", "unit", *[r6(F.col(c)).alias(c) for c in ("w", "m", "v")])


def _adam_sql(lazy: bool) -> str:
    g = "coalesce(g, 0.0)"
    m, v = f"0.9 * m + 0.1 * {g}", f"0.999 * v + 0.001 * {g} * {g}"
    w = f"w - {RATE} * (({m}) / (1 - pow(0.9, 5))) / (sqrt(({v}) / (1 - pow(0.999, 5))) + 1e-8)"
    if lazy:
        w, m, v = (f"CASE WHEN g IS NULL THEN {old} ELSE {new} END" for old, new in (("w", w), ("m", m), ("v", v)))
    return f"{ADAM} SELECT neuron_id, unit, {r6_sql(f'({w})')} AS w, {r6_sql(f'({m})')} AS m, {r6_sql(f'({v})')} AS v FROM pm LEFT JOIN go USING (neuron_id, unit)"


@query(_adam_sql(True))
def q_adam_lazy_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _adam(spark, sf_dir, True)


@query(_adam_sql(False))
def q_adam_dense_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _adam(spark, sf_dir, False)


@query(f"{STEP} SELECT neuron_id, unit, {r6_sql(f'(w - {RATE} * coalesce(g, 0.0))')} AS w FROM w_out LEFT JOIN go USING (neuron_id, unit)")
def q_sgd_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return network.sgd(n.w_out, n.grad_out(), ["neuron_id", "unit"], RATE).select("neuron_id", "unit", r6(F.col("w")).alias("w"))


@query(f"""{STEP}, w1 AS MATERIALIZED (SELECT neuron_id, unit, w - {RATE} * coalesce(g, 0.0) AS w FROM w_out LEFT JOIN go USING (neuron_id, unit)),
z1 AS (SELECT act.instance_id, act.neuron_id, coalesce(sum(a * w), 0.0) AS z FROM act LEFT JOIN hid USING (instance_id) LEFT JOIN w1 USING (neuron_id, unit) GROUP BY 1, 2), {softmax_sql('pr1', 'z1')},
d1 AS (SELECT instance_id, neuron_id, prob - CASE WHEN lab.instance_id IS NULL THEN 0.0 ELSE 1.0 END AS delta FROM pr1 LEFT JOIN lab USING (instance_id, neuron_id)),
g1 AS (SELECT neuron_id, unit, sum(delta * a) / any_value(n) AS g FROM d1 JOIN hid USING (instance_id), n GROUP BY 1, 2)
SELECT neuron_id, unit, {r6_sql(f'(w - {RATE} * coalesce(g, 0.0))')} AS w FROM w1 LEFT JOIN g1 USING (neuron_id, unit)""")
def q_train_two_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    active = n.active()
    w1 = network.sgd(n.w_out, n.grad_out(), ["neuron_id", "unit"], RATE)
    d1 = network.output_delta(network.active_softmax(network.forward_active(active, n.hidden, w1)), n.labels)
    return network.sgd(w1, network.output_gradient(d1, n.hidden, n.count), ["neuron_id", "unit"], RATE).select("neuron_id", "unit", r6(F.col("w")).alias("w"))


# deltas of four writers: each takes the documents of one residue
WRITERS = f"""{STEP}, wr AS (SELECT instance_id % 4 AS writer, neuron_id, unit, sum(delta * a) AS delta FROM dl JOIN hid USING (instance_id) GROUP BY 1, 2, 3)"""


def _writers(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return n.delta().join(n.hidden, "instance_id").groupBy((F.col("instance_id") % 4).alias("writer"), "neuron_id", "unit").agg(F.sum(F.col("delta") * F.col("a")).alias("delta"))


@query(f"{WRITERS} SELECT neuron_id, unit, {r6_sql('sum(delta)')} AS delta FROM wr GROUP BY 1, 2")
def q_async_merge_sum(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.merge_deltas(_writers(spark, sf_dir), ["neuron_id", "unit"], "sum").select("neuron_id", "unit", r6(F.col("delta")).alias("delta"))


@query(f"{WRITERS} SELECT neuron_id, unit, {r6_sql('avg(delta)')} AS delta FROM wr GROUP BY 1, 2")
def q_async_merge_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.merge_deltas(_writers(spark, sf_dir), ["neuron_id", "unit"], "mean").select("neuron_id", "unit", r6(F.col("delta")).alias("delta"))


@query(f"""{WRITERS}, o AS (SELECT *, row_number() OVER (PARTITION BY neuron_id, unit ORDER BY {h32_sql(str(SEED), 'writer', 'neuron_id', 'unit')} DESC, writer DESC) AS r FROM wr)
SELECT neuron_id, unit, {r6_sql('delta')} AS delta FROM o WHERE r = 1""")
def q_async_merge_random_one(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.merge_deltas(_writers(spark, sf_dir), ["neuron_id", "unit"], "random_one", SEED).select("neuron_id", "unit", r6(F.col("delta")).alias("delta"))


# ---- baselines ----
DENSE = f"""{NET}, every AS (SELECT instance_id, n.range AS neuron_id FROM lab, range({CLASSES}) n),
zd AS MATERIALIZED (SELECT every.instance_id, CAST(every.neuron_id AS INTEGER) AS neuron_id, coalesce(sum(a * w), 0.0) AS z FROM every LEFT JOIN hid USING (instance_id) LEFT JOIN w_out USING (neuron_id, unit) GROUP BY 1, 2)"""


def _dense(n: Net) -> DataFrame:
    return n.logits(n.all_neurons())


@query(f"{DENSE}, {softmax_sql('pr', 'zd')} SELECT instance_id, neuron_id, {r6_sql('prob')} AS prob FROM pr")
def q_full_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.active_softmax(_dense(Net(spark, sf_dir))).select("instance_id", "neuron_id", r6(F.col("prob")).alias("prob"))


@query(f"{DENSE}, {softmax_sql('pr', 'zd')} SELECT instance_id, neuron_id, {r6_sql('prob')} AS prob FROM pr")
def q_sharded_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return network.sharded_softmax(_dense(Net(spark, sf_dir)), 4).select("instance_id", "neuron_id", r6(F.col("prob")).alias("prob"))


SHARE = 13  # a fifth of the classes


def _sampled_sql(weight: str, correct: bool) -> str:
    z = "z - coalesce(ln(incl), 0.0)" if correct else "z"
    return f"""{DENSE}, lw AS (SELECT n.range AS neuron_id, {weight} AS w FROM range({CLASSES}) n LEFT JOIN (SELECT neuron_id, count(*) AS c FROM lab GROUP BY 1) l ON l.neuron_id = n.range),
sm AS (SELECT neuron_id, least(1.0, {SHARE} * w / (SELECT sum(w) FROM lw)) AS incl FROM lw ORDER BY -ln(({h32_sql(str(SEED), 'neuron_id')} + 1) / 4294967296.0) / w, neuron_id LIMIT {SHARE}),
sa AS (SELECT instance_id, neuron_id FROM lab UNION SELECT instance_id, sm.neuron_id FROM lab, sm),
zs AS (SELECT instance_id, neuron_id, {z} AS z FROM zd JOIN sa USING (instance_id, neuron_id) LEFT JOIN sm USING (neuron_id)), {softmax_sql('pr', 'zs')}
SELECT instance_id, neuron_id, {r6_sql('prob')} AS prob FROM pr"""


def _sampled(spark: SparkSession, sf_dir: str, freq: bool, correct: bool) -> DataFrame:
    n = Net(spark, sf_dir)
    neurons = n.w_out.select("neuron_id").distinct()
    if freq:
        count = n.labels.groupBy("neuron_id").agg(F.count(F.lit(1)).alias("c"))
        neurons = neurons.join(count, "neuron_id", "left").select("neuron_id", (F.coalesce("c", F.lit(0)) + 1).cast("double").alias("weight"))
    sample = network.sampled_neurons(neurons, SHARE, SEED, "weight" if freq else None)
    active = network.with_labels(n.labels.select("instance_id").join(F.broadcast(sample.select("neuron_id"))), n.labels)
    z = n.logits(active)
    return network.active_softmax(network.correct_logits(z, sample) if correct else z).select("instance_id", "neuron_id", r6(F.col("prob")).alias("prob"))


@query(_sampled_sql("1.0", False))
def q_sampled_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sampled(spark, sf_dir, False, False)


@query(_sampled_sql("CAST(coalesce(c, 0) + 1 AS DOUBLE)", False))
def q_sampled_softmax_freq(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sampled(spark, sf_dir, True, False)


@query(_sampled_sql("CAST(coalesce(c, 0) + 1 AS DOUBLE)", True))
def q_sampled_softmax_corrected(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sampled(spark, sf_dir, True, True)


@query(f"{DENSE} SELECT instance_id, neuron_id FROM (SELECT *, row_number() OVER (PARTITION BY instance_id ORDER BY round(z, 9) DESC, neuron_id) AS r FROM zd) WHERE r <= 5")
def q_exact_topk_activation(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = _dense(Net(spark, sf_dir)).withColumn("z", F.round("z", 9))
    return network.exact_topk(z, 5).select("instance_id", "neuron_id")


@query(f"{DENSE} SELECT instance_id, neuron_id FROM every WHERE {h32_sql(str(SEED), 'instance_id', 'neuron_id')} % 2 = 0")
def q_dropout_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Net(spark, sf_dir).all_neurons().where(h32(SEED, F.col("instance_id"), F.col("neuron_id")) % 2 == 0)


# ---- predictions and measures ----
PRED = f"{DENSE}, pd AS (SELECT instance_id, r AS rank, neuron_id AS label FROM (SELECT *, row_number() OVER (PARTITION BY instance_id ORDER BY round(z, 9) DESC, neuron_id) AS r FROM zd) WHERE r <= 5), ht AS (SELECT pd.instance_id, rank, CASE WHEN lab.instance_id IS NULL THEN 0 ELSE 1 END AS hit FROM pd LEFT JOIN lab ON lab.instance_id = pd.instance_id AND lab.neuron_id = pd.label)"


def _pred(n: Net) -> DataFrame:
    from pyspark.sql.window import Window

    w = Window.partitionBy("instance_id").orderBy(F.desc(F.round("z", 9)), "neuron_id")
    return _dense(n).withColumn("rank", F.row_number().over(w)).where("rank <= 5").select("instance_id", "rank", F.col("neuron_id").alias("label"))


def _truth(n: Net) -> DataFrame:
    return n.labels.select("instance_id", F.col("neuron_id").alias("label"))


@query(f"{PRED} SELECT instance_id, CAST(rank AS INTEGER) AS rank, label FROM pd")
def q_topk_predictions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pred(Net(spark, sf_dir))


@query(f"{PRED} SELECT k, {r6_sql('avg(h)')} AS value FROM (SELECT k, instance_id, sum(CASE WHEN rank <= k THEN hit ELSE 0 END) / CAST(k AS DOUBLE) AS h FROM ht, (SELECT unnest([1, 3, 5]) AS k) GROUP BY 1, 2) GROUP BY 1")
def q_precision_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return metrics.precision_at_k(_pred(n), _truth(n), [1, 3, 5]).select("k", r6(F.col("value")).alias("value"))


@query(f"{PRED} SELECT k, {r6_sql('avg(h)')} AS value FROM (SELECT k, instance_id, CAST(sum(CASE WHEN rank <= k THEN hit ELSE 0 END) AS DOUBLE) AS h FROM ht, (SELECT unnest([1, 3, 5]) AS k) GROUP BY 1, 2) GROUP BY 1")
def q_recall_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return metrics.recall_at_k(_pred(n), _truth(n), [1, 3, 5]).select("k", r6(F.col("value")).alias("value"))


@query(f"{PRED} SELECT 5 AS k, {r6_sql('avg(g)')} AS value FROM (SELECT instance_id, sum(hit / log2(rank + 1.0)) AS g FROM ht GROUP BY 1)")
def q_ndcg_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return metrics.ndcg_at_k(_pred(n), _truth(n), 5).select("k", r6(F.col("value")).alias("value"))


# a run log from events: a run is an event type, an iteration a day of its, its score the share of all users that the type has reached by then
LOG = """WITH ev AS (SELECT event_type AS run_id, user_id, CAST(ts AS DATE) AS day, min(epoch_us(ts)) AS lo, max(epoch_us(ts)) AS hi FROM events WHERE ts IS NOT NULL GROUP BY 1, 2, 3),
dy AS (SELECT run_id, day, min(lo) AS lo, max(hi) AS hi, sum(CASE WHEN day = first THEN 1 ELSE 0 END) AS fresh FROM (SELECT *, min(day) OVER (PARTITION BY run_id, user_id) AS first FROM ev) GROUP BY 1, 2),
lg AS (SELECT run_id, row_number() OVER (PARTITION BY run_id ORDER BY day) AS iteration, (hi - min(lo) OVER (PARTITION BY run_id)) // 1000 + 1 AS wall_ms,
CAST(sum(fresh) OVER (PARTITION BY run_id ORDER BY day) AS DOUBLE) / (SELECT count(DISTINCT user_id) FROM events) AS p_at_1 FROM dy)"""


def runlog(spark: SparkSession, sf_dir: str) -> DataFrame:
    """run_id, iteration, wall_ms, p_at_1; windows over all days of a type hold one row a day."""
    from pyspark.sql.window import Window

    e = load(spark, sf_dir, "events")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    ev = e.where("ts is not null").groupBy(F.col("event_type").alias("run_id"), "user_id", F.to_date("ts").alias("day")).agg(F.min(us).alias("lo"), F.max(us).alias("hi"))
    ev = ev.withColumn("fresh", (F.col("day") == F.min("day").over(Window.partitionBy("run_id", "user_id"))).cast("long"))
    days = ev.groupBy("run_id", "day").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("fresh").alias("fresh"))
    users = e.agg(F.count_distinct("user_id").alias("users"))
    run = Window.partitionBy("run_id")
    by_day = run.orderBy("day")
    return days.join(F.broadcast(users)).select("run_id", F.row_number().over(by_day).cast("long").alias("iteration"), (F.floor((F.col("hi") - F.min("lo").over(run)) / 1000) + 1).alias("wall_ms"), (F.sum("fresh").over(by_day).cast("double") / F.col("users")).alias("p_at_1"))


TTA = f"{LOG}, tg AS (SELECT unnest([0.5, 0.7, 0.9]) AS target), ta AS (SELECT run_id, CAST(target AS DOUBLE) AS target, min(wall_ms) FILTER (p_at_1 >= target) AS wall_ms, min(iteration) FILTER (p_at_1 >= target) AS iteration FROM lg, tg GROUP BY 1, 2)"


@query(f"{TTA} SELECT run_id, target, wall_ms, iteration FROM ta")
def q_time_to_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.time_to_accuracy(runlog(spark, sf_dir), [0.5, 0.7, 0.9])


@query(f"{TTA} SELECT a.run_id, a.target, {r6_sql('CAST(b.wall_ms AS DOUBLE) / a.wall_ms')} AS ratio FROM ta a JOIN ta b ON a.target = b.target AND b.run_id = 'view'")
def q_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.speedup(metrics.time_to_accuracy(runlog(spark, sf_dir), [0.5, 0.7, 0.9]), "view").select("run_id", "target", r6(F.col("ratio")).alias("ratio"))


@query(f"""{LOG}, b AS (SELECT *, max(p_at_1) OVER (PARTITION BY run_id ORDER BY iteration) AS best FROM lg), w AS (SELECT *, lag(best, 3) OVER (PARTITION BY run_id ORDER BY iteration) AS was FROM b)
SELECT run_id, min(iteration) AS stop_at FROM w WHERE was IS NOT NULL AND best < was + 0.05 GROUP BY 1""")
def q_early_stop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.early_stop(runlog(spark, sf_dir), 3, 0.05)


@query(f"{LOG} SELECT run_id, iteration, {r6_sql('p_at_1 - lag(p_at_1) OVER (PARTITION BY run_id ORDER BY iteration)')} AS gain, {r6_sql('avg(p_at_1) OVER (PARTITION BY run_id ORDER BY iteration ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)')} AS smooth FROM lg")
def q_runlog_lag(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql.window import Window

    w = Window.partitionBy("run_id").orderBy("iteration")
    return runlog(spark, sf_dir).select("run_id", "iteration", r6(F.col("p_at_1") - F.lag("p_at_1").over(w)).alias("gain"), r6(F.avg("p_at_1").over(w.rowsBetween(-2, 0))).alias("smooth"))


@query(f"""{NET}, s AS (SELECT instance_id, count(*) AS n FROM act GROUP BY 1) SELECT count(*) AS instances, {r6_sql('avg(n)')} AS active_mean, max(n) AS active_max, {r6_sql(f'avg(n) / {CLASSES}')} AS active_frac FROM s""")
def q_active_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = metrics.active_stats(Net(spark, sf_dir).active(), CLASSES)
    return s.withColumns({"active_mean": r6(F.col("active_mean")), "active_frac": r6(F.col("active_frac"))})


@query(f"""{NET}, t AS (SELECT DISTINCT neuron_id, unit FROM act JOIN hid USING (instance_id)),
s AS (SELECT avg(n) / {CLASSES} AS f FROM (SELECT count(*) AS n FROM act GROUP BY instance_id))
SELECT {r6_sql(f'count(*) / CAST({CLASSES * UNITS} AS DOUBLE)')} AS measured, {r6_sql('any_value(f) * any_value(f)')} AS expected FROM t, s""")
def q_update_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    touched = n.active().join(n.hidden, "instance_id").select("neuron_id", "unit").distinct()
    share = metrics.update_share(touched, CLASSES * UNITS, metrics.active_stats(n.active(), CLASSES))
    return share.select(r6(F.col("measured")).alias("measured"), r6(F.col("expected")).alias("expected"))


@query(f"""{NET}, c AS (SELECT neuron_id, unit, count(*) AS n FROM act JOIN hid USING (instance_id) GROUP BY 1, 2)
SELECT count(*) AS touched, CAST(sum(CASE WHEN n > 1 THEN 1 ELSE 0 END) AS BIGINT) AS shared, {r6_sql('sum(CASE WHEN n > 1 THEN 1 ELSE 0 END) / CAST(count(*) AS DOUBLE)')} AS rate FROM c""")
def q_conflict_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    c = metrics.conflict_rate(n.active().join(n.hidden, "instance_id"), ["neuron_id", "unit"])
    return c.withColumn("rate", r6(F.col("rate")))


@query(f"""{NET} SELECT (SELECT count(*) FROM feats) * {UNITS} AS input_layer, (SELECT count(*) FROM act JOIN hid USING (instance_id)) AS output_sparse,
(SELECT count(*) FROM documents) * {UNITS * CLASSES} AS output_dense""")
def q_flops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Multiply-adds of a forward pass: the input layer by non-zeros, the output layer by active pairs and densely."""
    n = Net(spark, sf_dir)
    a = n.features.agg((F.count(F.lit(1)) * UNITS).alias("input_layer"))
    b = n.active().join(n.hidden, "instance_id").agg(F.count(F.lit(1)).alias("output_sparse"))
    return a.join(F.broadcast(b)).withColumn("output_dense", F.lit(n.count * UNITS * CLASSES).cast("long"))


@query(f"{NET} SELECT 'in' AS layer, count(*) AS params FROM w_in UNION ALL SELECT 'out', count(*) FROM w_out")
def q_param_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    return n.w_in.agg(F.count(F.lit(1)).alias("params")).withColumn("layer", F.lit("in")).unionByName(n.w_out.agg(F.count(F.lit(1)).alias("params")).withColumn("layer", F.lit("out")))


@query(f"""{NET}, f AS (SELECT instance_id, count(*) AS n FROM feats GROUP BY 1)
SELECT count(*) AS instances, (SELECT count(DISTINCT idx) FROM feats) AS features, {r6_sql('avg(n)')} AS mean_nonzeros, {r6_sql(f'avg(n) / {DIMS}')} AS density, (SELECT count(DISTINCT neuron_id) FROM lab) AS labels FROM f""")
def q_dataset_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = Net(spark, sf_dir)
    s = workloads.dataset_stats(n.features, n.labels.withColumnRenamed("neuron_id", "label"), DIMS)
    return s.withColumns({"mean_nonzeros": r6(F.col("mean_nonzeros")), "density": r6(F.col("density"))})


# ---- binary measures on the quality labels: score by symbols in the text ----
BIN = "WITH b AS (SELECT quality AS y, 1.0 / (1 + (length(text) - length(replace(text, '*', '')))) AS p FROM labels JOIN documents USING (doc_id))"


def _binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id")
    return d.select(F.col("quality").alias("y"), (1.0 / (1 + F.length("text") - F.length(F.replace("text", F.lit("*"), F.lit(""))))).alias("p"))


@query(f"{BIN} SELECT {r6_sql('(SELECT sum(CASE WHEN a.p > c.p THEN 1.0 WHEN a.p = c.p THEN 0.5 ELSE 0 END) / count(*) FROM b a, b c WHERE a.y = 1 AND c.y = 0)')} AS value")
def q_auc_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.auc(_binary(spark, sf_dir)).select(r6(F.col("value")).alias("value"))


@query(f"{BIN} SELECT {r6_sql('-avg(CASE WHEN y = 1 THEN ln(least(1 - 1e-12, greatest(1e-12, p))) ELSE ln(1 - least(1 - 1e-12, greatest(1e-12, p))) END)')} AS value FROM b")
def q_log_loss_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.log_loss(_binary(spark, sf_dir)).select(r6(F.col("value")).alias("value"))


# ---- workloads ----
WORDS = "wd AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^\\p{L}\\p{N}]+'), lambda x: x <> '') AS ws FROM documents), pw AS (SELECT doc_id, unnest(range(len(ws))) AS place, unnest(ws) AS word, len(ws) AS n FROM wd)"


@query(f"""WITH {WORDS}, f AS (SELECT DISTINCT doc_id, word FROM pw WHERE place * 2 < n), l AS (SELECT DISTINCT doc_id, word FROM pw WHERE place * 2 >= n),
c AS (SELECT word FROM l GROUP BY 1 HAVING count(*) >= 2)
SELECT doc_id AS instance_id, 'feature' AS role, count(*) AS n FROM f GROUP BY 1 UNION ALL SELECT doc_id, 'label', count(*) FROM l JOIN c USING (word) GROUP BY 1""")
def q_wordtag_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    f, lab = workloads.word_tagging(spark, sf_dir)
    both = f.withColumn("role", F.lit("feature")).unionByName(lab.withColumn("role", F.lit("label")))
    return both.groupBy("instance_id", "role").agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH {WORDS}, s AS (SELECT DISTINCT doc_id, CAST(v.range AS INTEGER) AS view, CAST({h32_sql('word')} % 4096 AS INTEGER) AS idx FROM (SELECT DISTINCT doc_id, word FROM pw), range(-1, {workloads.VIEWS}) v
WHERE {h32_sql('11', 'v.range', 'doc_id', 'word')} % 2 = 0),
c AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS label FROM documents) SELECT doc_id AS instance_id, view, idx, label FROM s JOIN c USING (doc_id)""")
def q_knownitem_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.known_item(spark, sf_dir, 4096).drop("val")


@query(f"""WITH {WORDS}, s AS (SELECT DISTINCT doc_id, CASE WHEN {h32_sql('11', 'doc_id', 'place')} % 4 < 3 THEN 'train' ELSE 'test' END AS split, CAST({h32_sql('word')} % 4096 AS INTEGER) AS idx FROM pw),
c AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS label FROM documents) SELECT doc_id AS instance_id, split, idx, label FROM s JOIN c USING (doc_id)""")
def q_knownitem_strict_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.strict_known_item(spark, sf_dir, 4096).drop("val")


@query(f"""WITH p AS (SELECT DISTINCT l_orderkey AS instance_id, l_partkey AS part FROM lineitem), r AS (SELECT *, row_number() OVER (PARTITION BY instance_id ORDER BY {h32_sql('11', 'instance_id', 'part')}, part) AS r, count(*) OVER (PARTITION BY instance_id) AS n FROM p)
SELECT instance_id, part, r = 1 AS is_label FROM r WHERE n >= 2""")
def q_copurchase_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.copurchase(spark, sf_dir)


@query("""SELECT DISTINCT o_orderkey, unnest(['segment=' || c_mktsegment, 'nation=' || n_name, 'region=' || r_name]) AS feature FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
UNION SELECT l_orderkey, unnest(['brand=' || p_brand, 'type=' || p_type, 'supplied=' || s_nationkey]) FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey""")
def q_star_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.star_features(spark, sf_dir)


@query("""SELECT 'lang' AS kind, lang AS label, count(*) AS n FROM documents GROUP BY 2 UNION ALL SELECT 'quality', CAST(quality AS VARCHAR), count(*) FROM labels GROUP BY 2
UNION ALL SELECT 'toxic', CAST(toxic AS VARCHAR), count(*) FROM labels GROUP BY 2 UNION ALL SELECT 'role', role, count(*) FROM conversations GROUP BY 2""")
def q_small_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [workloads.small_labels(spark, sf_dir, k).groupBy("label").agg(F.count(F.lit(1)).alias("n")).withColumn("kind", F.lit(k)) for k in ("lang", "quality", "toxic", "role")]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("""WITH w AS (SELECT page_id, unnest(regexp_split_to_array(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^\\p{L}\\p{N}]+')) AS word FROM pages)
SELECT page_id AS instance_id, count(*) AS n_words, count(DISTINCT word) AS n_distinct FROM w WHERE word <> '' GROUP BY 1""")
def q_page_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return workloads.page_words(spark, sf_dir).groupBy("instance_id").agg(F.count(F.lit(1)).alias("n_words"), F.count_distinct("word").alias("n_distinct"))


_slot = lambda *x: f"{h32_sql(*x)} % 1024"


@query(f"""SELECT event_id, CAST(user_id % 10 AS INTEGER) AS label, list_sort(list_distinct([{_slot("'t'", 'event_type')}, {_slot("'k'", "json_extract_string(props, '$.k')")}, {_slot("'h'", 'hour(ts)')}])) AS slots FROM events""".replace("SELECT event_id", "WITH x AS (SELECT event_id").replace("FROM events", "FROM events) SELECT event_id, label, array_to_string(slots, ',') AS slots FROM x"))
def q_event_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = workloads.event_instances(load(spark, sf_dir, "events"), 1024)
    return e.select("event_id", "label", F.array_join(F.sort_array("feats"), ",").alias("slots"))


# ---- whole runs: no SQL counterpart, tests/ holds their properties ----
def _runs(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> DataFrame:
    from bucketnet import experiments

    return experiments.time_accuracy(spark, sf_dir, rounds=3, local_steps=40, names=names).drop("wall_ms")


@query()
def q_train_hashed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """120 steps of the method with each strategy on the known-item workload."""
    return _runs(spark, sf_dir, ("topk", "vanilla", "threshold"))


@query()
def q_train_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _runs(spark, sf_dir, ("dense",))


@query()
def q_train_sampled_softmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _runs(spark, sf_dir, ("static", "static_freq", "static_corrected", "static_20pct"))


@query()
def q_train_ceilings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact adaptive sparsity and random dropout."""
    return _runs(spark, sf_dir, ("exact_topk", "dropout"))


@query()
def q_train_async(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four learners with stale snapshots."""
    from bucketnet import experiments

    sets = experiments.known_item_sets(spark, sf_dir)
    arm = experiments.main_arms(sets[2], max(20, sets[2] // 200))["topk"]
    return experiments.run_arms(spark, sets, {"learners_4": arm}, 3, 20, learners=4, logs=1).drop("wall_ms")


@query()
def q_train_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plan C on the known-item workload: eight steps with the output layer in four shards, dense and by threshold."""
    from bucketnet import experiments
    from bucketnet.plans import shards
    from bucketnet.plans.kernel import NetConf

    rows, _, labels = experiments.known_item_sets(spark, sf_dir)
    logs = []
    for arm in ("dense", "threshold"):
        conf = NetConf(experiments.DIMS, 32, labels, strategy=arm, k=4, tables=12, rate=0.01, n0=4)
        logs += [(arm, x["iteration"], x["loss"], x["active_mean"] / labels, x["refreshed"]) for x in shards.train(rows, conf, 8, 4)[1]]
    return spark.createDataFrame(logs, "run_id string, iteration long, loss double, active_frac double, refreshed boolean")


@query()
def q_train_languages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four labels, dense output."""
    from bucketnet import experiments

    return experiments.run_arms(spark, experiments.small_label_sets(spark, sf_dir, "lang"), {"lang": {"strategy": "dense"}}, 2, 30, logs=1).drop("wall_ms")


@query()
def q_family_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet import experiments

    return experiments.family_curve(spark, sf_dir)


@query()
def q_tables_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet import experiments

    return experiments.tables_sweep(spark, sf_dir)


@query("SELECT t, at_iteration FROM (SELECT t, CAST(ceil(sum(50 * exp(0.1 * (t - 1))) OVER (ORDER BY t) - 1e-9) AS BIGINT) AS at_iteration FROM (SELECT range AS t FROM range(1, 60))) WHERE at_iteration <= 180")
def q_train_refreshes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The iterations at which the tables of a real run were refreshed are those of the calendar."""
    from bucketnet import experiments

    return experiments.refresh_log(spark, sf_dir).select("t", "at_iteration")


@query()
def q_train_families(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet import experiments

    return experiments.family_arms(spark, sf_dir).drop("wall_ms")


@query()
def q_train_share_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet import experiments

    return experiments.share_sweep(spark, sf_dir).drop("wall_ms")


@query()
def q_train_word_tagging(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many labels an instance."""
    from bucketnet import experiments

    return experiments.trained_workload(spark, sf_dir, "word_tagging", 2).drop("wall_ms")


@query()
def q_train_copurchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts to parts."""
    from bucketnet import experiments

    return experiments.trained_workload(spark, sf_dir, "copurchase", 2).drop("wall_ms")


@query()
def q_train_roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Roles of conversations."""
    from bucketnet import experiments

    return experiments.trained_workload(spark, sf_dir, "role", 2).drop("wall_ms")


@query()
def q_update_heuristics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W13."""
    from bucketnet import experiments

    return experiments.update_heuristics(spark, sf_dir, 2, 30).drop("wall_ms")


@query()
def q_batch_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W7, C18."""
    from bucketnet import experiments

    return experiments.batch_sweep(spark, sf_dir, rounds=2, local_steps=20).drop("wall_ms")


@query()
def q_asynchrony(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W15."""
    from bucketnet import experiments

    return experiments.asynchrony(spark, sf_dir, 2, 20).drop("wall_ms")


@query()
def q_strategy_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Times are of the machine; recall and mean product are not."""
    from bucketnet import experiments

    return experiments.strategy_times(spark, sf_dir).select("strategy", "beta", "mean_chosen", "recall", "mean_product")


@query()
def q_run_time_to_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W5, C3-C5 of real runs, one seed."""
    from bucketnet import experiments

    return experiments.time_to_accuracy(spark, sf_dir, seeds=(1,), rounds=4).select("run_id", "iteration", "best_p_at_1")
