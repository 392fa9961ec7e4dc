"""The relational operators around the methods, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bucketnet.functions.vector import r6, r6_sql
from bucketnet.sources.tables import load

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f
    return keep


@query("SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' AND l_discount BETWEEN 0.03 AND 0.06 AND l_returnflag IN ('A', 'R')")
def q_filter_lineitem_shipdate(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "lineitem")
    return d.where((F.col("l_shipdate") >= "1996-01-01") & (F.col("l_shipdate") < "1997-01-01") & F.col("l_discount").between(0.03, 0.06) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_linenumber", "l_extendedprice")


@query("SELECT doc_id, n_chars FROM documents WHERE lang IS NOT NULL AND lang <> 'en' AND source LIKE 'src1%'")
def q_docs_lang_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").where("lang is not null and lang <> 'en' and source like 'src1%'").select("doc_id", "n_chars")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(CAST(l_quantity AS DOUBLE)), 2) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem GROUP BY 1, 2")
def q_pricing_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("SELECT vec_id, i - 1 AS idx, embedding[i] AS val FROM (SELECT vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings) WHERE embedding[i] <> 0")
def q_nonzero_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("idx", "val")).where("val <> 0").withColumn("idx", F.col("idx").cast("long"))


JOIN = "SELECT o_orderpriority, count(*) AS n, count(DISTINCT l_partkey) AS parts FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"


def _orders(spark: SparkSession, sf_dir: str, hint: str | None) -> DataFrame:
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    joined = (o.hint(hint) if hint else o).join(li, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("l_partkey").alias("parts"))


@query(JOIN)
def q_orders_lineitem_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _orders(spark, sf_dir, "merge")


@query(JOIN)
def q_orders_lineitem_shash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _orders(spark, sf_dir, "shuffle_hash")


@query(JOIN)
def q_orders_lineitem_auto(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _orders(spark, sf_dir, None)


@query("SELECT r_name, n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def q_broadcast_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")  # 25 and 5 rows by definition
    return load(spark, sf_dir, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


NEAR = 4.999  # certainly within 5, whatever rounding does


@query("""SELECT a.p_partkey AS part, count(*) AS near FROM part a JOIN part b ON a.p_brand = b.p_brand AND abs(a.p_retailprice - b.p_retailprice) <= 5 AND a.p_partkey <> b.p_partkey GROUP BY 1""")
def q_price_band_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A range join by counts: parts are first counted by brand and price.

    Prices nearer than 5 by far are a sum in a window over a brand's prices; those at 5, up to rounding, are joined by bins and
    compared as doubles. Pairs of equal key are taken off again.
    """
    p = load(spark, sf_dir, "part").select("p_partkey", "p_brand", F.col("p_retailprice").cast("double").alias("x")).where("p_partkey is not null and p_brand is not null and x is not null")
    by = p.groupBy("p_brand", "x").agg(F.count(F.lit(1)).alias("n"))
    inner = by.withColumn("inside", F.expr(f"sum(n) over (partition by p_brand order by x range between {NEAR}D preceding and {NEAR}D following)"))
    edge = lambda at, d: F.floor((F.col("x") + at) * 1000) + d
    one = by.select("p_brand", "x", F.explode(F.array(*[edge(at, d) for at in (-5, 5) for d in (-1, 0, 1)])).alias("bin"))
    two = by.select(F.col("p_brand").alias("b2"), F.col("x").alias("x2"), F.col("n").alias("n2"), F.floor(F.col("x") * 1000).alias("bin2"))
    rim = one.join(two, (F.col("p_brand") == F.col("b2")) & (F.col("bin") == F.col("bin2"))).where(((F.col("x2") < F.col("x") - NEAR) | (F.col("x2") > F.col("x") + NEAR)) & (F.abs(F.col("x") - F.col("x2")) <= 5))
    rim = rim.groupBy(F.col("p_brand").alias("r_b"), F.col("x").alias("r_x")).agg(F.sum("n2").alias("rim"))
    near = inner.join(rim, (F.col("p_brand") == F.col("r_b")) & (F.col("x") == F.col("r_x")), "left").select(F.col("p_brand").alias("n_b"), F.col("x").alias("n_x"), (F.col("inside") + F.coalesce("rim", F.lit(0))).alias("near"))
    own = p.select(F.col("p_partkey").alias("o_k"), F.col("p_brand").alias("o_b"), F.col("x").alias("o_x"))
    same = p.join(own, (F.col("p_partkey") == F.col("o_k")) & (F.col("p_brand") == F.col("o_b"))).where(F.abs(F.col("x") - F.col("o_x")) <= 5).groupBy(F.col("p_partkey").alias("s_k")).agg(F.count(F.lit(1)).alias("same"))
    total = p.join(near, (F.col("p_brand") == F.col("n_b")) & (F.col("x") == F.col("n_x"))).groupBy("p_partkey").agg(F.sum("near").alias("all"))
    return total.join(same, F.col("p_partkey") == F.col("s_k")).select(F.col("p_partkey").alias("part"), (F.col("all") - F.col("same")).alias("near")).where("near > 0")


@query("SELECT a.event_id, count(*) AS following FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR GROUP BY 1")
def q_events_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An interval join by time bins: an event within 6 hours is in this bin of 6 hours or the next."""
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    width = 6 * 3600
    a = e.withColumn("bin", F.explode(F.array((F.unix_timestamp("ts") / width).cast("long"), (F.unix_timestamp("ts") / width).cast("long") + 1)))
    b = e.select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), (F.unix_timestamp("ts") / width).cast("long").alias("bin2"))
    near = a.join(b, (F.col("user_id") == F.col("u2")) & (F.col("bin") == F.col("bin2"))).where((F.col("t2") > F.col("ts")) & (F.col("t2") <= F.col("ts") + F.expr("interval 6 hours")))
    return near.groupBy("event_id").agg(F.count(F.lit(1)).alias("following"))


@query("""WITH s AS (SELECT t.range AS t, CAST(ceil((SELECT sum(5 * exp(0.1 * i.range)) FROM range(12) i WHERE i.range < t.range) - 1e-9) AS BIGINT) AS at_iteration FROM range(1, 13) t),
o AS (SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS iteration FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL)
SELECT event_id, iteration, (SELECT max(t) FROM s WHERE at_iteration <= o.iteration) AS last_refresh FROM o""")
def q_iteration_asof_refresh(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join: a user's events are iterations, each with the last refresh before it, carried forward in the union of both sides."""
    from bucketnet.operators.index import rehash_schedule

    e = load(spark, sf_dir, "events").where("user_id is not null and ts is not null")
    own = Window.partitionBy("user_id")
    i = e.select("user_id", "event_id", F.row_number().over(own.orderBy("ts", "event_id")).cast("long").alias("iteration"), F.lit(None).cast("long").alias("t"), F.lit(1).alias("kind"))
    s = rehash_schedule(spark, 5, 0.1, 12).select(F.col("at_iteration").alias("iteration"), "t", F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"))
    s = e.select("user_id").distinct().join(F.broadcast(s))
    w = own.orderBy("iteration", "kind").rowsBetween(Window.unboundedPreceding, 0)
    return s.unionByName(i).withColumn("last_refresh", F.last("t", ignorenulls=True).over(w)).where("kind = 1").select("event_id", "iteration", "last_refresh")


@query("SELECT event_id, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.ts < a.ts AND b.event_type = 'purchase' AND b.ts = (SELECT max(c.ts) FROM events c WHERE c.user_id = a.user_id AND c.ts < a.ts AND c.event_type = 'purchase')) AS last_purchase FROM events a")
def q_events_asof_purchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", F.max(F.when(F.col("event_type") == "purchase", F.struct("ts", "event_id"))).over(w)["event_id"].alias("last_purchase"))


@query("SELECT c_custkey, c_mktsegment FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_customers_without_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders").select("o_custkey")
    return load(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey", "c_mktsegment")


@query("SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000)")
def q_customers_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders").where("o_totalprice > 300000").select("o_custkey")
    return load(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_mktsegment")


@query("SELECT d.doc_id, d.lang, l.quality, l.toxic FROM documents d LEFT JOIN labels l USING (doc_id)")
def q_docs_labels_left(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id", "lang").join(load(spark, sf_dir, "labels"), "doc_id", "left")


@query("SELECT coalesce(a.u, b.u) AS user_id, coalesce(a.n, 0) AS clicks, coalesce(b.n, 0) AS purchases FROM (SELECT user_id AS u, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY 1) a FULL JOIN (SELECT user_id AS u, count(*) AS n FROM events WHERE event_type = 'purchase' GROUP BY 1) b ON a.u = b.u")
def q_users_full_outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    count = lambda kind, name: e.where(F.col("event_type") == kind).groupBy("user_id").agg(F.count(F.lit(1)).alias(name))
    return count("click", "clicks").join(count("purchase", "purchases"), "user_id", "full").select("user_id", F.coalesce("clicks", F.lit(0)).alias("clicks"), F.coalesce("purchases", F.lit(0)).alias("purchases"))


@query("SELECT c_custkey, t.o_orderkey, t.o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 3) t")
def q_lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    top = load(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3")
    return load(spark, sf_dir, "customer").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey", "o_totalprice")


@query("SELECT vec_id, arg_max(i, embedding[i + 1]) AS top FROM (SELECT vec_id, embedding, unnest(range(64)) AS i FROM embeddings) GROUP BY 1")
def q_argmax_per_bin(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x"))
    return rows.groupBy("vec_id").agg(F.max_by(F.col("i").cast("long"), "x").alias("top"))


@query("SELECT count(DISTINCT user_id) AS users, count(DISTINCT event_type) AS types FROM events")
def q_distinct_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").agg(F.count_distinct("user_id").alias("users"), F.count_distinct("event_type").alias("types"))


@query("SELECT event_type, date_trunc('day', ts) AS day, count(*) AS n, CAST(grouping(event_type) AS INTEGER) AS g1, CAST(grouping(date_trunc('day', ts)) AS INTEGER) AS g2 FROM events GROUP BY ROLLUP (event_type, date_trunc('day', ts))")
def q_events_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").select("event_type", F.date_trunc("day", "ts").alias("day"))
    return e.rollup("event_type", "day").agg(F.count(F.lit(1)).alias("n"), F.grouping("event_type").cast("int").alias("g1"), F.grouping("day").cast("int").alias("g2")).withColumn("day", F.col("day").cast("timestamp_ntz"))


@query("SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)")
def q_docs_cube_lang_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query("SELECT c_nationkey, c_mktsegment, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_nationkey), (c_mktsegment), ())")
def q_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").groupingSets([["c_nationkey"], ["c_mktsegment"], []], "c_nationkey", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]


@query("SELECT c_nationkey, " + ", ".join(f"count(*) FILTER (c_mktsegment = '{s}') AS {s.lower()}" for s in SEGMENTS) + " FROM customer GROUP BY 1")
def q_pivot_segment(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "customer").groupBy("c_nationkey").pivot("c_mktsegment", SEGMENTS).agg(F.count(F.lit(1)))
    return p.select("c_nationkey", *[F.coalesce(s, F.lit(0)).alias(s.lower()) for s in SEGMENTS])


@query("SELECT doc_id, 'quality' AS kind, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def q_unpivot_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "kind", "value")


@query(f"SELECT event_type, {r6_sql('avg(value)')} AS mean, {r6_sql('stddev_samp(value)')} AS sd, {r6_sql('quantile_cont(value, 0.5)')} AS median, {r6_sql('quantile_cont(value, 0.9)')} AS p90 FROM events GROUP BY 1")
def q_value_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy("event_type").agg(r6(F.avg("value")).alias("mean"), r6(F.stddev("value")).alias("sd"), r6(F.percentile("value", F.lit(0.5))).alias("median"), r6(F.percentile("value", F.lit(0.9))).alias("p90"))


@query("SELECT CAST(floor(o_totalprice / 50000) AS BIGINT) AS bin, count(*) AS n FROM orders GROUP BY 1")
def q_price_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").groupBy(F.floor(F.col("o_totalprice") / 50000).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


_W = "PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey"


@query(f"SELECT c_custkey, CAST(row_number() OVER ({_W}) AS INTEGER) AS rn, CAST(rank() OVER ({_W}) AS INTEGER) AS rk, CAST(dense_rank() OVER ({_W}) AS INTEGER) AS dr, CAST(ntile(4) OVER ({_W}) AS INTEGER) AS quarter, {r6_sql(f'percent_rank() OVER ({_W})')} AS pr FROM customer")
def q_window_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf_dir, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("quarter"), r6(F.percent_rank().over(w)).alias("pr"))


@query("SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id, 2) OVER w AS next2, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def q_window_analytic(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id", 2).over(w).alias("next2"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


@query(f"SELECT event_id, {r6_sql('avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW)')} AS moving FROM events")
def q_events_moving_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return load(spark, sf_dir, "events").select("event_id", r6(F.avg("value").over(w)).alias("moving"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def q_top_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


BUYERS = "SELECT user_id FROM events WHERE event_type = 'purchase'"
VIEWERS = "SELECT user_id FROM events WHERE event_type = 'view'"


def _users(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    return load(spark, sf_dir, "events").where(F.col("event_type") == kind).select("user_id")


@query(f"{BUYERS} INTERSECT {VIEWERS}")
def q_users_intersect(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _users(spark, sf_dir, "purchase").intersect(_users(spark, sf_dir, "view"))


@query(f"{BUYERS} EXCEPT {VIEWERS}")
def q_users_except(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _users(spark, sf_dir, "purchase").subtract(_users(spark, sf_dir, "view"))


@query(f"{BUYERS} UNION {VIEWERS}")
def q_users_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _users(spark, sf_dir, "purchase").union(_users(spark, sf_dir, "view")).distinct()


@query("SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS canonical FROM documents")
def q_docs_canonical(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet.workloads import canonical_documents

    return canonical_documents(spark, sf_dir)


@query("""WITH RECURSIVE st AS (SELECT event_type AS run_id, CAST(count(DISTINCT user_id) AS DOUBLE) AS n0 FROM events WHERE event_type IS NOT NULL GROUP BY 1),
s(run_id, n0, t, due) AS (SELECT run_id, n0, 1, n0 FROM st UNION ALL SELECT run_id, n0, t + 1, due + n0 * exp(0.1 * t) FROM s WHERE t < 12) SELECT run_id, t, CAST(ceil(due - 1e-9) AS BIGINT) AS at_iteration FROM s""")
def q_schedule_recursive(spark: SparkSession, sf_dir: str) -> DataFrame:
    from bucketnet.queries.retrieval import starts

    return spark.sql("WITH RECURSIVE s(run_id, n0, t, due) AS (SELECT run_id, CAST(n0 AS DOUBLE), 1, CAST(n0 AS DOUBLE) FROM {st} UNION ALL SELECT run_id, n0, t + 1, due + n0 * exp(0.1D * t) FROM s WHERE t < 12) SELECT run_id, t, CAST(ceil(due - 1e-9D) AS BIGINT) AS at_iteration FROM s", st=starts(spark, sf_dir))


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity > (SELECT 1.5 * avg(l_quantity) FROM lineitem)")
def q_above_avg_value(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "lineitem")
    top = d.agg((1.5 * F.avg("l_quantity")).alias("top"))
    return d.join(F.broadcast(top), F.col("l_quantity") > F.col("top")).select("l_orderkey", "l_linenumber", "l_quantity")


@query("SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def q_events_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT date_trunc('hour', ts) AS begins, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def q_events_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    return e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("begins"), "event_type", "n").withColumn("begins", F.col("begins").cast("timestamp_ntz"))


@query("SELECT w AS begins, count(*) AS n FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR * i.range AS w FROM events, range(3) i) GROUP BY 1")
def q_events_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    return e.groupBy(F.window("ts", "3 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("begins"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS begins, count(*) AS n FROM s GROUP BY user_id, k""")
def q_events_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    return e.groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("begins"), "n")
