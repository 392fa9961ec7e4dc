import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketnet.operators import hashing, index, sampling
from bucketnet.sources.tables import every, vectors

SMALL = "/root/testdata/sf0.001"
FAM = hashing.SimHash(4, 6, 64, 11)


def as_set(df):
    return {tuple(r) for r in df.collect()}


def test_calendar_golden(spark):
    got = [round(r.exact, 3) for r in index.rehash_schedule(spark, 50, 0.1, 7).orderBy("t").collect()]
    assert got == [50, 105.259, 166.329, 233.822, 308.413, 390.849, 481.955]
    clock = index.Refresh("decay", 50, 0.1)
    fired = [i for i in range(1, 500) if clock.fires(i)]
    assert fired == [r.at_iteration for r in index.rehash_schedule(spark, 50, 0.1, 7).orderBy("t").collect()]


def test_merged_reservoir_is_the_whole_ones(spark):
    codes = FAM.codes(vectors(spark, SMALL), "id", "vec")
    whole = index.build_index(codes, 5)
    parts = index.merge_index(index.build_index(codes.where("id % 3 = 0"), 5), index.build_index(codes.where("id % 3 != 0"), 5), 5)
    cols = ["table_id", "code", "id"]
    assert as_set(whole.select(*cols)) == as_set(parts.select(*cols))


def test_order_of_rows_changes_nothing(spark):
    v = vectors(spark, SMALL)
    a = as_set(index.build_index(FAM.codes(v, "id", "vec"), 3).select("table_id", "code", "id"))
    b = as_set(index.build_index(FAM.codes(v.repartition(7, F.rand(3)), "id", "vec"), 3).select("table_id", "code", "id"))
    assert a == b


def test_reservoir_is_uniform():
    """Chance of each of 20 arrivals to be among 5: by the priority rule over many seeds."""
    from bucketnet.functions.seeds import h32_of

    runs, n, cap = 4000, 20, 5
    hits = np.zeros(n)
    for s in range(runs):
        hits[np.argsort([h32_of(s, i, 0) for i in range(n)])[:cap]] += 1
    expected = runs * cap / n
    assert ((hits - expected) ** 2 / expected).sum() < 45  # chi-square, 19 degrees, about 1 in 1000


def test_sequential_reservoir_keeps_cap(spark):
    rows = spark.createDataFrame([(0, 7, i, i) for i in range(50)] + [(1, 2, 5, 0)], "table_id int, code long, id long, seq long")
    got = index.cap_reservoir_sequential(rows, 8).groupBy("table_id", "code").count().collect()
    assert {(r.table_id, r.code): r["count"] for r in got} == {(0, 7): 8, (1, 2): 1}


def test_threshold_and_intersection_limits(spark):
    codes = FAM.codes(vectors(spark, SMALL), "id", "vec")
    p = sampling.probe(every(codes), index.build_index(codes)).persist()
    assert as_set(sampling.sample_threshold(p, 1).select("query_id", "id")) == as_set(sampling.sample_union(p))
    assert as_set(sampling.sample_threshold(p, 6).select("query_id", "id")) == as_set(sampling.sample_intersect(p, 6))
    assert as_set(sampling.sample_vanilla(p, 6, 10**6).select("query_id", "id")) == as_set(sampling.sample_union(p))


def test_one_bucket_search_is_exact(spark):
    """With every item in one bucket, search with re-ranking is brute force."""
    v = vectors(spark, SMALL)
    codes = v.select("id", F.lit(0).alias("table_id"), F.lit(0).cast("long").alias("code"))
    assert as_set(sampling.ann_search(every(codes), index.build_index(codes), every(v), v, 7)) == as_set(sampling.exact_knn(every(v), v, 7))


def test_cosine_and_blocks(spark, monkeypatch):
    v = vectors(spark, SMALL)
    whole = as_set(sampling.exact_knn(every(v), v, 5, "cosine"))
    monkeypatch.setattr(sampling, "QUERY_BLOCK", 3)
    assert as_set(sampling.exact_knn(every(v), v, 5, "cosine")) == whole


def test_incremental_projection_is_exact(spark):
    v = vectors(spark, SMALL)
    delta = spark.createDataFrame([(3, 5, 0.25), (3, 6, -0.5), (8, 0, 1.0)], "id long, idx int, val double")
    new = v.join(delta.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("idx", "val"))).alias("d")), "id", "left")
    grid = lambda x: F.floor(x.cast("double") * (1 << 20)) / (1 << 20)
    moved = new.select("id", F.transform("vec", lambda x, i: grid(x) + F.coalesce(F.element_at("d", i), F.lit(0.0))).alias("vec"))
    a = FAM.update(FAM.project(v, "id", "vec"), FAM.project_sparse(delta))
    assert as_set(a.select("id", "fn", "s")) == as_set(FAM.project(moved, "id", "vec").select("id", "fn", "s"))


def test_edges(spark):
    d = spark.createDataFrame([(1, [0.0] * 64), (2, None), (None, [1.0] * 64)], "id long, vec array<float>")
    got = FAM.codes(d, "id", "vec").collect()
    assert {r.id for r in got} == {1} and {r.code for r in got} == {15}  # projections of 0 count as positive
    assert FAM.codes(d.where("false"), "id", "vec").count() == 0
    f = spark.createDataFrame([(1, 3, 2.0), (2, 5, 0.0)], "id long, idx int, val double")
    codes = {r.id: r.code for r in hashing.DWTA(2, 1, 16, m=4).codes_sparse(f).collect()}
    assert codes[2] == hashing.EMPTY and codes[1] >= 0


def test_plan_limits_groups_before_the_shuffle(spark):
    codes = FAM.codes(vectors(spark, SMALL), "id", "vec")
    plan = index.build_index(codes, 4)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("WindowGroupLimit") == 2


def test_register_family():
    class Mine(hashing.SimHash):
        pass

    hashing.register_family("mine", Mine)
    assert hashing.FAMILIES["mine"] is Mine


@pytest.mark.parametrize("k", [4, 9])
def test_scan_gives_the_rows_of_search_without_pairs(spark, monkeypatch, k):
    """Ties, a vector of zeros, nulls and queries of fewer than ten candidates included, in one block and in several."""
    rng = np.random.default_rng(3)
    x = rng.integers(-2, 3, (400, 8)).astype(float)
    x[5], x[100:140] = 0, x[60:100]
    v = spark.createDataFrame([*((i, r) for i, r in enumerate(x.tolist())), (None, x[0].tolist()), (400, None)], "id long, vec array<double>").repartition(3).localCheckpoint()
    family = hashing.SimHash(k, 5, 8, 11)
    codes, q = family.codes(v, "id", "vec"), v.where("id % 5 = 0")
    want = sorted(map(tuple, sampling.ann_search(codes.where("id % 5 = 0"), index.build_index(codes), q, v, 10).collect()))
    for block in (sampling.QUERY_BLOCK, 30):
        monkeypatch.setattr(sampling, "QUERY_BLOCK", block)
        scan = sampling.ann_scan(family, q, v, 10)
        assert sorted(map(tuple, scan.collect())) == want
    assert "Join" not in scan._jdf.queryExecution().executedPlan().toString()


def test_search_query_sends_no_pairs(spark):
    """A query meets nearly all items in its tables: joined with vectors they filled the disk."""
    from bucketnet.queries import retrieval

    assert "Join" not in retrieval.q_ann_search(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
