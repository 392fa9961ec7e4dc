"""Every query with a SQL counterpart, against DuckDB on the smallest tables."""

import math

import duckdb
import pytest

from bucketnet import queries
from bucketnet.sources.tables import SCHEMAS

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for name in SCHEMAS:
        con.execute(f"create view {name} as select * from '{SMALL}/{name}.parquet'")
    return con


def rows(df):
    clean = lambda v: None if v is None or str(v) in ("nan", "NaT", "<NA>") else round(float(v), 9) if isinstance(v, float) else v
    got = [tuple(clean(v.item() if hasattr(v, "item") else v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False)]
    return sorted(got, key=lambda r: tuple((v is None, str(v)) for v in r))


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_same_rows(spark, duck, name):
    ours = queries.QUERIES[name](spark, SMALL).toPandas()
    theirs = duck.execute(queries.ORACLES[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    a, b = rows(ours), rows(theirs)
    assert len(a) == len(b)
    for x, y in zip(a, b, strict=True):
        assert all(p == q or (isinstance(p, float) and isinstance(q, (int, float)) and math.isclose(p, q, abs_tol=2e-6)) for p, q in zip(x, y, strict=True)), (x, y)


def test_entry_gives_rows(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_changes_lie_on_the_grid(spark):
    from bucketnet.functions.vector import GRID
    from bucketnet.queries import retrieval

    steps = [r.val * GRID for r in retrieval._delta(spark, SMALL).collect()]
    assert steps and all(x == int(x) and -GRID // 2 <= x < GRID // 2 for x in steps)


def test_price_band_counts_prices(spark, tmp_path):
    """Prices at exactly 5 apart, equal ones and a repeated key; as many partner rows as a pair join would make never arise."""
    rows = [(1, "a", 10.0), (2, "a", 15.0), (3, "a", 15.0), (4, "a", 20.01), (4, "a", 20.02), (5, "b", 12.0), (6, "a", 5.0), (7, "a", 0.1), (8, "a", 5.1), (9, None, 5.1), (10, "a", None), (11, "a", -5.0)]
    spark.createDataFrame(rows, "p_partkey long, p_brand string, p_retailprice double").coalesce(1).write.parquet(str(tmp_path / "part.parquet"))
    df = queries.QUERIES["q_price_band_join"](spark, str(tmp_path))
    con = duckdb.connect()
    con.execute(f"create view part as select * from '{tmp_path}/part.parquet/*.parquet'")
    want = sorted(con.execute(queries.ORACLES["q_price_band_join"]).fetchall())
    assert sorted((r.part, r.near) for r in df.collect()) == want
    many = spark.range(3000).selectExpr("id as p_partkey", "'a' as p_brand", "cast(id % 3 as double) as p_retailprice")
    many.coalesce(1).write.parquet(str(tmp_path / "many/part.parquet"))
    big = queries.QUERIES["q_price_band_join"](spark, str(tmp_path / "many"))
    assert {r.near for r in big.collect()} == {2999}
    assert "Window" in big._jdf.queryExecution().toString()


@pytest.mark.parametrize("name", ["q_early_stop", "q_runlog_lag", "q_speedup", "q_time_to_accuracy"])
def test_reads_the_events(spark, name):
    assert any("events" in f for f in queries.QUERIES[name](spark, SMALL).inputFiles())


@pytest.mark.parametrize("name", ["q_iteration_asof_refresh", "q_probabilities", "q_rehash_schedule", "q_schedule_recursive", "q_schedule_variants"])
def test_reads_a_given_table(spark, name):
    plan = queries.QUERIES[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "parquet" in plan
