import numpy as np
import pytest
from pyspark.sql import functions as F

from bucketnet.functions import probability as P

GOLDEN = [  # p, k, union of 50, at least 2 of 50
    (0.5, 9, 0.09313, 0.00439), (0.6, 9, 0.39736, 0.09061), (0.7, 9, 0.87248, 0.60438), (0.8, 9, 0.99926, 0.99351),
    (0.5, 8, 0.17774, 0.01651), (0.6, 8, 0.57128, 0.20508), (0.7, 8, 0.94864, 0.79153), (0.9, 8, 1.0, 1.0)]


@pytest.mark.parametrize(("p", "k", "union", "two"), GOLDEN)
def test_golden(p, k, union, two):
    assert abs(P.union(p, k, 50) - union) < 1e-5
    assert abs(P.threshold(p, k, 50, 2) - two) < 1e-5


def test_columns_equal_plain_functions(spark):
    d = spark.createDataFrame([(p, k) for p, k, *_ in GOLDEN] + [(1.0, 3)], "p double, k int")
    n = F.lit(50)
    for r in d.select("p", "k", P.prob_union(F.col("p"), F.col("k"), n).alias("u"), P.prob_threshold(F.col("p"), F.col("k"), n, F.lit(2)).alias("t")).collect():
        assert abs(r.u - P.union(r.p, r.k, 50)) < 1e-9
        assert abs(r.t - P.threshold(r.p, r.k, 50, 2)) < 1e-9


def test_inclusion_by_simulation():
    """An item that each table holds with chance q is met in tau tables as often as the formula says."""
    rng = np.random.default_rng(1)
    q, tau, runs = 0.3, 4, 20_000
    met = (rng.random((runs, tau)) < q).any(axis=1).mean()
    expected = 1 - (1 - q) ** tau
    assert abs(met - expected) < 4 * np.sqrt(expected * (1 - expected) / runs)
