"""Closed forms of the chances that hash tables select an item, as Columns. p: collision chance of one function."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def prob_table(p: Column, k: Column) -> Column:
    """One table of k functions hits."""
    return F.pow(p, k)


def prob_union(p: Column, k: Column, tables: Column) -> Column:
    """At least one of the tables hits."""
    return 1 - F.pow(1 - prob_table(p, k), tables)


def prob_vanilla_printed(p: Column, k: Column, tables: Column, tau: Column) -> Column:
    """One given set of tau tables hits and the others miss (the form that is in print)."""
    q = prob_table(p, k)
    return F.pow(q, tau) * F.pow(1 - q, tables - tau)


def prob_vanilla_inclusion(p: Column, k: Column, tau: Column) -> Column:
    """An item is met in the first tau tables: what sampling does."""
    return 1 - F.pow(1 - prob_table(p, k), tau)


def prob_threshold(p: Column, k: Column, tables: Column, m: Column) -> Column:
    """At least m of the tables hit: the upper tail of a binomial, term by term from the term before."""
    q = prob_table(p, k)
    first = F.named_struct(F.lit("term"), F.pow(1 - q, tables), F.lit("sum"), F.when(m <= 0, F.pow(1 - q, tables)).otherwise(F.lit(0.0)))
    odds = F.try_divide(q, 1 - q)

    def step(a: Column, i: Column) -> Column:
        term = a["term"] * (tables - i + 1) / i * odds
        return F.named_struct(F.lit("term"), term, F.lit("sum"), a["sum"] + F.when(i >= m, term).otherwise(F.lit(0.0)))

    tail = F.aggregate(F.sequence(F.lit(1), tables.cast("int")), first, step)["sum"]
    return F.when(q >= 1, F.when(m <= tables, 1.0).otherwise(0.0)).otherwise(tail)


def collision_simhash(cosine: Column) -> Column:
    """1 - angle / pi."""
    return 1 - F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), cosine))) / math.pi


def expected_update_share(active_share: Column) -> Column:
    """Share of weights that move when a share of each layer is active."""
    return active_share * active_share


def union(p: float, k: int, tables: int) -> float:
    return 1 - (1 - p**k) ** tables


def threshold(p: float, k: int, tables: int, m: int) -> float:
    q = p**k
    return sum(math.comb(tables, i) * q**i * (1 - q) ** (tables - i) for i in range(m, tables + 1))
