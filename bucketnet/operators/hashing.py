"""Locality-sensitive hash families: K functions a table, L tables, all from a seed.

A family turns vectors into codes (id, table_id, code). Dense vectors are hashed in the row, by Column
expressions or by one Arrow matrix product; sparse ones as rows (id, idx, val) joined with the relation of
the functions, which is small (functions x dimensions) and generated, not stored.
"""

from __future__ import annotations

import math
from abc import ABC, abstractmethod
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketnet.functions.probability import collision_simhash
from bucketnet.functions.seeds import h32, h32_of
from bucketnet.functions.vector import GRID, fixed_point, long_dot, vec_dot

EMPTY = -1  # code of a sparse input without any non-zero


@dataclass(frozen=True)
class HashFamily(ABC):
    """What all families have. Longer inputs than dim are cut by expression paths; null vectors give null codes."""

    k: int
    tables: int
    dim: int
    seed: int = 11

    @property
    def functions(self) -> int:
        return self.k * self.tables

    @abstractmethod
    def symbols(self, vec: Column) -> Column:
        """array<long> of all functions' symbols of a dense vector column."""

    @property
    @abstractmethod
    def radix(self) -> int:
        """Symbols are below this."""

    def collision_prob(self, similarity: Column) -> Column:
        """The chance of equal symbols at a similarity, where the family has a closed form."""
        raise NotImplementedError(type(self).__name__)

    def codes(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        """id, table_id, code of each dense vector."""
        s = df.select(F.col(id_col).alias("id"), self.symbols(F.col(vec_col)).alias("s"))
        packed = F.array(*[self.pack([F.get("s", F.lit(t * self.k + j)) for j in range(self.k)]) for t in range(self.tables)])
        return s.select("id", F.posexplode(packed).alias("table_id", "code"))

    def pack(self, symbols: list[Column]) -> Column:
        """One code of a table's symbols, lowest first; a hash of them where radix**k does not fit."""
        if self.radix**self.k < 2**62:
            code = F.lit(0).cast("long")
            for j, s in enumerate(symbols):
                code = code + s.cast("long") * F.lit(self.radix**j)
            return code
        return h32(*symbols)


BROADCAST_ROWS = 2_000_000


def small(rows: DataFrame, count: int) -> DataFrame:
    """rows, of at most count small rows, marked for broadcast where that is few; else joined by a shuffle."""
    return F.broadcast(rows) if count <= BROADCAST_ROWS else rows


@dataclass(frozen=True)
class SimHash(HashFamily):
    """Signs of projections on ternary directions; a projection of 0 counts as positive.

    density: share of non-zero coefficients, 1, 2/3 or 1/3 (kept as 6, 4 or 2 of 6).
    """

    sixths: int = 4

    @property
    def radix(self) -> int:
        return 2

    def coefficient(self, fn, idx) -> Column:
        r = h32(self.seed, fn, idx) % 6
        half = self.sixths // 2
        return F.when(r < half, 1).when(r < self.sixths, -1).otherwise(0)

    def direction(self, fn: int) -> list[int]:
        half = self.sixths // 2
        return [1 if r < half else -1 if r < self.sixths else 0 for r in (h32_of(self.seed, fn, i) % 6 for i in range(self.dim))]

    def matrix(self) -> np.ndarray:
        """dim x functions of -1, 0, 1."""
        return np.array([self.direction(f) for f in range(self.functions)], dtype=np.int64).T

    def relation(self, spark: SparkSession) -> DataFrame:
        """fn, idx, coef of the non-zero coefficients, made on the executors."""
        rows = spark.range(self.functions * self.dim).select((F.col("id") / self.dim).cast("int").alias("fn"), (F.col("id") % self.dim).cast("int").alias("idx"))
        return rows.withColumn("coef", self.coefficient(F.col("fn"), F.col("idx"))).where("coef != 0")

    def project(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        """id, fn, s: the projections on the fixed-point grid, kept for update()."""
        q = df.select(F.col(id_col).alias("id"), fixed_point(vec_col).alias("q"))
        sums = F.array(*[self._sum(F.col("q"), self.direction(f)) for f in range(self.functions)])
        return q.select("id", F.posexplode(sums).alias("fn", "s"))

    @staticmethod
    def _sum(q: Column, direction: list[int]) -> Column:
        """Additions and subtractions of the coordinates that the direction names."""
        take = lambda sign: F.aggregate(F.array(*[F.lit(i) for i, c in enumerate(direction) if c == sign] or [F.lit(-1)]), F.lit(0).cast("long"), lambda a, i: a + F.coalesce(F.get(q, i), F.lit(0)))
        return take(1) - take(-1)

    def project_sparse(self, features: DataFrame) -> DataFrame:
        """id, fn, s from features (id, idx, val): only stored coefficients of present features are touched."""
        rel = small(self.relation(features.sparkSession), self.functions * self.dim * self.sixths // 6)
        q = features.withColumn("q", F.floor(F.col("val").cast("double") * GRID).cast("long"))
        return q.join(rel, "idx").groupBy("id", "fn").agg(F.sum(F.col("q") * F.col("coef")).alias("s"))

    @staticmethod
    def update(projections: DataFrame, delta_projections: DataFrame) -> DataFrame:
        """Projections after a change whose own projections are given (grid differences): exact, changed ids alone cost work."""
        d = delta_projections.select(F.col("id").alias("d_id"), F.col("fn").alias("d_fn"), F.col("s").alias("d_s"))
        joined = projections.join(d, (F.col("id") == F.col("d_id")) & (F.col("fn") == F.col("d_fn")), "left")
        return joined.select("id", "fn", (F.col("s") + F.coalesce("d_s", F.lit(0))).alias("s"))

    def codes_of(self, projections: DataFrame) -> DataFrame:
        """id, table_id, code from id, fn, s."""
        bit = F.when(F.col("s") >= 0, F.pow(F.lit(2.0), F.col("fn") % self.k).cast("long")).otherwise(F.lit(0).cast("long"))
        return projections.groupBy("id", (F.col("fn") / self.k).cast("int").alias("table_id")).agg(F.sum(bit).alias("code"))

    def symbols(self, vec: Column) -> Column:
        q = fixed_point(vec)
        dirs = [F.array(*[F.lit(c).cast("long") for c in self.direction(f)]) for f in range(self.functions)]
        return F.transform(F.array(q), lambda x: F.array(*[F.when(long_dot(x, d) >= 0, 1).otherwise(0) for d in dirs]))[0]

    def codes(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        """By one Arrow matrix product a batch: the same codes as by expressions."""
        spark, m, k, tables = df.sparkSession, self.matrix(), self.k, self.tables
        id_type = dict(df.dtypes)[id_col]
        shared = spark.sparkContext.broadcast(m)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            weight = 1 << np.arange(k, dtype=np.int64)
            for b in batches:
                n = b.num_rows
                if n == 0:
                    continue
                x = b.column("v").flatten().to_numpy(zero_copy_only=False).reshape(n, -1)[:, : len(shared.value)]
                bits = np.floor(x.astype(np.float64) * GRID).astype(np.int64) @ shared.value >= 0
                code = bits.reshape(n, tables, k) @ weight
                yield pa.RecordBatch.from_arrays([b.column("id").take(pa.array(np.repeat(np.arange(n), tables))), pa.array(np.tile(np.arange(tables, dtype=np.int32), n)), pa.array(code.ravel())], ["id", "table_id", "code"])

        rows = df.select(F.col(id_col).alias("id"), F.col(vec_col).alias("v")).where("id is not null and v is not null")
        return rows.mapInArrow(run, f"id {id_type}, table_id int, code long")

    def codes_by_expression(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        return HashFamily.codes(self, df, id_col, vec_col)

    def collision_prob(self, similarity: Column) -> Column:
        return collision_simhash(similarity)


@dataclass(frozen=True)
class GaussianHash(HashFamily):
    """Signs of projections on normal directions: the law 1 - angle / pi holds exactly in the mean."""

    @property
    def radix(self) -> int:
        return 2

    def matrix(self) -> np.ndarray:
        u = np.array([[(h32_of(self.seed, f, i, s) + 1) / 2**32 for i in range(self.dim)] for f in range(self.functions) for s in (0, 1)])
        return (np.sqrt(-2 * np.log(np.minimum(u[0::2], 1.0))) * np.cos(2 * math.pi * u[1::2])).T

    def symbols(self, vec: Column) -> Column:
        return F.array(*[F.when(vec_dot(vec, F.array(*[F.lit(float(x)) for x in col])) >= 0, 1).otherwise(0) for col in self.matrix().T])

    def collision_prob(self, similarity: Column) -> Column:
        return collision_simhash(similarity)


@dataclass(frozen=True)
class WTA(HashFamily):
    """Place of the largest of m coordinates in a random order; of equal ones the first."""

    m: int = 8

    @property
    def radix(self) -> int:
        return self.m

    def order(self, fn: int) -> list[int]:
        return sorted(range(self.dim), key=lambda i: (h32_of(self.seed, fn, i), i))[: self.m]

    def symbols(self, vec: Column) -> Column:
        seen = [F.array(*[F.get(vec, F.lit(i)) for i in self.order(f)]) for f in range(self.functions)]
        return F.array(*[F.array_position(x, F.array_max(x)).cast("long") - 1 for x in seen])


@dataclass(frozen=True)
class DWTA(HashFamily):
    """WTA for sparse input: ceil(functions * m / dim) permutations, each cut into bins of m places.

    One pass over the non-zeros keeps each bin's largest value (of equal ones the first place). An empty
    bin borrows from the first filled one in an order of all bins that is its own, so a bin is never left empty; an
    input without non-zeros has code EMPTY in every table.
    """

    m: int = 8

    @property
    def radix(self) -> int:
        return self.m

    @property
    def bins(self) -> int:
        """Bins of one permutation."""
        return max(1, self.dim // self.m)

    @property
    def permutations(self) -> int:
        return -(-self.functions // self.bins)

    def relation(self, spark: SparkSession) -> DataFrame:
        """idx, fn, pos: where each coordinate stands; permutations x dim rows, functions beyond those wanted left out."""
        from pyspark.sql.window import Window

        rows = spark.range(self.permutations * self.dim).select((F.col("id") / self.dim).cast("int").alias("perm"), (F.col("id") % self.dim).cast("int").alias("idx"))
        w = Window.partitionBy("perm").orderBy(h32(self.seed, F.col("perm"), F.col("idx")), "idx")
        rows = rows.withColumn("place", F.row_number().over(w) - 1)
        rows = rows.select("idx", (F.col("perm") * self.bins + (F.col("place") / self.m).cast("int")).alias("fn"), (F.col("place") % self.m).alias("pos"), "place")
        return rows.where((F.col("place") < self.bins * self.m) & (F.col("fn") < self.functions)).drop("place")

    def symbols(self, vec: Column) -> Column:
        raise NotImplementedError("DWTA hashes sparse rows: use codes_sparse")

    def unit(self, fn: int) -> int:
        """Bin b is tried by function fn at turn (b - fn) * unit modulo functions: a permutation, as the unit has no common factor with their number."""
        u = h32_of(self.seed, "probe", fn) % self.functions
        while math.gcd(u, self.functions) != 1:
            u += 1
        return u

    def filled(self, features: DataFrame) -> DataFrame:
        """id, fn, symbol of the bins that hold a non-zero."""
        rel = small(self.relation(features.sparkSession), min(self.permutations * self.dim, self.functions * self.m))
        best = F.max_by("pos", F.struct(F.col("val"), -F.col("pos")))
        return features.where("val != 0").join(rel, "idx").groupBy("id", "fn").agg(best.alias("symbol"))

    def tries(self, features: DataFrame) -> DataFrame:
        """id, tries: how many other bins the empty bins of an input ask before they borrow, for inputs with a filled bin."""
        wanted = F.array(*[F.struct(F.lit(f).alias("fn"), F.lit(self.unit(f)).cast("long").alias("u")) for f in range(self.functions)])
        have = self.filled(features).groupBy("id").agg(F.collect_list("fn").alias("have"))
        turns = F.transform(wanted, lambda f: F.array_min(F.transform("have", lambda b: F.pmod((b - f["fn"]) * f["u"], F.lit(self.functions)))))
        return have.select("id", F.aggregate(turns, F.lit(0).cast("long"), lambda a, x: a + x).alias("tries"))

    def codes_sparse(self, features: DataFrame, densify: bool = True) -> DataFrame:
        """id, table_id, code from features (id, idx, val), with a row for each id that has any row."""
        ids = features.select("id").distinct()
        by_id = self.filled(features).groupBy("id").agg(F.collect_list(F.struct("fn", "symbol")).alias("have"))
        rows = ids.join(by_id, "id", "left")
        wanted = F.array(*[F.struct(F.lit(f).alias("fn"), F.lit(self.unit(f)).cast("long").alias("u")) for f in range(self.functions)])
        if densify:
            turn = lambda f, b: F.struct(F.pmod((b["fn"] - f["fn"]) * f["u"], F.lit(self.functions)).alias("turn"), b["symbol"].alias("symbol"))
            symbols = F.transform(wanted, lambda f: F.array_min(F.transform("have", lambda b: turn(f, b)))["symbol"])
        else:
            symbols = F.transform(wanted, lambda f: F.coalesce(F.array_max(F.transform(F.filter("have", lambda b: b["fn"] == f["fn"]), lambda b: b["symbol"])), F.lit(0)))
        rows = rows.select("id", F.col("have").isNull().alias("nothing"), symbols.alias("s"))
        code = lambda t: F.aggregate(F.sequence(F.lit(0), F.lit(self.k - 1)), F.lit(0).cast("long"), lambda a, j: a + F.get("s", t * self.k + j) * F.pow(F.lit(float(self.m)), j).cast("long"))
        packed = rows.select("id", "nothing", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(self.tables - 1)), lambda t: F.when(~F.col("nothing"), code(t)))).alias("table_id", "code"))
        return packed.select("id", "table_id", F.when(F.col("nothing"), F.lit(EMPTY).cast("long")).otherwise(F.col("code")).alias("code"))


@dataclass(frozen=True)
class MinHash(HashFamily):
    """Smallest hashes of a set under each function; the chance of equality is the Jaccard similarity."""

    one_permutation: bool = False
    tries: int = 3

    @property
    def radix(self) -> int:
        return 1 << 32

    def symbols(self, vec: Column) -> Column:
        """vec: a set as an array (a weight vector's set is its support, see support())."""
        return F.array(*[F.array_min(F.transform(vec, lambda x, f=f: h32(self.seed, f, x))) for f in range(self.functions)])

    def codes_set(self, elements: DataFrame) -> DataFrame:
        """id, table_id, code from elements (id, element): md5 once an element, functions as mixes of it."""
        n = self.functions
        if self.one_permutation:
            h = h32(self.seed, F.col("element"))
            bins = elements.select("id", (h % n).cast("int").alias("fn"), F.floor(h / n).cast("long").alias("v")).groupBy("id", "fn").agg(F.min("v").alias("v"))
            by_id = bins.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("fn", "v"))).alias("have"))
            values = [F.coalesce(F.element_at("have", F.lit(f)), *[F.element_at("have", F.lit(h32_of(self.seed, "probe", f, t) % n)) for t in range(self.tries)], F.lit(-1)) for f in range(n)]
            mins = by_id.select("id", F.array(*values).alias("s"))
        else:
            # (a * h + b) mod 2**31 - 1 with h below 2**31: fits a long
            h = h32(self.seed, F.col("element")) % (2**31 - 1)
            mins = elements.withColumn("h", h).groupBy("id").agg(F.array(*[F.min((F.col("h") * (1 + h32_of(self.seed, "a", f) % (2**31 - 2)) + h32_of(self.seed, "b", f) % (2**31 - 1)) % (2**31 - 1)) for f in range(n)]).alias("s"))
        packed = F.array(*[h32(*[F.get("s", F.lit(t * self.k + j)) for j in range(self.k)]) for t in range(self.tables)])
        return mins.select("id", F.posexplode(packed).alias("table_id", "code"))

    def collision_prob(self, similarity: Column) -> Column:
        return similarity


def support(vec: Column, top: int | None = None) -> Column:
    """Set of a vector for MinHash: places of its non-zeros, or of its top largest values."""
    at = F.transform(vec, lambda x, i: F.struct((-x).alias("v"), i.alias("i")))
    if top is None:
        return F.transform(F.filter(at, lambda s: s["v"] != 0), lambda s: s["i"])
    return F.transform(F.slice(F.sort_array(at), 1, top), lambda s: s["i"])


@dataclass(frozen=True)
class MipsTransform:
    """Inner products as cosines: data are scaled into the unit ball and padded to norm 1, queries get unit norm."""

    family: SimHash  # over dim + 1

    def data(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        """id, v. One aggregate finds the largest norm, on the grid."""
        q = df.select(F.col(id_col).alias("id"), fixed_point(vec_col).alias("q")).withColumn("n2", long_dot("q", "q"))
        top = q.agg(F.max("n2").alias("top"))
        scaled = q.join(F.broadcast(top)).withColumn("m", F.sqrt(F.col("top").cast("double")))
        pad = F.sqrt(F.greatest(F.lit(0.0), 1 - F.col("n2").cast("double") / F.col("top")))
        return scaled.select("id", F.concat(F.transform("q", lambda x: x / F.col("m")), F.array(pad)).alias("v"))

    def query(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        q = df.select(F.col(id_col).alias("id"), fixed_point(vec_col).alias("q")).withColumn("m", F.sqrt(long_dot("q", "q").cast("double")))
        return q.where("m > 0").select("id", F.concat(F.transform("q", lambda x: x / F.col("m")), F.array(F.lit(0.0))).alias("v"))

    def data_codes(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        return self.family.codes(self.data(df, id_col, vec_col), "id", "v")

    def query_codes(self, df: DataFrame, id_col: str, vec_col: str) -> DataFrame:
        return self.family.codes(self.query(df, id_col, vec_col), "id", "v")


FAMILIES: dict[str, type] = {"simhash": SimHash, "gaussian": GaussianHash, "wta": WTA, "dwta": DWTA, "minhash": MinHash}


def register_family(name: str, cls: type) -> None:
    """Makes a user's family known by name to configurations."""
    if not issubclass(cls, HashFamily):
        raise TypeError(f"{cls.__name__} is no HashFamily")
    FAMILIES[name] = cls
