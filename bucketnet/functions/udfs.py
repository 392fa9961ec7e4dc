"""SQL names for the library's functions: SQL macros where an expression does, Arrow functions where not."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from bucketnet.functions.vector import GRID
from bucketnet.operators.hashing import SimHash

MACROS = {
    "prob_union": "(p DOUBLE, k INT, l INT) RETURNS DOUBLE RETURN 1 - power(1 - power(p, k), l)",
    "prob_vanilla": "(p DOUBLE, k INT, tau INT) RETURNS DOUBLE RETURN 1 - power(1 - power(p, k), tau)",
    "hash32": "(s STRING) RETURNS BIGINT RETURN cast(conv(substring(md5(s), 1, 8), 16, 10) AS BIGINT)",
    "hamming64": "(a BIGINT, b BIGINT) RETURNS INT RETURN bit_count(a ^ b)",
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
}


@pandas_udf(T.DoubleType())
def logsumexp(z: pd.Series) -> float:
    """Grouped: log of the sum of exponentials."""
    top = z.max()
    return float(top + np.log(np.exp(z - top).sum())) if len(z) else float("nan")


@pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(v: pd.Series) -> list[float]:
    """Grouped: the sum of arrays of one length. A group is one task's work; sum() by element scales further."""
    return np.sum(np.stack(v.to_numpy()), axis=0).tolist()


def simhash_codes_arrow(family: SimHash):
    """An Arrow scalar function array<float> -> array<long> of the family's codes."""
    m, k, tables = family.matrix(), family.k, family.tables

    @arrow_udf("array<long>")
    def codes(v: pa.Array) -> pa.Array:
        x = np.floor(v.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(v), -1) * GRID).astype(np.int64)
        out = (x @ m >= 0).reshape(len(v), tables, k) @ (1 << np.arange(k, dtype=np.int64))
        return pa.array(list(out), pa.list_(pa.int64()))

    return codes


def lsh_codes_udtf(family: SimHash):
    """A table function (vector) -> rows (table_id, code), for LATERAL in SQL."""
    m, k, tables = family.matrix(), family.k, family.tables

    @udtf(returnType="table_id int, code long")
    class Codes:
        def eval(self, vec):
            bits = np.floor(np.array(vec, dtype=np.float64) * GRID).astype(np.int64) @ m >= 0
            for t, c in enumerate(bits.reshape(tables, k) @ (1 << np.arange(k))):
                yield t, int(c)

    return Codes


def register(spark: SparkSession, family: SimHash) -> None:
    """All names for a session: the macros, logsumexp, vector_sum, simhash_codes and lsh_codes."""
    for name, body in MACROS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("logsumexp", logsumexp)
    spark.udf.register("vector_sum", vector_sum)
    spark.udf.register("simhash_codes", simhash_codes_arrow(family))
    spark.udtf.register("lsh_codes", lsh_codes_udtf(family))


def agree(df, family: SimHash, id_col: str, vec_col: str):
    """Rows where the Arrow function and the expressions differ: none."""
    a = df.select(F.col(id_col).alias("id"), F.posexplode(simhash_codes_arrow(family)(F.col(vec_col))).alias("table_id", "code"))
    return a.exceptAll(family.codes_by_expression(df, id_col, vec_col))
