"""Functions for SQL users where built-in expressions do not reach: kernels over arrays and tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def csr_row_dot(cols: pd.Series, vals: pd.Series, x: pd.Series) -> pd.Series:
    """Product of a sparse row (columns, values) and a dense vector."""
    return pd.Series([float(np.dot(np.asarray(v, float), np.asarray(d, float)[np.asarray(c, int)])) if len(c) else 0.0 for c, v, d in zip(cols, vals, x)])


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(x: pd.Series) -> list:
    """Sum of a group's vectors; for groups of bounded size (see ``add_vectors`` for others)."""
    return np.sum(np.stack([np.asarray(v, float) for v in x]), axis=0).tolist()


def add_vectors(df, key: str, vector: str):
    """Sum of a group's vectors of any number, place by place with map-side sums."""
    long = df.select(key, F.posexplode(vector).alias("pos", "x"))
    sums = long.groupBy(key, "pos").agg(F.sum("x").alias("x"))
    packed = sums.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("pos", "x"))).alias("p"))
    return packed.select(key, F.transform("p", lambda s: s["x"]).alias(vector))


@F.udtf(returnType=T.StructType([T.StructField(n, T.IntegerType()) for n in ("ti", "tk", "tj")]))
class WorkCube:
    """All units of a tile cube."""

    def eval(self, m: int, k: int, n: int) -> Iterator[tuple]:
        for ti in range(m):
            for tk in range(k):
                for tj in range(n):
                    yield ti, tk, tj


@F.udtf(returnType=T.StructType([T.StructField("r", T.IntegerType()), T.StructField("c", T.LongType()), T.StructField("v", T.DoubleType())]))
class Untile:
    """Entries of one CSR tile; ``row_idx`` numbers its rows where empty ones are left out."""

    def eval(self, row_ptr: list, col_idx: list, vals: list, row_idx: list | None = None) -> Iterator[tuple]:
        for n in range(len(row_ptr) - 1):
            r = n if row_idx is None else row_idx[n]
            for at in range(row_ptr[n], row_ptr[n + 1]):
                yield r, col_idx[at], float(vals[at])


def register(spark: SparkSession) -> None:
    """Makes them callable from SQL text: csr_row_dot, vector_sum, work_cube, untile."""
    spark.udf.register("csr_row_dot", csr_row_dot)
    spark.udf.register("vector_sum", vector_sum)
    spark.udtf.register("work_cube", WorkCube)
    spark.udtf.register("untile", Untile)
