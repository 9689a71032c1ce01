"""Communication volume, arithmetic intensity and rooflines in closed form.

A roof is the smaller of peak and intensity times bandwidth. Columns are computed from a table
of parameters, so a sweep is one DataFrame without a shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values of the measured machine: bytes per second, flops per second.
NET_BANDWIDTH, NODE_BANDWIDTH, PEAK = 3.83e9, 50e9, 16e12
#: Device memory bandwidth is a parameter: the source does not print one.
MEMORY_BANDWIDTH = 900e9


def _root(p: Column) -> Column:
    return F.sqrt(p.cast("double"))


def sparse_tile(rows: Column, cols: Column, density: Column, p: Column) -> Column:
    """Numbers in one CSR tile of √p × √p: values, columns and row pointers."""
    return 2 * density * rows * cols / p + rows / _root(p) + 1


def with_sparse_dense(params: DataFrame, w: int = 4) -> DataFrame:
    """Adds comm_elements, flops, ai_net and ai_local to rows (m, k, n, nnz, p)."""
    m, k, n, p = (F.col(c).cast("double") for c in ("m", "k", "n", "p"))
    d = F.col("nnz") / (m * k)
    a, b, c = sparse_tile(m, k, d, p), k * n / p, m * n / p
    work = 2 * d * m * k * n / (p * _root(p))
    return params.select(
        "*",
        d.alias("density"),
        (a + b).alias("comm_elements"),
        work.alias("flops"),
        (work / (w * (a + b))).alias("ai_net"),
        (work / (w * (a + b + c))).alias("ai_local"),
    )


def with_sparse_sparse(params: DataFrame, w: int = 4, b: int = 12) -> DataFrame:
    """Adds ai_net and ai_local to rows (m, k, n, nnz, p, flops, cf); ``flops`` per unit."""
    m, k, n, p = (F.col(c).cast("double") for c in ("m", "k", "n", "p"))
    d = F.col("nnz") / (m * k)
    moved = sparse_tile(m, k, d, p) + sparse_tile(k, n, d, p)
    return params.select(
        "*",
        (F.col("flops") / (w * moved)).alias("ai_net"),
        (F.col("cf") / ((3 + 2 * F.col("cf")) * b)).alias("ai_local"),
    )


def roofline(intensities: DataFrame, peak: float = PEAK, memory: float = MEMORY_BANDWIDTH, net: float = NET_BANDWIDTH) -> DataFrame:
    """Adds local_roof, net_roof, attainable and bound to rows with ai_net and ai_local."""
    local = F.least(F.lit(peak), F.col("ai_local") * memory)
    network = F.col("ai_net") * net
    return intensities.select(
        "*",
        local.alias("local_roof"),
        network.alias("net_roof"),
        F.least(local, network).alias("attainable"),
        F.when(network < local, "network").otherwise("compute").alias("bound"),
    )


def efficiency(runs: DataFrame, model: DataFrame, on: list[str]) -> DataFrame:
    """Share of the attainable rate that runs (..., rate) reached."""
    return runs.join(model, on).withColumn("fraction", F.col("rate") / F.col("attainable"))


def volume_by_stationary(params: DataFrame) -> DataFrame:
    """(…, c, a, b): elements that move for each stationary operand, of rows (nnz_a, nnz_b, nnz_c, gm, gk, gn)."""
    a, b, c = F.col("nnz_a"), F.col("nnz_b"), F.col("nnz_c")
    return params.select(
        "*",
        (F.col("gn") * a + F.col("gm") * b).alias("move_c"),
        (F.col("gm") * b + F.col("gk") * c).alias("move_a"),
        (F.col("gn") * a + F.col("gk") * c).alias("move_b"),
    )


def parameters(spark: SparkSession, rows: list[tuple], ddl: str) -> DataFrame:
    return spark.createDataFrame(rows, ddl)
