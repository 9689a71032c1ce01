"""Learning and block iterative methods on the sparse-times-dense kernel."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..matrix import Matrix
from ..operators import panels, products
from ..session import materialise


def dense_to_matrix(spark, x: np.ndarray) -> Matrix:
    """A small dense matrix of the driver as entries (both sides bounded by a block's width)."""
    rows, cols = x.shape
    cells = pd.DataFrame({"i": np.repeat(np.arange(rows), cols), "j": np.tile(np.arange(cols), rows), "v": x.ravel()})
    return Matrix(spark.createDataFrame(cells, "i long, j long, v double"), rows, cols)


def narrow_product(x: Matrix, w: np.ndarray) -> Matrix:
    """A tall matrix times a small one: each row's entries meet in one place, no exchange of W."""
    small = dense_to_matrix(x.df.sparkSession, w)
    return Matrix(
        x.df.join(F.broadcast(small.df.select(F.col("i").alias("j"), F.col("j").alias("o"), F.col("v").alias("w"))), "j")
        .groupBy("i", F.col("o").alias("j"))
        .agg(F.sum(F.col("v") * F.col("w")).alias("v")),
        x.rows,
        w.shape[1],
    )


def propagate(a: Matrix, h: Matrix, weights: list[np.ndarray], relu: bool = True) -> Matrix:
    """Layers of graph propagation: H becomes the activation of Â·H·W, Â normalized with loops.

    The roots of the degrees scale the narrow side before and after the product, and the loops add it as it is,
    so the graph stays a pattern of bits of places and is never normalized itself.
    """
    graph = a.pattern()
    if len(weights) > 1:
        graph = graph.with_df(materialise(graph.df))
    nodes = a.df.sparkSession.range(min(a.rows, a.cols)).select(F.col("id").alias("i"))
    degrees = nodes.join(graph.row_sums().select("i", "s"), "i", "left")
    roots = materialise(degrees.select("i", (1 / F.sqrt(F.coalesce("s", F.lit(0)) + 1)).alias("root")))

    def scaled(x: DataFrame) -> DataFrame:
        return x.join(roots, "i").select("i", "j", (F.col("v") * F.col("root")).alias("v"))

    def spread(x: Matrix) -> Matrix:
        y = x.with_df(materialise(scaled(x.df)))
        met = panels.by_panels(graph, y).df.unionByName(y.df)
        return Matrix(scaled(met.groupBy("i", "j").agg(F.sum("v").alias("v"))), a.rows, x.cols)

    for n, w in enumerate(weights):
        # the narrower side first: H·W before Â where W shrinks H
        h = spread(narrow_product(h, w)) if w.shape[1] <= w.shape[0] else narrow_product(spread(h), w)
        if relu and n < len(weights) - 1:
            h = h.relu()
    return h


def gram(x: Matrix, y: Matrix | None = None) -> np.ndarray:
    """Xᵀ·Y on the driver: a block's width squared, whatever the number of rows."""
    y = y or x
    left, right = x.df, y.df.select("i", F.col("j").alias("l"), F.col("v").alias("w"))
    out = np.zeros((x.cols, y.cols))
    for r in left.join(right, "i").groupBy("j", "l").agg(F.sum(F.col("v") * F.col("w")).alias("g")).collect():
        out[r["j"], r["l"]] = r["g"]
    return out


def subspace(a: Matrix, width: int, rounds: int = 20, tol: float = 1e-8, seed: int = 0) -> tuple[np.ndarray, Matrix]:
    """Largest eigenvalues and vectors of a symmetric matrix by block power iteration.

    Orthonormal columns come from the Cholesky factor of the block's Gram matrix.
    """
    spark = a.df.sparkSession
    start = spark.range(a.rows).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(width - 1).cast("long"))).alias("j"))
    x = Matrix(start.select("i", "j", (F.pmod(F.xxhash64("i", "j", F.lit(seed)), F.lit(2001)) / 1000.0 - 1.0).alias("v")), a.rows, width)
    a = a.with_df(materialise(a.df))
    values = np.zeros(width)
    for _ in range(rounds):
        g = gram(x)
        x = narrow_product(x, np.linalg.inv(np.linalg.cholesky(g + 1e-12 * np.trace(g) * np.eye(width))).T)
        x = x.with_df(materialise(x.df))
        y = products.plain(a, x)
        y = y.with_df(materialise(y.df))
        ritz, turn = np.linalg.eigh((lambda s: (s + s.T) / 2)(gram(x, y)))
        order = np.argsort(-np.abs(ritz))
        fresh = ritz[order]
        q, x = narrow_product(x, turn[:, order]), y
        if np.max(np.abs(fresh - values)) <= tol * max(1.0, np.max(np.abs(fresh))):
            values = fresh
            break
        values = fresh
    return values, q


def nmf_update(a: Matrix, w: Matrix, h: Matrix, rounds: int = 1) -> tuple[Matrix, Matrix]:
    """Multiplicative updates of A ≈ W·Hᵀ for nonnegative W (m×r) and H (k×r)."""
    a = a.with_df(materialise(a.df))
    for _ in range(rounds):
        top = products.plain(a.transpose(), w)
        h = _ratio(h, top, narrow_product(h, gram(w)))
        top = products.plain(a, h)
        w = _ratio(w, top, narrow_product(w, gram(h)))
        w, h = w.with_df(materialise(w.df)), h.with_df(materialise(h.df))
    return w, h


def _ratio(x: Matrix, top: Matrix, bottom: Matrix) -> Matrix:
    t, b = top.df.withColumnRenamed("v", "t"), bottom.df.withColumnRenamed("v", "b")
    fresh = x.df.join(t, ["i", "j"], "left").join(b, ["i", "j"], "left")
    return x.with_df(fresh.select("i", "j", (F.col("v") * F.coalesce("t", F.lit(0.0)) / (F.coalesce("b", F.lit(0.0)) + 1e-12)).alias("v")))


def nmf_products(a: Matrix, w: Matrix, h: Matrix) -> DataFrame:
    """(side, i, j, v): both sparse-times-dense products of one update, Aᵀ·W and A·H."""
    down = products.plain(a.transpose(), w).df.select(F.lit("atw").alias("side"), "i", "j", "v")
    across = products.plain(a, h).df.select(F.lit("ah").alias("side"), "i", "j", "v")
    return down.unionByName(across)
