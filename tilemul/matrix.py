"""Matrices as DataFrames of their stored entries."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Matrix:
    """Entries (i LONG, j LONG, v), unique on (i, j), of a ``rows`` × ``cols`` matrix.

    Absent entries are the semiring's zero; stored zeros count as entries. A dense operand is
    the same table with an entry everywhere. Instances never change: every operation returns
    a new one with a lazy DataFrame.
    """

    df: DataFrame
    rows: int
    cols: int
    #: Values at (rows, columns) of a dense operand made by rule, from index arrays; no operation keeps it.
    rule: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None
    #: Whether entries of near rows lie together in ``df``'s partitions, in runs; no operation keeps it.
    placed: bool = False

    @classmethod
    def of(cls, df: DataFrame, rows: int | None = None, cols: int | None = None, i: str = "i", j: str = "j", v: str = "v", combine: bool = False) -> Matrix:
        """A matrix from any columns; ``combine`` adds up repeated places.

        Dimensions that are not given are the largest index plus one (one aggregation).
        """
        entries = df.select(F.col(i).cast("long").alias("i"), F.col(j).cast("long").alias("j"), F.col(v).alias("v"))
        if combine:
            entries = entries.groupBy("i", "j").agg(F.sum("v").alias("v"))
        if rows is None or cols is None:
            top = entries.agg(F.max("i"), F.max("j")).first()
            rows = rows if rows is not None else (top[0] + 1 if top[0] is not None else 0)
            cols = cols if cols is not None else (top[1] + 1 if top[1] is not None else 0)
        return cls(entries, rows, cols)

    def with_df(self, df: DataFrame, rows: int | None = None, cols: int | None = None) -> Matrix:
        return replace(self, df=df, rows=self.rows if rows is None else rows, cols=self.cols if cols is None else cols, rule=None, placed=False)

    def validate(self) -> Matrix:
        """Raises on null or out-of-range indices, null values or repeated places."""
        bad = self.df.agg(
            F.count_if(F.col("i").isNull() | F.col("j").isNull() | F.col("v").isNull()).alias("nulls"),
            F.count_if(
                (F.col("i") < 0) | (F.col("j") < 0) | (F.col("i") >= self.rows) | (F.col("j") >= self.cols)
            ).alias("outside"),
            F.count("*").alias("n"),
        ).first()
        if bad["nulls"]:
            raise ValueError(f"{bad['nulls']} entries with a null index or value")
        if bad["outside"]:
            raise ValueError(f"{bad['outside']} entries outside {self.rows} x {self.cols}")
        twice = self.df.groupBy("i", "j").count().where("count > 1").limit(1).count()
        if twice:
            raise ValueError("places with more than one entry")
        return self

    # elementwise and structural operations, all narrow unless said otherwise

    def map_values(self, change) -> Matrix:
        return self.with_df(self.df.select("i", "j", change(F.col("v")).alias("v")))

    def scale(self, factor: float | int) -> Matrix:
        return self.map_values(lambda v: v * factor)

    def pattern(self) -> Matrix:
        return self.map_values(lambda v: F.lit(1).cast("long"))

    def relu(self) -> Matrix:
        return self.map_values(lambda v: F.greatest(v, v * 0))

    def drop_zeros(self) -> Matrix:
        return self.where(F.col("v") != 0)

    def threshold(self, least: float | int) -> Matrix:
        return self.where(F.col("v") >= least)

    def where(self, condition: Column) -> Matrix:
        return self.with_df(self.df.where(condition))

    def transpose(self) -> Matrix:
        return self.with_df(self.df.select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), self.cols, self.rows)

    def diagonal(self) -> Matrix:
        return self.where(F.col("i") == F.col("j"))

    def tril(self, strict: bool = True) -> Matrix:
        return self.where(F.col("j") < F.col("i") if strict else F.col("j") <= F.col("i"))

    def triu(self, strict: bool = True) -> Matrix:
        return self.where(F.col("j") > F.col("i") if strict else F.col("j") >= F.col("i"))

    def slice(self, rows: tuple[int, int], cols: tuple[int, int]) -> Matrix:
        """Entries with rows[0] <= i < rows[1] and so for columns; indices stay as they are."""
        i, j = F.col("i"), F.col("j")
        return self.where((i >= rows[0]) & (i < rows[1]) & (j >= cols[0]) & (j < cols[1]))

    def select_rows(self, ids: DataFrame) -> Matrix:
        """Rows whose index is in the first column of ``ids`` (semi-join)."""
        return self.with_df(self.df.join(ids.select(F.col(ids.columns[0]).alias("i")), "i", "left_semi"))

    def add(self, other: Matrix, sign: int = 1) -> Matrix:
        """Entrywise sum: a union added up, with map-side sums, no join."""
        self._same_shape(other)
        both = self.df.unionByName(other.df.select("i", "j", (F.col("v") * sign).alias("v")))
        return self.with_df(both.groupBy("i", "j").agg(F.sum("v").alias("v")))

    def subtract(self, other: Matrix) -> Matrix:
        return self.add(other, -1)

    def hadamard(self, other: Matrix) -> Matrix:
        self._same_shape(other)
        right = other.df.withColumnRenamed("v", "w")
        return self.with_df(self.df.join(right, ["i", "j"]).select("i", "j", (F.col("v") * F.col("w")).alias("v")))

    def divide(self, other: Matrix) -> Matrix:
        self._same_shape(other)
        right = other.df.withColumnRenamed("v", "w")
        return self.with_df(self.df.join(right, ["i", "j"]).select("i", "j", (F.col("v") / F.col("w")).alias("v")))

    def add_self_loops(self) -> Matrix:
        ones = self.df.sparkSession.range(min(self.rows, self.cols)).select(
            F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1).alias("v")
        )
        return self.add(self.with_df(ones))

    def symmetrise(self) -> Matrix:
        return self.add(self.transpose())

    def row_sums(self) -> DataFrame:
        return self.df.groupBy("i").agg(F.sum("v").alias("s"), F.count("*").alias("degree"))

    def col_sums(self) -> DataFrame:
        return self.df.groupBy("j").agg(F.sum("v").alias("s"), F.count("*").alias("degree"))

    def normalize(self, mode: str = "row") -> Matrix:
        """Row- or column-stochastic, or symmetric by both roots of the row sums."""
        v = F.col("v").cast("double")
        if mode == "row":
            df = self.df.join(self.row_sums().select("i", "s"), "i").select("i", "j", (v / F.col("s")).alias("v"))
        elif mode == "column":
            df = self.df.join(self.col_sums().select("j", "s"), "j").select("i", "j", (v / F.col("s")).alias("v"))
        elif mode == "symmetric":
            sums = self.row_sums()
            df = (
                self.df.join(sums.select("i", F.col("s").alias("si")), "i")
                .join(sums.select(F.col("i").alias("j"), F.col("s").alias("sj")), "j")
                .select("i", "j", (v / F.sqrt("si") / F.sqrt("sj")).alias("v"))
            )
        else:
            raise ValueError(f"no normalization {mode!r}")
        return self.with_df(df)

    def nnz(self) -> int:
        return self.df.count()

    def _same_shape(self, other: Matrix) -> None:
        if (self.rows, self.cols) != (other.rows, other.cols):
            raise ValueError(f"{self.rows}x{self.cols} against {other.rows}x{other.cols}")


def identity(spark, n: int) -> Matrix:
    df = spark.range(n).select(F.col("id").alias("i"), F.col("id").alias("j"), F.lit(1).cast("long").alias("v"))
    return Matrix(df, n, n)
