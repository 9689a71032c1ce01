"""Regular tile grids, tile owners and visiting schedules."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridSpec:
    """Tiles of C (m×n) in gm×gn, of A (m×k) in gm×gk and of B (k×n) in gk×gn.

    ``pr`` × ``pc`` workers hold tiles in block-cyclic order. All tiles of a dimension have
    the same extent except the last one.
    """

    m: int
    k: int
    n: int
    gm: int
    gk: int
    gn: int
    pr: int = 1
    pc: int = 1

    def __post_init__(self) -> None:
        if min(self.gm, self.gk, self.gn, self.pr, self.pc) < 1:
            raise ValueError("a grid has at least one tile and one worker in each dimension")

    @classmethod
    def regular(cls, m: int, k: int, n: int, gm: int, gk: int, gn: int, pr: int | None = None, pc: int | None = None) -> GridSpec:
        return cls(m, k, n, gm, gk, gn, pr or gm, pc or gn)

    @classmethod
    def for_workers(cls, m: int, k: int, n: int, p: int) -> GridSpec:
        """The grid of p workers that is as near to square as p's divisors allow."""
        rows = max(d for d in range(1, math.isqrt(p) + 1) if p % d == 0)
        side = max(rows, p // rows)
        return cls(m, k, n, rows, side, p // rows, rows, p // rows)

    @classmethod
    def layout_1d(cls, m: int, k: int, n: int, p: int) -> GridSpec:
        """Rows of A and C are dealt out; B goes to every worker that needs it."""
        return cls(m, k, n, p, 1, 1, p, 1)

    @property
    def workers(self) -> int:
        return self.pr * self.pc

    @property
    def square(self) -> bool:
        return self.pr == self.pc

    @staticmethod
    def _extent(size: int, tiles: int) -> int:
        return max(1, -(-size // tiles))

    @property
    def tile_m(self) -> int:
        return self._extent(self.m, self.gm)

    @property
    def tile_k(self) -> int:
        return self._extent(self.k, self.gk)

    @property
    def tile_n(self) -> int:
        return self._extent(self.n, self.gn)

    def ti(self, i: str | Column = "i") -> Column:
        return _tile(i, self.tile_m)

    def tk(self, k: str | Column = "k") -> Column:
        return _tile(k, self.tile_k)

    def tj(self, j: str | Column = "j") -> Column:
        return _tile(j, self.tile_n)

    def owner(self, row: str | Column, col: str | Column) -> Column:
        """The worker that holds tile (row, col) of any of the three matrices, as an int."""
        row, col = _column(row), _column(col)
        return (F.pmod(row, F.lit(self.pr)) * self.pc + F.pmod(col, F.lit(self.pc))).cast("int")

    def owner_of(self, row: int, col: int) -> int:
        return row % self.pr * self.pc + col % self.pc

    def cube(self, spark: SparkSession) -> DataFrame:
        """All (ti, tk, tj) as ints: made from one range, not from a cross join."""
        size = self.gm * self.gk * self.gn
        x = F.col("id")
        return spark.range(size).select(
            F.expr(f"int(id div {self.gk * self.gn})").alias("ti"),
            F.pmod(F.expr(f"id div {self.gn}"), F.lit(self.gk)).cast("int").alias("tk"),
            F.pmod(x, F.lit(self.gn)).cast("int").alias("tj"),
        )


def _column(c: str | Column) -> Column:
    return F.col(c) if isinstance(c, str) else c


def _tile(index: str | Column, extent: int) -> Column:
    """Index divided by a tile's extent in whole numbers, never through floating point."""
    return F.call_function("div", _column(index).cast("long"), F.lit(extent).cast("long")).cast("int")


#: Stationary operand -> (row tile, column tile, moving index) of a work unit.
HOME = {"c": ("ti", "tj", "tk"), "a": ("ti", "tk", "tj"), "b": ("tk", "tj", "ti")}


def schedule(spark: SparkSession, grid: GridSpec, stationary: str = "c", offset: bool = True) -> DataFrame:
    """(rank, step, ti, tk, tj, src_a, src_b): who works on which unit at which step.

    A worker goes through its stationary tiles; inside a tile the moving index starts at the
    sum of the tile's two indices where ``offset`` is set, so that a row or column of workers
    asks for different tiles at one time.
    """
    row, col, moving = HOME[stationary]
    many = {"ti": grid.gm, "tk": grid.gk, "tj": grid.gn}[moving]
    start = F.col(row) + F.col(col) if offset else F.lit(0)
    return grid.cube(spark).select(
        grid.owner(row, col).alias("rank"),
        F.pmod(F.col(moving) - start, F.lit(many)).cast("int").alias("step"),
        "ti",
        "tk",
        "tj",
        grid.owner("ti", "tk").alias("src_a"),
        grid.owner("tk", "tj").alias("src_b"),
    )
