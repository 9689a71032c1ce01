"""Which operand stays where it is, on which grid, and rewrites before Spark plans."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import functions as F

from ..grid import GridSpec
from ..matrix import Matrix
from ..operators import products


@dataclass(frozen=True)
class Stats:
    rows: int
    cols: int
    entries: int

    @classmethod
    def of(cls, a: Matrix) -> Stats:
        return cls(a.rows, a.cols, a.nnz())


@dataclass(frozen=True)
class StrategyPlan:
    stationary: str
    grid: GridSpec
    moved: dict[str, int]
    reason: str

    def explain(self) -> str:
        volumes = ", ".join(f"{s}: {v:,}" for s, v in sorted(self.moved.items()))
        g = self.grid
        return f"stationary {self.stationary.upper()} on {g.gm}x{g.gk}x{g.gn} tiles ({self.reason}); entries moved {volumes}"


#: Entries of operands and result that one worker's partition is to hold, and workers at least and at most.
ENTRIES_PER_WORKER, LEAST_WORKERS, MOST_WORKERS = 2_000_000, 8, 1 << 20


def choose_workers(a: Stats, b: Stats, entries_c: int | None = None) -> int:
    """Workers for a product: entries of A, B and a bounded C over what one worker is to hold.

    A power of four, so that the grid is square and its traffic least.
    """
    entries_c = min(a.rows * b.cols, 16 * (a.entries + b.entries)) if entries_c is None else entries_c
    wanted = -(-(a.entries + b.entries + entries_c) // ENTRIES_PER_WORKER)
    workers = 1
    while workers < min(wanted, MOST_WORKERS):
        workers *= 4
    return max(LEAST_WORKERS, workers)


def choose_grid(a: Stats, b: Stats, workers: int) -> GridSpec:
    """Rows × columns of workers with least traffic for a stationary C: gn·|A| + gm·|B|."""
    sides = [(d, workers // d) for d in range(1, workers + 1) if workers % d == 0]
    gm, gn = min(sides, key=lambda s: (s[1] * a.entries + s[0] * b.entries, abs(s[0] - s[1])))
    return GridSpec(a.rows, a.cols, b.cols, gm, max(gm, gn), gn, gm, gn)


def choose_strategy(a: Stats, b: Stats, workers: int, entries_c: int | None = None) -> StrategyPlan:
    """The largest matrix stays; ties go to C, which needs no accumulation.

    C is taken as dense where B is, else bounded by its size. A stationary B never moves less
    than a stationary C where B and C are equally large, so it needs B to be the largest.
    """
    entries_c = entries_c if entries_c is not None else a.rows * b.cols
    side = max(1, math.isqrt(workers))
    moved = {
        "c": side * (a.entries + b.entries),
        "a": side * (b.entries + entries_c),
        "b": side * (a.entries + entries_c),
    }
    best = min(("c", "a", "b"), key=lambda s: (moved[s], "cab".index(s)))
    largest = {"c": "C is the largest or ties", "a": "A is the largest", "b": "B is the largest"}[best]
    grid = choose_grid(a, b, workers) if best == "c" else GridSpec.for_workers(a.rows, a.cols, b.cols, workers)
    return StrategyPlan(best, grid, moved, largest)


def multiply(a: Matrix, b: Matrix, strategy: str = "auto", grid: GridSpec | None = None, workers: int | None = None, ring: str = "plus_times", mask: Matrix | None = None) -> Matrix:
    """C = A·B by a named strategy, or by the planner's.

    ``strategy``: auto, plain, c, a, b, 1d, 3d, balanced, lockstep-c, lockstep-a or lockstep-b. A
    ``mask`` keeps only its places and is pushed below the sum. Without ``workers`` or a grid
    their number follows from the operands' entries (one count of each).
    """
    products.check_shapes(a, b)
    if mask is not None:
        return products.masked(a, b, mask, ring)
    if strategy == "plain":
        return products.plain(a, b, ring)
    stats = (Stats.of(a), Stats.of(b)) if strategy == "auto" or (workers is None and grid is None) else None
    workers = workers or (choose_workers(*stats) if stats else grid.workers)
    if strategy == "1d":
        return products.layout_1d(a, b, workers, ring)
    if strategy == "auto":
        plan = choose_strategy(*stats, workers)
        strategy, grid = plan.stationary, grid or plan.grid
    grid = grid or GridSpec.for_workers(a.rows, a.cols, b.cols, workers)
    if strategy.startswith("lockstep-"):
        return products.lockstep(a, b, grid, strategy[-1], ring)
    if strategy == "balanced":
        return products.balanced(a, b, grid, 4 * grid.workers, ring)
    runs = {
        "c": products.stationary_c,
        "a": products.stationary_a,
        "b": products.stationary_b,
        "3d": products.layout_3d,
    }
    if strategy not in runs:
        raise ValueError(f"no strategy {strategy!r}")
    return runs[strategy](a, b, grid, ring=ring)


def multiply_slice(a: Matrix, b: Matrix, rows: tuple[int, int], cols: tuple[int, int], **options) -> Matrix:
    """A block of C: its rows select rows of A, its columns columns of B, before the product."""
    left = a.slice(rows, (0, a.cols))
    right = b.slice((0, b.rows), cols)
    return multiply(left, products.needed_rows(left, right), **options)


def chain(a: Matrix, b: Matrix, x: Matrix, **options) -> Matrix:
    """A·B·X in the order of fewer multiplications, estimated from entry counts."""
    na, nb, nx = a.nnz(), b.nnz(), x.nnz()
    left_first = na * nb / max(1, a.cols) + min(a.rows * b.cols, na * nb / max(1, a.cols)) * nx / max(1, b.cols)
    right_first = nb * nx / max(1, b.cols) + na * min(b.rows * x.cols, nb * nx / max(1, b.cols)) / max(1, a.cols)
    if right_first <= left_first:
        return multiply(a, multiply(b, x, **options), **options)
    return multiply(multiply(a, b, **options), x, **options)


def estimated_entries(a: Matrix, b: Matrix) -> int:
    """Upper bound on entries of A·B: multiplications, or the size of C."""
    left = a.df.groupBy(F.col("j").alias("k")).agg(F.count("*").alias("ca"))
    right = b.df.groupBy(F.col("i").alias("k")).agg(F.count("*").alias("rb"))
    mults = left.join(right, "k").agg(F.sum(F.col("ca") * F.col("rb"))).first()[0] or 0
    return min(int(mults), a.rows * b.cols)
