"""Work units of a tiled product and what they cost, without forming any product."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..grid import GridSpec, schedule
from ..matrix import Matrix

#: Bytes of a stored value and of an index in the cost model.
VALUE_BYTES, INDEX_BYTES = 4, 4


def marginals(a: Matrix, b: Matrix, grid: GridSpec) -> tuple[DataFrame, DataFrame]:
    """How many entries of A lie in (tile row, column) and of B in (row, tile column)."""
    left = a.df.groupBy(grid.ti("i").alias("ti"), F.col("j").alias("k")).agg(F.count("*").alias("ca"))
    right = b.df.groupBy(F.col("i").alias("k"), grid.tj("j").alias("tj")).agg(F.count("*").alias("rb"))
    return left, right


def unit_mults(a: Matrix, b: Matrix, grid: GridSpec) -> DataFrame:
    """(ti, tk, tj, mults): multiplications of each unit that has any."""
    left, right = marginals(a, b, grid)
    return (
        left.join(right, "k")
        .groupBy("ti", grid.tk("k").alias("tk"), "tj")
        .agg(F.sum(F.col("ca") * F.col("rb")).cast("long").alias("mults"))
    )


def tile_sizes(a: Matrix, rows: int, cols: int, dense: bool = False) -> DataFrame:
    """(r, c, nnz, bytes) of the tiles that hold any entry; rows × cols is a tile's extent.

    A sparse tile is values, column indices and row pointers; a dense one is its values.
    """
    r = F.call_function("div", F.col("i"), F.lit(rows).cast("long")).cast("int")
    c = F.call_function("div", F.col("j"), F.lit(cols).cast("long")).cast("int")
    nnz = F.count("*")
    size = nnz * VALUE_BYTES if dense else nnz * (VALUE_BYTES + INDEX_BYTES) + (rows + 1) * INDEX_BYTES
    return a.df.groupBy(r.alias("r"), c.alias("c")).agg(nnz.alias("nnz"), size.cast("long").alias("bytes"))


def work_units(a: Matrix, b: Matrix, grid: GridSpec, dense_b: bool = False) -> DataFrame:
    """(ti, tk, tj, mults, bytes_a, bytes_b, bytes_c) of every unit of the cube, idle ones too."""
    spark = a.df.sparkSession
    of_a = tile_sizes(a, grid.tile_m, grid.tile_k).select(F.col("r").alias("ti"), F.col("c").alias("tk"), F.col("bytes").alias("bytes_a"))
    of_b = tile_sizes(b, grid.tile_k, grid.tile_n, dense_b).select(F.col("r").alias("tk"), F.col("c").alias("tj"), F.col("bytes").alias("bytes_b"))
    most_c = grid.tile_m * grid.tile_n
    bytes_c = F.least(F.col("mults"), F.lit(most_c)) * (VALUE_BYTES if dense_b else VALUE_BYTES + INDEX_BYTES)
    zero = {"mults": 0, "bytes_a": 0, "bytes_b": 0}
    return (
        grid.cube(spark)
        .join(unit_mults(a, b, grid), ["ti", "tk", "tj"], "left")
        .join(of_a, ["ti", "tk"], "left")
        .join(of_b, ["tk", "tj"], "left")
        .fillna(zero)
        .select("ti", "tk", "tj", "mults", "bytes_a", "bytes_b", bytes_c.cast("long").alias("bytes_c"))
    )


def dense_work_units(a: Matrix, grid: GridSpec) -> DataFrame:
    """Work units of A times a dense B, from A's tile counts alone: no entry of B is made."""
    of_a = tile_sizes(a, grid.tile_m, grid.tile_k).select(F.col("r").alias("ti"), F.col("c").alias("tk"), "nnz", F.col("bytes").alias("bytes_a"))
    wide = lambda t, extent, size: F.greatest(F.lit(0), F.least(F.lit(extent), F.lit(size) - F.col(t) * extent))
    tall, thick, broad = wide("ti", grid.tile_m, grid.m), wide("tk", grid.tile_k, grid.k), wide("tj", grid.tile_n, grid.n)
    return (
        grid.cube(a.df.sparkSession)
        .join(of_a, ["ti", "tk"], "left")
        .fillna({"nnz": 0, "bytes_a": 0})
        .select(
            "ti", "tk", "tj", (F.col("nnz") * broad).cast("long").alias("mults"), "bytes_a",
            (thick * broad * VALUE_BYTES).cast("long").alias("bytes_b"), (tall * broad * VALUE_BYTES).cast("long").alias("bytes_c"),
        )
    )


def catalogue(a: Matrix, rows: int, cols: int, grid: GridSpec, dense: bool = False) -> DataFrame:
    """The directory of a matrix's tiles: (ti, tk, owner, nnz, bytes, n_pointers)."""
    return tile_sizes(a, rows, cols, dense).select(
        F.col("r").alias("ti"),
        F.col("c").alias("tk"),
        grid.owner("r", "c").alias("owner"),
        "nnz",
        "bytes",
        F.lit(1 if dense else 3).alias("n_pointers"),
    )


def flops(a: Matrix, b: Matrix) -> DataFrame:
    """(mults, flops): a multiplication and an addition for every pair that meets."""
    left = a.df.groupBy(F.col("j").alias("k")).agg(F.count("*").alias("ca"))
    right = b.df.groupBy(F.col("i").alias("k")).agg(F.count("*").alias("rb"))
    mults = F.coalesce(F.sum(F.col("ca") * F.col("rb")), F.lit(0)).cast("long")
    return left.join(right, "k").agg(mults.alias("mults")).select("mults", (F.col("mults") * 2).alias("flops"))


def compression_factor(a: Matrix, b: Matrix, approximate: bool = False, rsd: float = 0.02) -> DataFrame:
    """(mults, nnz, cf): multiplications per entry of the result; approximate by a sketch.

    The exact one counts the packed product's places where they are added up, and moves none.
    """
    if approximate:
        left = a.df.select("i", F.col("j").alias("k"))
        right = b.df.select(F.col("i").alias("k"), "j")
        one = left.join(right, "k").agg(F.count("*").alias("mults"), F.approx_count_distinct(F.struct("i", "j"), rsd).alias("nnz"))
    else:
        from . import panels

        counts = panels.by_panels(a, b, "plus_pair", fold=panels.COUNTS)
        one = counts.agg(*(F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in ("mults", "nnz")))
    return one.select("mults", "nnz", (F.col("mults") / F.col("nnz")).alias("cf"))


def nnz_imbalance(a: Matrix, gm: int = 10, gk: int = 10) -> DataFrame:
    """(nnz, largest, imbalance): largest tile over the average one, empty tiles included."""
    rows, cols = max(1, -(-a.rows // gm)), max(1, -(-a.cols // gk))
    return (
        tile_sizes(a, rows, cols)
        .agg(F.sum("nnz").cast("long").alias("nnz"), F.max("nnz").alias("largest"))
        .select("nnz", "largest", (F.col("largest") * (gm * gk) / F.col("nnz")).alias("imbalance"))
    )


def flop_imbalance(units: DataFrame, grid: GridSpec, stationary: str = "c") -> DataFrame:
    """(total, largest, imbalance) of multiplications by worker, from start to end."""
    by_rank = units.groupBy(_rank(grid, stationary).alias("rank")).agg(F.sum("mults").alias("f"))
    return by_rank.agg(F.sum("f").cast("long").alias("total"), F.max("f").cast("long").alias("largest")).select(
        "total", "largest", (F.col("largest") * grid.workers / F.col("total")).alias("imbalance")
    )


def _rank(grid: GridSpec, stationary: str):
    from ..grid import HOME

    row, col, _ = HOME[stationary]
    return grid.owner(row, col)


def stage_loads(units: DataFrame, grid: GridSpec, stationary: str = "c", offset: bool = True) -> DataFrame:
    """(step, largest, total): multiplications by worker in each step of a schedule."""
    plan = schedule(units.sparkSession, grid, stationary, offset)
    by_rank = plan.join(units, ["ti", "tk", "tj"]).groupBy("step", "rank").agg(F.sum("mults").alias("f"))
    return by_rank.groupBy("step").agg(F.max("f").cast("long").alias("largest"), F.sum("f").cast("long").alias("total"))


def stage_imbalance(units: DataFrame, grid: GridSpec, stationary: str = "c", offset: bool = True) -> DataFrame:
    """(ratio_of_sums, mean_of_ratios): what waiting at every step makes of the imbalance."""
    p = grid.workers
    ratio = F.when(F.col("total") > 0, F.col("largest") * p / F.col("total")).otherwise(1.0)
    return stage_loads(units, grid, stationary, offset).agg(
        (F.sum("largest") * p / F.sum("total")).alias("ratio_of_sums"), F.avg(ratio).alias("mean_of_ratios")
    )


def fetch_collisions(plan: DataFrame) -> DataFrame:
    """(step, most_a, most_b): requests for one tile at one step, at most."""
    of_a = plan.groupBy("step", "ti", "tk").count().groupBy("step").agg(F.max("count").alias("most_a"))
    of_b = plan.groupBy("step", "tk", "tj").count().groupBy("step").agg(F.max("count").alias("most_b"))
    return of_a.join(of_b, "step")


def first_fetch_local(plan: DataFrame) -> DataFrame:
    """Share of the first requests that go to the own worker, for A and for B."""
    local = lambda c: F.avg((F.col(c) == F.col("rank")).cast("double"))
    return plan.where("step = 0").agg(local("src_a").alias("local_a"), local("src_b").alias("local_b"))


def comm_exact(units: DataFrame, grid: GridSpec, stationary: str = "c") -> DataFrame:
    """(rank, units, remote_bytes): bytes of operand tiles that a worker does not own."""
    rank = _rank(grid, stationary)
    remote = F.when(grid.owner("ti", "tk") != rank, F.col("bytes_a")).otherwise(0) + F.when(
        grid.owner("tk", "tj") != rank, F.col("bytes_b")
    ).otherwise(0)
    return units.groupBy(rank.alias("rank")).agg(F.count("*").alias("units"), F.sum(remote).cast("long").alias("remote_bytes"))


#: Units in a chunk of the two-level running total.
CHUNK = 1024


def rebalance(units: DataFrame, slots: int) -> DataFrame:
    """(ti, tk, tj, mults, before, total, pieces): a plan of ``slots`` partitions of nearly equal cost.

    Units stand in order of (ti, tk, tj) and ``before`` is the cost up to a unit; partition s takes
    what lies between s and s + 1 parts of the ``total``. A unit that costs more than a quarter
    of a partition is cut into ``pieces``, which ``part_of`` places. Running totals are
    taken over chunks of units and inside a chunk, so no window holds all units; units without any
    work are left out.
    """
    from pyspark.sql import Window

    some = units.where("mults > 0").select("ti", "tk", "tj", F.col("mults").cast("long").alias("mults"))
    # a chunk is a stretch of the order: units of one (ti, tk) and a stretch of tj
    chunk = F.struct("ti", "tk", F.expr(f"tj div {CHUNK}").alias("c"))
    chunked = some.withColumn("chunk", chunk)
    sums = chunked.groupBy("chunk").agg(F.sum("mults").alias("s"))
    rows = sums.groupBy("chunk.ti").agg(F.sum("s").alias("s"))
    earlier = lambda *by: Window.partitionBy(*by).orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    sum_of = lambda name, w: F.coalesce(F.sum(name).over(w), F.lit(0))
    over_rows = Window.orderBy("ti").rowsBetween(Window.unboundedPreceding, -1)  # one row per row of tiles
    row_base = rows.select("ti", sum_of("s", over_rows).alias("row_base"))
    base = sums.withColumn("ti", F.col("chunk.ti")).join(row_base, "ti").select("chunk", (F.col("row_base") + sum_of("s", earlier("ti"))).alias("base"))
    inside = Window.partitionBy("chunk").orderBy("tj").rowsBetween(Window.unboundedPreceding, -1)
    total = some.agg(F.sum("mults").alias("total"))
    pieces = F.greatest(F.lit(1), F.ceil(F.col("mults") * slots * 4 / F.col("total")))
    return (
        chunked.join(base, "chunk")
        .withColumn("before", F.col("base") + sum_of("mults", inside))
        .join(F.broadcast(total))  # one row
        .select("ti", "tk", "tj", "mults", "before", "total", pieces.cast("long").alias("pieces"))
    )


def part_of(before, mults, piece, pieces, total, slots: int):
    """The partition of one piece of a unit, by whole-number arithmetic on its middle."""
    middle = before + F.call_function("div", (2 * piece + 1) * mults, 2 * pieces)
    return F.least(F.lit(slots - 1), F.call_function("div", middle.cast("decimal(38,0)") * slots, total)).cast("int")


def part_loads(plan: DataFrame, slots: int) -> DataFrame:
    """(part, pieces, mults): what each partition of a ``rebalance`` plan works on."""
    each = plan.withColumn("piece", F.explode(F.sequence(F.lit(0).cast("long"), F.col("pieces") - 1)))
    part = part_of(F.col("before"), F.col("mults"), F.col("piece"), F.col("pieces"), F.col("total"), slots)
    share = F.call_function("div", (F.col("piece") + 1) * F.col("mults"), F.col("pieces")) - F.call_function("div", F.col("piece") * F.col("mults"), F.col("pieces"))
    return each.groupBy(part.alias("part")).agg(F.count("*").alias("pieces"), F.sum(share).cast("long").alias("mults"))
