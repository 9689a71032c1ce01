"""Matrices as rows of CSR tiles: packing, fetching, replacing, and tile-wise products."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels
from ..grid import GridSpec
from ..matrix import Matrix
from ..session import materialise

#: ``row_idx`` numbers the rows that ``row_ptr`` is about, where more than half the rows of a tile are empty; else null: all of them.
TILE_DDL = "ti int, tk int, nrows int, ncols int, row_ptr array<long>, col_idx array<long>, vals array<{0}>, row_idx array<long>"
#: Entries packed at once, as whole tiles; a tile of more is packed alone.
AT_ONCE = 1 << 17
#: Tiles replaced at once whose keys are broadcast.
BROADCAST_TILES = 1 << 14
#: Products of a pair of tiles that are expanded at once, as whole rows of A.
PRODUCTS = 1 << 19


@dataclass(frozen=True)
class Tiled:
    """Tiles of a rows × cols matrix with tiles of ``tile_rows`` × ``tile_cols``."""

    df: DataFrame
    rows: int
    cols: int
    tile_rows: int
    tile_cols: int
    #: The table that was packed from entries, and how to pack only those of some tiles.
    packed_from: tuple[DataFrame, Callable[[int, int], DataFrame]] | None = field(default=None, compare=False)

    @property
    def value_type(self) -> str:
        return self.df.schema["vals"].dataType.elementType.simpleString()

    def get(self, ti: int, tk: int) -> DataFrame:
        """One tile, as a lazy one-row table; pruned to its folder where stored by ``ti``, else packed alone."""
        if self.packed_from and self.packed_from[0] is self.df:
            return self.packed_from[1](ti, tk)
        return self.df.where((F.col("ti") == ti) & (F.col("tk") == tk))

    def get_async(self, ti: int, tk: int) -> Future:
        """One tile as a future of its row, fetched by a thread of the driver."""
        return _POOL.submit(lambda: self.get(ti, tk).first())

    def mine(self, rank: int, grid: GridSpec) -> DataFrame:
        """The tiles that one worker owns."""
        return self.df.where(grid.owner("ti", "tk") == rank)

    def replace(self, new: DataFrame, rank: int | None = None, grid: GridSpec | None = None) -> Tiled:
        """A new version with tiles replaced or added; with ``rank`` only by their owner."""
        if rank is not None and new.where(grid.owner("ti", "tk") != rank).limit(1).count():
            raise PermissionError(f"worker {rank} does not own all of these tiles")
        new = materialise(new)
        keys = new.select("ti", "tk")
        if new.count() <= BROADCAST_TILES:  # the tiles that stay are not moved
            keys = F.broadcast(keys)
        kept = self.df.join(keys, ["ti", "tk"], "left_anti")
        return replace(self, df=kept.unionByName(new))

    def renew(self) -> Tiled:
        """The version that all later readers share: written once, read from there."""
        return replace(self, df=materialise(self.df))


_POOL = ThreadPoolExecutor(max_workers=4, thread_name_prefix="tile")


_ARROW = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "float": pa.float32()}

#: What a kernel needs of a tile.
_CELLS = ("row_ptr", "col_idx", "vals", "row_idx", "nrows", "ncols")


def to_tiles(a: Matrix, tile_rows: int, tile_cols: int) -> Tiled:
    """CSR tiles: one shuffle, many tiles packed at once in time linear in their sorted entries.

    A tile takes no more room than its entries: rows without any are left out where they are the most.
    """
    row = F.call_function("div", F.col("i"), F.lit(tile_rows).cast("long")).cast("int")
    col = F.call_function("div", F.col("j"), F.lit(tile_cols).cast("long")).cast("int")
    kind = a.df.schema["v"].dataType.simpleString()
    rows, cols, values = a.rows, a.cols, _ARROW[kind]
    entries = a.df.select(row.alias("ti"), col.alias("tk"), (F.col("i") % tile_rows).alias("r"), (F.col("j") % tile_cols).alias("c"), "v")

    def tiles(held: list[list[np.ndarray]]) -> pa.RecordBatch:
        ti, tk, r, c, v = (np.concatenate(x) for x in zip(*held))
        fresh = np.r_[True, (ti[1:] != ti[:-1]) | (tk[1:] != tk[:-1])]
        first = np.flatnonzero(fresh)
        filled_at = np.flatnonzero(fresh | np.r_[True, r[1:] != r[:-1]])
        of = np.searchsorted(first, filled_at, "right") - 1
        filled = np.bincount(of, minlength=len(first))
        nrows = np.minimum(tile_rows, rows - ti[first].astype(np.int64) * tile_rows)
        ncols = np.minimum(tile_cols, cols - tk[first].astype(np.int64) * tile_cols)
        sparse = 2 * filled < nrows
        ends = lambda many: np.r_[0, np.cumsum(many)]
        # a slot for the start of each tile and one for each of its rows, with the row's number of entries
        width = np.where(sparse, filled, nrows) + 1
        slots = ends(width)
        many = np.zeros(slots[-1], np.int64)
        place = np.where(sparse[of], np.arange(len(of)) - ends(filled)[of], r[filled_at])
        many[slots[of] + 1 + place] = np.diff(np.r_[filled_at, len(r)])
        before = np.cumsum(many)
        row_ptr = before - np.repeat(before[slots[:-1]], width)
        cells = np.r_[first, len(r)]
        lists = lambda at, x: pa.ListArray.from_arrays(pa.array(at, pa.int32()), x)
        row_idx = pa.ListArray.from_arrays(
            pa.array(ends(np.where(sparse, filled, 0)), pa.int32()), pa.array(r[filled_at][sparse[of]], pa.int64()), mask=pa.array(~sparse)
        )
        heads = [pa.array(x, pa.int32()) for x in (ti[first], tk[first], nrows, ncols)]
        lasts = [lists(slots, pa.array(row_ptr, pa.int64())), lists(cells, pa.array(c, pa.int64())), lists(cells, pa.array(v, values)), row_idx]
        return pa.RecordBatch.from_arrays([*heads, *lasts], ["ti", "tk", "nrows", "ncols", "row_ptr", "col_idx", "vals", "row_idx"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append([batch.column(k).to_numpy(zero_copy_only=False) for k in range(5)])
            n += batch.num_rows
            ti, tk = held[-1][:2]
            if n < AT_ONCE or (ti[-1], tk[-1]) == (held[0][0][0], held[0][1][0]):
                continue
            # the last tile may go on in the next batch
            other = np.flatnonzero((ti != ti[-1]) | (tk != tk[-1]))
            at = int(other[-1]) + 1 if len(other) else 0
            back = len(held) - 1
            while at == 0 and back > 0:
                back -= 1
                ti, tk = held[back][:2]
                other = np.flatnonzero((ti != held[-1][0][-1]) | (tk != held[-1][1][-1]))
                at = int(other[-1]) + 1 if len(other) else 0
            done = held[:back] + [[x[:at] for x in held[back]]]
            held = [x for x in ([y[at:] for y in held[back]], *held[back + 1 :]) if len(x[0])]
            n = sum(len(x[0]) for x in held)
            yield tiles(done)
        if held:
            yield tiles(held)

    def pack(some: DataFrame) -> DataFrame:
        return some.repartition("ti", "tk").sortWithinPartitions("ti", "tk", "r", "c").mapInArrow(run, TILE_DDL.format(kind))

    df = pack(entries)
    one = lambda ti, tk: pack(entries.where((F.col("ti") == ti) & (F.col("tk") == tk)))
    return Tiled(df, a.rows, a.cols, tile_rows, tile_cols, (df, one))


def _csr(batch: pa.RecordBatch, n: int, side: str) -> kernels.Csr:
    """One side of a joined row as a tile with a pointer to each of its rows."""
    take = lambda c: batch.column(f"{side}_{c}")[n].values.to_numpy(zero_copy_only=False)
    row_ptr = take("row_ptr")
    if batch.column(f"{side}_row_idx")[n].is_valid:
        many = np.zeros(batch.column(f"{side}_nrows")[n].as_py() + 1, np.int64)
        many[take("row_idx") + 1] = np.diff(row_ptr)
        row_ptr = np.cumsum(many)
    return kernels.Csr(row_ptr, take("col_idx"), take("vals"), batch.column(f"{side}_ncols")[n].as_py())


def _slabs(a: kernels.Csr, b: kernels.Csr) -> Iterator[tuple[int, kernels.Csr]]:
    """``a`` in runs of rows that make up to ``PRODUCTS`` products with ``b``, or are one row; each with its first row."""
    made = np.r_[0, np.cumsum(np.diff(b.row_ptr)[a.col_idx])][a.row_ptr]
    at = 0
    while at < a.rows:
        end = max(at + 1, int(np.searchsorted(made, made[at] + PRODUCTS, "right")) - 1)
        if made[end] > made[at]:
            low, high = a.row_ptr[at], a.row_ptr[end]
            yield at, kernels.Csr(a.row_ptr[at : end + 1] - low, a.col_idx[low:high], a.vals[low:high], a.cols)
        at = end


def from_tiles(t: Tiled) -> Matrix:
    """The entries of all tiles; narrow."""
    numbers = F.coalesce("row_idx", F.sequence(F.lit(0).cast("long"), F.col("nrows").cast("long") - 1))
    many = lambda n: (F.element_at("row_ptr", n + 2) - F.element_at("row_ptr", n + 1)).cast("int")
    rows = F.flatten(F.transform(numbers, lambda r, n: F.array_repeat(r, many(n))))
    df = t.df.select("ti", "tk", F.explode(F.arrays_zip(rows.alias("r"), F.col("col_idx").alias("c"), F.col("vals").alias("v"))).alias("e"))
    i = F.col("ti").cast("long") * t.tile_rows + F.col("e.r")
    j = F.col("tk").cast("long") * t.tile_cols + F.col("e.c")
    return Matrix(df.select(i.alias("i"), j.alias("j"), F.col("e.v").alias("v")), t.rows, t.cols)


def put_block(t: Tiled, ti: int, tk: int, block: np.ndarray, row0: int = 0, col0: int = 0) -> Tiled:
    """A new version with a dense block written over part of one tile."""
    spark = t.df.sparkSession
    base_i, base_j = ti * t.tile_rows + row0, tk * t.tile_cols + col0
    cells = [(base_i + r, base_j + c, v.item()) for (r, c), v in np.ndenumerate(block)]
    fresh = spark.createDataFrame(cells, f"i long, j long, v {t.value_type}")
    old = from_tiles(replace(t, df=t.get(ti, tk))).df
    merged = old.join(fresh.select("i", "j"), ["i", "j"], "left_anti").unionByName(fresh)
    return t.replace(to_tiles(Matrix(merged, t.rows, t.cols), t.tile_rows, t.tile_cols).df)


def tile_product(a: Tiled, b: Tiled, ring: str = "plus_times") -> Matrix:
    """C by local kernels: tiles meet in a join on the inner tile, partial tiles are added up.

    Each joined row holds one tile of A and one of B, so a worker's memory is bounded by the
    tile size, and products are expanded a run of rows at a time; partial sums leave the kernel gathered and are added where C is owned.
    """
    if a.cols != b.rows or a.tile_cols != b.tile_rows:
        raise ValueError("inner dimensions or tiles do not fit")
    kind = a.value_type
    arrow = _ARROW[kind]
    height, width = a.tile_rows, b.tile_cols
    left = a.df.select("ti", F.col("tk").alias("k"), *(F.col(c).alias(f"a_{c}") for c in _CELLS))
    right = b.df.select(F.col("ti").alias("k"), F.col("tk").alias("tj"), *(F.col(c).alias(f"b_{c}") for c in _CELLS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for n in range(batch.num_rows):
                right_tile = _csr(batch, n, "b")
                for first, slab in _slabs(_csr(batch, n, "a"), right_tile):
                    rows, cols, vals = kernels.csr_csr(slab, right_tile, ring)
                    i = rows.astype(np.int64) + (batch.column("ti")[n].as_py() * height + first)
                    j = cols.astype(np.int64) + batch.column("tj")[n].as_py() * width
                    yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(vals, arrow)], ["i", "j", "v"])

    parts = left.join(right, "k").mapInArrow(run, f"i long, j long, v {kind}")
    from ..functions.semirings import semiring

    return Matrix(parts.groupBy("i", "j").agg(semiring(ring).plus(F.col("v")).alias("v")), a.rows, b.cols)


def tile_product_c(a: Tiled, b: Tiled, grid: GridSpec, ring: str = "plus_times", offset: bool = True) -> Matrix:
    """C by local kernels with a stationary C: each worker walks its C tiles in schedule order.

    Tiles of A and B go to the owner of each C tile that needs them. Both carry the step at which
    the schedule wants them, which starts at the sum of the C tile's indices where ``offset`` is set;
    the join on it hands the kernel pair after pair in that order, while later batches
    are fetched ahead. A worker holds one pair and the C tile it adds to.
    """
    if a.cols != b.rows or a.tile_cols != b.tile_rows:
        raise ValueError("inner dimensions or tiles do not fit")
    kind = a.value_type
    arrow = _ARROW[kind]
    height, width, inner = a.tile_rows, b.tile_cols, -(-a.cols // a.tile_cols)
    start = F.col("ti") + F.col("tj") if offset else F.lit(0)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = a.df.withColumn("tj", every(-(-b.cols // width))).withColumn("step", F.pmod(F.col("tk") - start, F.lit(inner)))
    right = b.df.select(F.col("ti").alias("tk"), F.col("tk").alias("tj"), *_CELLS).withColumn("ti", every(-(-a.rows // height)))
    right = right.withColumn("step", F.pmod(F.col("tk") - start, F.lit(inner)))
    keys = ["owner", "ti", "tj", "step"]

    def placed(tiles: DataFrame, side: str) -> DataFrame:
        owned = tiles.withColumn("owner", grid.owner("ti", "tj")).repartitionById(grid.workers, F.col("owner"))
        return owned.select(*keys, *(F.col(c).alias(f"{side}_{c}") for c in _CELLS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, so_far = None, None

        def finished() -> pa.RecordBatch:
            rows, cols, vals = so_far
            i, j = rows.astype(np.int64) + at[0] * height, cols.astype(np.int64) + at[1] * width
            return pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(vals, arrow)], ["i", "j", "v"])

        for batch in batches:
            for n in range(batch.num_rows):
                tile = (batch.column("ti")[n].as_py(), batch.column("tj")[n].as_py())
                if at is not None and tile != at:
                    yield finished()
                    so_far = None
                at, right_tile = tile, _csr(batch, n, "b")
                part = kernels.csr_csr(_csr(batch, n, "a"), right_tile, ring)
                so_far = part if so_far is None else kernels.add_tiles([so_far, part], right_tile.cols, ring)
        if at is not None:
            yield finished()

    # a merge join sorts both sides by the keys, so a C tile's pairs come together and in step order
    pairs = placed(left, "a").hint("merge").join(placed(right, "b"), keys)
    return Matrix(pairs.mapInArrow(run, f"i long, j long, v {kind}"), a.rows, b.cols)
