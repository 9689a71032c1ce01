"""Readers and writers: entry tables, tiles, owner-placed tables and coordinate text."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..grid import GridSpec
from ..matrix import Matrix
from ..operators.layout import Tiled


def _write_dims(spark: SparkSession, path: str, **dims: int) -> None:
    row = spark.createDataFrame([tuple(dims.values())], ", ".join(f"{n} long" for n in dims))
    row.coalesce(1).write.mode("overwrite").json(f"{path}/dims")


def write_coo(a: Matrix, path: str) -> None:
    a.df.select("i", "j", "v").write.mode("overwrite").parquet(f"{path}/entries")
    _write_dims(a.df.sparkSession, path, rows=a.rows, cols=a.cols)


def read_coo(spark: SparkSession, path: str) -> Matrix:
    dims = spark.read.schema("rows long, cols long").json(f"{path}/dims").first()
    return Matrix(spark.read.parquet(f"{path}/entries"), dims["rows"], dims["cols"])


def write_tiles(t: Tiled, path: str) -> None:
    """One folder per row of tiles, so that fetching a tile reads only its row."""
    t.df.write.mode("overwrite").partitionBy("ti").parquet(f"{path}/tiles")
    _write_dims(t.df.sparkSession, path, rows=t.rows, cols=t.cols, tile_rows=t.tile_rows, tile_cols=t.tile_cols)


def read_tiles(spark: SparkSession, path: str) -> Tiled:
    d = spark.read.schema("rows long, cols long, tile_rows long, tile_cols long").json(f"{path}/dims").first()
    return Tiled(spark.read.parquet(f"{path}/tiles"), d["rows"], d["cols"], d["tile_rows"], d["tile_cols"])


def save_stationary(a: Matrix, name: str, grid: GridSpec) -> None:
    """The operand that stays, bucketed by owner: later joins on the owner do not move it."""
    placed = a.df.select("i", "j", "v", grid.ti("i").alias("ti"), grid.tk("j").alias("tk"))
    placed.withColumn("owner", grid.owner("ti", "tk")).write.mode("overwrite").bucketBy(grid.workers, "owner").saveAsTable(name)


def stationary_product(spark: SparkSession, name: str, b: Matrix, rows: int, grid: GridSpec) -> Matrix:
    """A saved stationary operand times B: only B's rows and partial sums are shuffled."""
    left = spark.table(name).select("owner", "i", F.col("j").alias("k"), F.col("v").alias("a"))
    right = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("b"), grid.tk("i").alias("tk"))
    right = right.withColumn("ti", F.explode(F.sequence(F.lit(0), F.lit(grid.gm - 1))))
    right = right.select(grid.owner("ti", "tk").alias("owner"), "k", "j", "b").distinct()
    parts = left.join(right, ["owner", "k"]).groupBy("owner", "i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("v"))
    return Matrix(parts.groupBy("i", "j").agg(F.sum("v").alias("v")), rows, b.cols)


def read_edges(spark: SparkSession, path: str, fmt: str, mode: str = "FAILFAST", header: bool = True) -> DataFrame:
    """Edge lists (i, j, v) in csv, json, orc or parquet, with the schema given and never inferred."""
    reader = spark.read.schema("i long, j long, v double")
    if fmt in ("csv", "json"):
        reader = reader.option("mode", mode)
    if fmt == "csv":
        reader = reader.option("header", header)
    return reader.format(fmt).load(path)


def write_edges(a: Matrix, path: str, fmt: str) -> None:
    writer = a.df.select("i", "j", F.col("v").cast("double").alias("v")).write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def write_mtx(a: Matrix, path: str, kind: str = "integer") -> None:
    """Coordinate text: banner and dimensions in a first file, entries from 1 in the others."""
    spark = a.df.sparkSession
    head = [("0", f"%%MatrixMarket matrix coordinate {kind} general"), ("1", f"{a.rows} {a.cols} {a.nnz()}")]
    lines = spark.createDataFrame(head, "n string, value string").orderBy("n").coalesce(1).select("value")
    lines.write.mode("overwrite").text(path)
    a.df.select(F.concat_ws(" ", (F.col("i") + 1).cast("string"), (F.col("j") + 1).cast("string"), F.col("v").cast("string")).alias("value")).write.mode("append").text(path)


def read_mtx(spark: SparkSession, path: str) -> Matrix:
    """Coordinate text, general, symmetric or pattern; comments are skipped."""
    lines = spark.read.text(path)
    banner = lines.where("value like '%MatrixMarket%'").first()
    words = banner["value"].lower().split() if banner else ["", "matrix", "coordinate", "real", "general"]
    kind, shape = words[3], words[4]
    parts = F.split(F.trim("value"), r"\s+")
    numbers = lines.where("value not like '\\\\%%' and trim(value) <> ''").select(parts.alias("p"))
    # the line of dimensions is the only one whose last number counts the others
    wide = 2 if kind == "pattern" else 3
    dims = _dimensions(numbers, lines)
    value = F.lit(1).cast("long") if kind == "pattern" else F.get("p", F.lit(2)).cast("long" if kind == "integer" else "double")
    entries = numbers.where(F.concat_ws(" ", "p") != F.lit(" ".join(map(str, dims)))) if wide == 3 else numbers.where(F.size("p") == 2)
    cells = entries.select((F.get("p", F.lit(0)).cast("long") - 1).alias("i"), (F.get("p", F.lit(1)).cast("long") - 1).alias("j"), value.alias("v"))
    a = Matrix(cells, dims[0], dims[1])
    if shape == "symmetric":
        mirrored = a.where(F.col("i") != F.col("j")).transpose().df
        a = replace(a, df=cells.unionByName(mirrored))
    return a


def _dimensions(numbers: DataFrame, lines: DataFrame) -> tuple[int, int, int]:
    """The line of dimensions: the entry count is one less than the number of lines."""
    n = numbers.count() - 1
    found = numbers.where((F.size("p") == 3) & (F.get("p", F.lit(2)) == F.lit(str(n)))).select(
        F.get("p", F.lit(0)).cast("long").alias("m"), F.get("p", F.lit(1)).cast("long").alias("k")
    )
    top = found.orderBy(F.desc("m"), F.desc("k")).first()
    if top is None:
        raise ValueError("no line of dimensions")
    return top["m"], top["k"], n
