"""Matrices built from the given tables and from rules."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..matrix import Matrix
from ..session import materialise

#: Quadrant probabilities of the recursive generator times 65536, added up.
RMAT_CUTS = (39322, 48060, 56798)
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _size(df: DataFrame, key: str) -> int:
    top = df.agg(F.max(key)).first()[0]
    return 0 if top is None else int(top) + 1


def order_part(spark: SparkSession, sf_dir: str) -> Matrix:
    lines = table(spark, sf_dir, "lineitem")
    cells = lines.groupBy(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j")).agg(
        F.sum("l_quantity").cast("long").alias("v")
    )
    return Matrix(cells, _size(table(spark, sf_dir, "orders"), "o_orderkey"), _size(table(spark, sf_dir, "part"), "p_partkey"))


def supp_part(spark: SparkSession, sf_dir: str) -> Matrix:
    lines = table(spark, sf_dir, "lineitem")
    cells = lines.groupBy(F.col("l_suppkey").alias("i"), F.col("l_partkey").alias("j")).agg(
        F.sum("l_quantity").cast("long").alias("v")
    )
    return Matrix(cells, _size(table(spark, sf_dir, "supplier"), "s_suppkey"), _size(table(spark, sf_dir, "part"), "p_partkey"))


def cust_supp(spark: SparkSession, sf_dir: str) -> Matrix:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    cells = (
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .groupBy(F.col("o_custkey").alias("i"), F.col("l_suppkey").alias("j"))
        .agg(F.count("*").alias("v"))
    )
    return Matrix(cells, _size(table(spark, sf_dir, "customer"), "c_custkey"), _size(table(spark, sf_dir, "supplier"), "s_suppkey"))


def nation_trade(spark: SparkSession, sf_dir: str) -> Matrix:
    """Quantity from the nation of a customer to that of a supplier; both key tables are small."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    suppliers = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    cells = (
        lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
        .join(customers, F.col("o_custkey") == F.col("c_custkey"))
        .join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
        .groupBy(F.col("c_nationkey").cast("long").alias("i"), F.col("s_nationkey").cast("long").alias("j"))
        .agg(F.sum("l_quantity").cast("long").alias("v"))
    )
    n = _size(table(spark, sf_dir, "nation"), "n_nationkey")
    return Matrix(cells, n, n)


def user_follow(spark: SparkSession, sf_dir: str) -> Matrix:
    """How often an event of one user comes right before one of another.

    Successors are found inside an hour; the last event of an hour takes the first of the next
    hour that has any, so no window goes over all events.
    """
    events = table(spark, sf_dir, "events").select(
        "user_id", "ts", "event_id", F.date_trunc("hour", "ts").alias("hour")
    )
    inside = Window.partitionBy("hour").orderBy("ts", "event_id")
    heads = events.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"))
    following = heads.select("hour", F.lead("head").over(Window.orderBy("hour")).alias("next_head"))
    steps = (
        events.select("hour", "user_id", F.lead("user_id").over(inside).alias("next"))
        .join(following, "hour")
        .select(F.col("user_id").alias("i"), F.coalesce("next", "next_head").alias("j"))
        .where("j is not null")
    )
    n = _size(events, "user_id")
    return Matrix(steps.groupBy("i", "j").agg(F.count("*").alias("v")), n, n)


def event_code(column: str = "event_type") -> Column:
    return F.array_position(F.array(*(F.lit(t) for t in EVENT_TYPES)), F.col(column)) - 1


def user_event(spark: SparkSession, sf_dir: str) -> Matrix:
    events = table(spark, sf_dir, "events")
    cells = events.groupBy(F.col("user_id").alias("i"), event_code().cast("long").alias("j")).agg(F.count("*").alias("v"))
    return Matrix(cells, _size(events, "user_id"), len(EVENT_TYPES))


#: Rows of a run that one task counts pairs for, and pairs that it holds uncounted.
RUN_ROWS, PAIRS_AT_ONCE = 1 << 14, 1 << 22


def _pairs_of(sizes: np.ndarray, parts: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All ordered pairs of members of each set, sets one after the other, some ``PAIRS_AT_ONCE`` at a time."""
    of = np.repeat(sizes, sizes)
    first = np.repeat(np.cumsum(sizes) - sizes, sizes)
    up_to = np.concatenate([[0], np.cumsum(of)])
    at = 0
    while at < len(parts):
        end = max(at + 1, int(np.searchsorted(up_to, up_to[at] + PAIRS_AT_ONCE, "right")) - 1)
        some = of[at:end]
        other = np.repeat(first[at:end] - up_to[at:end] + up_to[at], some)
        other += np.arange(len(other))
        yield np.repeat(parts[at:end], some), parts[other]
        at = end


def copurchase(spark: SparkSession, sf_dir: str) -> Matrix:
    """Pairs of different parts in one order; an order has few lines.

    Orders move packed, once to each run of rows that one of their parts is in; pairs are made and counted there.
    """
    n = _size(table(spark, sf_dir, "part"), "p_partkey")
    height = min(RUN_ROWS, max(256, -(-n // 48)))
    runs = -(-max(1, n) // height)

    def send(orders: np.ndarray, parts: np.ndarray) -> Iterator[pa.RecordBatch]:
        fresh = np.r_[True, (orders[1:] != orders[:-1]) | (parts[1:] != parts[:-1])]
        orders, parts = orders[fresh], parts[fresh]
        starts = np.flatnonzero(np.r_[True, orders[1:] != orders[:-1]])
        sizes = np.diff(np.r_[starts, len(orders)])
        order, run = np.repeat(np.arange(len(sizes)), sizes), parts // height
        once = np.r_[True, (order[1:] != order[:-1]) | (run[1:] != run[:-1])] & (np.repeat(sizes, sizes) > 1)
        order, run = order[once], run[once]
        by_run = np.argsort(run, kind="stable")
        order, run = order[by_run], run[by_run]
        ends = np.flatnonzero(np.r_[run[1:] != run[:-1], True]) + 1 if len(run) else []
        at = 0
        for end in ends:
            some = order[at:end]
            many = sizes[some]
            places = np.repeat(starts[some] - np.cumsum(many) + many, many)
            places += np.arange(len(places))
            cells = [pa.compress(x.astype("<i8").tobytes(), "zstd", asbytes=True) for x in (many, parts[places])]
            yield pa.RecordBatch.from_pydict({"run": [int(run[at])], "orders": [len(many)], "sizes": [cells[0]], "members": [len(places)], "parts": [cells[1]]}, wire)
            at = end

    wire = pa.schema([("run", pa.int64()), ("orders", pa.int64()), ("sizes", pa.binary()), ("members", pa.int64()), ("parts", pa.binary())])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append(tuple(batch.column(k).to_numpy(zero_copy_only=False) for k in range(2)))
                rows += batch.num_rows
            if rows >= 1 << 19:
                orders, parts = (np.concatenate(x) for x in zip(*held))
                whole = int(np.searchsorted(orders, orders[-1]))  # the last order may go on
                if whole:
                    yield from send(orders[:whole], parts[:whole])
                held, rows = [(orders[whole:], parts[whole:])], len(orders) - whole
        if held:
            yield from send(*(np.concatenate(x) for x in zip(*held)))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, keys, many, waiting, n_waiting = None, np.zeros(0, np.int64), np.zeros(0, np.int64), [], 0

        def merge() -> None:
            nonlocal keys, many, waiting, n_waiting
            fresh, found = np.unique(np.concatenate(waiting), return_counts=True) if waiting else (keys[:0], many[:0])
            if len(keys):
                both, back = np.unique(np.concatenate([keys, fresh]), return_inverse=True)
                keys, many = both, np.bincount(back, np.concatenate([many, found])).astype(np.int64)
            else:
                keys, many = fresh, found.astype(np.int64)
            waiting, n_waiting = [], 0

        def shown() -> Iterator[pa.RecordBatch]:
            nonlocal keys, many
            merge()
            for x in range(0, len(keys), 1 << 17):
                some = keys[x : x + (1 << 17)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in ((some >> 48) + at * height, some & ((1 << 48) - 1), many[x : x + (1 << 17)])], ["i", "j", "v"])
            keys, many = keys[:0], many[:0]

        for batch in batches:
            for k in range(batch.num_rows):
                run, orders, sizes, members, parts = (c[0].as_py() for c in batch.slice(k, 1).columns)
                if run != at:
                    if at is not None:
                        yield from shown()
                    at = run
                sizes, parts = (np.frombuffer(pa.decompress(x, 8 * m, "zstd", asbytes=True), "<i8") for x, m in ((sizes, orders), (parts, members)))
                for i, j in _pairs_of(sizes, parts):
                    keep = (i // height == at) & (i != j)
                    waiting.append(((i[keep] - at * height) << 48) + j[keep])
                    n_waiting += len(waiting[-1])
                    if n_waiting >= max(PAIRS_AT_ONCE, len(keys)):
                        merge()
        if at is not None:
            yield from shown()

    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").where("l_orderkey is not null and l_partkey is not null")
    orders = lines.repartition("l_orderkey").sortWithinPartitions("l_orderkey", "l_partkey").mapInArrow(pack, "run long, orders long, sizes binary, members long, parts binary")
    parts = min(1024, runs)
    sent = orders.repartitionById(parts, F.pmod("run", F.lit(parts).cast("long")).cast("int")).sortWithinPartitions("run")
    return Matrix(sent.mapInArrow(count, "i long, j long, v long"), n, n, placed=True)


def banded(spark: SparkSession, sf_dir: str) -> Matrix:
    lines = table(spark, sf_dir, "lineitem")
    n = _size(table(spark, sf_dir, "orders"), "o_orderkey")
    column = F.least(F.col("l_orderkey") + F.col("l_linenumber") - 1, F.lit(n - 1))
    cells = lines.groupBy(F.col("l_orderkey").alias("i"), column.cast("long").alias("j")).agg(F.count("*").alias("v"))
    return Matrix(cells, n, n)


def tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return docs.select("doc_id", F.explode(F.split(F.lower("text"), " ", -1)).alias("token")).where("token <> ''")


#: Tokens that one task numbers.
TOKENS_PER_RANGE = 1_000_000


def dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(token, j): all tokens numbered in order, written once; ranges are counted, not gathered."""
    different = materialise(tokens(spark, sf_dir).select("token").distinct())
    parts = max(1, -(-different.count() // TOKENS_PER_RANGE))
    ordered = different.repartitionByRange(parts, "token") if parts > 1 else different.coalesce(1)
    placed = materialise(ordered.sortWithinPartitions("token").withColumn("at", F.monotonically_increasing_id()))
    part = F.shiftright("at", 33)
    counts = placed.groupBy(part.alias("part")).agg(F.count("*").alias("n"))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row per range
    starts = counts.select("part", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("start"))
    number = F.col("start") + F.col("at").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn("part", part).join(F.broadcast(starts), "part").select("token", number.cast("long").alias("j"))


def doc_term(spark: SparkSession, sf_dir: str) -> Matrix:
    """Counts of all tokens of all documents; counted by document first, so that a common token's rows are few."""
    words = materialise(dictionary(spark, sf_dir))
    counts = tokens(spark, sf_dir).groupBy("doc_id", "token").agg(F.count("*").alias("v"))
    cells = counts.join(words, "token").select(F.col("doc_id").alias("i"), "j", "v")
    return Matrix(cells, _size(table(spark, sf_dir, "documents"), "doc_id"), words.count())


def emb_graph(spark: SparkSession, sf_dir: str, block: int = 4096) -> Matrix:
    """Pairs of vectors with cosine of 0.2 or more, tested in whole numbers.

    The fixture is A·Aᵀ over quantized components, thresholded. Vectors are packed into blocks of
    near ids and bounded size, every block meets itself and those after it by an equi-join on the block's number,
    and dense products of slices of two blocks keep only the pairs that pass, in both directions.
    """
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    n = _size(vectors, "vec_id")
    blocks = max(1, -(-n // block))

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        x = np.floor(np.stack([np.asarray(v, dtype=float) for v in rows["embedding"]]) * 1000 + 0.5)
        cells = [(rows["b"].iloc[0], x.shape[1], rows["vec_id"].to_numpy("<i8").tobytes(), x.astype("<f8").tobytes())]
        return pd.DataFrame(cells, columns=["b", "dim", "ids", "x"])

    packed = vectors.withColumn("b", F.call_function("div", F.col("vec_id"), F.lit(block).cast("long")).cast("int")).groupBy("b").applyInPandas(
        pack, "b int, dim int, ids binary, x binary"
    )
    right = packed.select("b", F.col("ids").alias("ids2"), F.col("x").alias("x2"))
    left = packed.select(F.col("b").alias("own"), "dim", "ids", "x", F.explode(F.sequence(F.col("b"), F.lit(blocks - 1))).alias("b"))

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                i, j = np.frombuffer(r["ids"], "<i8"), np.frombuffer(r["ids2"], "<i8")
                x, y = (np.frombuffer(r[c], "<f8").reshape(-1, r["dim"]) for c in ("x", "x2"))
                length = (y * y).sum(1)
                for at in range(0, len(i), 512):
                    some, ids = x[at : at + 512], i[at : at + 512]
                    s = some @ y.T  # whole numbers far below 2**53: exact
                    alike = (s > 0) & (25 * s * s >= np.outer((some * some).sum(1), length)) & (ids[:, None] != j[None, :])
                    at_i, at_j = np.nonzero(alike)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[at_i]), pa.array(j[at_j])], ["i", "j"])
                    if r["own"] != r["b"]:
                        yield pa.RecordBatch.from_arrays([pa.array(j[at_j]), pa.array(ids[at_i])], ["i", "j"])

    met = left.join(right, "b").select("own", "b", "dim", "ids", "x", "ids2", "x2")
    edges = met.mapInArrow(pairs, "i long, j long")
    return Matrix(edges.select("i", "j", F.lit(1).cast("long").alias("v")), n, n, placed=True)


def href(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, href, n): links of each page, counted."""
    pages = table(spark, sf_dir, "pages")
    links = pages.select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return links.groupBy("page_id", "href").agg(F.count("*").alias("n"))


def rmat(spark: SparkSession, scale: int, edge_factor: int = 8, seed: int = 42, merge: bool = True) -> Matrix:
    """Recursive power-law graph from hashed digits, the same in any engine that has md5."""
    row, col = F.lit(0).cast("long"), F.lit(0).cast("long")
    edges = spark.range(edge_factor << scale).select(
        "id", *(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("id").cast("string"), F.lit(str(part)))).alias(f"h{part}") for part in range((scale + 7) // 8))
    )
    for level in range(scale):
        u = F.conv(F.substring(f"h{level // 8}", 4 * (level % 8) + 1, 4), 16, 10).cast("long")
        row = row * 2 + F.when(u >= RMAT_CUTS[1], 1).otherwise(0)
        col = col * 2 + F.when(((u >= RMAT_CUTS[0]) & (u < RMAT_CUTS[1])) | (u >= RMAT_CUTS[2]), 1).otherwise(0)
    cells = edges.select(row.alias("i"), col.alias("j"), F.lit(1).cast("long").alias("v"))
    n = 1 << scale
    if merge:
        return Matrix(cells.groupBy("i", "j").agg(F.sum("v").alias("v")), n, n)
    return Matrix(cells, n, n)


def by_rule(keys: DataFrame, n: int) -> DataFrame:
    """(i, j, v): n entries by rule in every row of ``keys`` (i)."""
    rows = keys.select("i", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("j"))
    return rows.select("i", "j", (F.pmod(31 * F.col("i") + 17 * F.col("j"), F.lit(97)) - 48).cast("long").alias("v"))


def grid_b(spark: SparkSession, k: int, n: int) -> Matrix:
    """A dense operand by rule: one range, one explode of a fixed width."""
    return Matrix(by_rule(spark.range(k).select(F.col("id").alias("i")), n), k, n, lambda i, j: (31 * i + 17 * j) % 97 - 48)


def emb_b(spark: SparkSession, sf_dir: str, exact: bool = False) -> Matrix:
    """The embeddings as a tall-skinny dense operand; ``exact`` in thousandths as whole numbers."""
    vectors = table(spark, sf_dir, "embeddings")
    long = vectors.select(F.col("vec_id").alias("i"), F.posexplode("embedding").alias("j", "x"))
    x = F.col("x").cast("double")
    value = F.floor(x * 1000 + 0.5).cast("long") if exact else x
    width = vectors.select(F.max(F.size("embedding"))).first()[0] or 0
    return Matrix(long.select("i", F.col("j").cast("long").alias("j"), value.alias("v")), _size(vectors, "vec_id"), width)
