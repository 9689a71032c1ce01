"""SimHash near-duplicates found by multi-index hashing.

A 64-bit fingerprint is cut into two 32-bit segments. Two fingerprints at distance three or
less agree to within one bit in at least one segment, so every fingerprint looks up the
Hamming ball of radius one around each of its segments in the table of segments, and the
complete distance is verified on what the table returns.

Skew. Exact copies share one fingerprint and are linked through it, not in pairs. A segment
value with very many different fingerprints is not joined in pairs either: its members meet
at points of small balls around the *other* segment (radius one against radius two), and each
point links its members to one of them. Rows stay linear in the members and no link between
different texts is lost.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, hot_keys, join_hot, whole

#: Shingles whose bits are counted at once; bounds the memory of one very long text.
SHINGLES_AT_ONCE = 1 << 16
#: Segment values with more different fingerprints than this are linked through ball points.
HOT_SEGMENT = 1024

_LANES = np.uint64(0x0101010101010101)


def count_bits(hashes: np.ndarray) -> np.ndarray:
    """How often each of the 64 bits (lowest first) is set in an array of uint64."""
    total = np.zeros(64, dtype=np.int64)
    starts = np.arange(0, len(hashes), 255)  # a byte lane holds up to 255
    for bit in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(bit)) & _LANES, starts)
        total[bit::8] += lanes.view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    return total


def fingerprint(text: str | None, shingle: int = 3, seed: int = 42) -> int:
    """Fingerprint of one text; no words: 0; fewer words than a shingle: the whole sequence."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    digest, bits = xxhash.xxh64_intdigest, np.zeros(64, dtype=np.int64)
    for at in range(0, n, SHINGLES_AT_ONCE):
        some = words[at : at + SHINGLES_AT_ONCE + shingle - 1]
        grams = zip(*(some[i:] for i in range(shingle))) if len(words) >= shingle else [words]
        bits += count_bits(
            np.fromiter((digest(b" ".join(g), seed) for g in grams), dtype=np.uint64)
        )
    return sum(1 << i for i in np.flatnonzero(2 * bits > n).tolist())


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp LONG: the 64 bits as a signed number) for every row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = np.fromiter(
                (fingerprint(t.as_py(), shingle) for t in batch.column(1)),
                dtype=np.uint64,
                count=batch.num_rows,
            )
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), pa.array(bits.view(np.int64))], ["doc_id", "fp"]
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text")).mapInArrow(
        run, "doc_id long, fp long"
    )


def _halves() -> list[Column]:
    """Segments as longs that carry their own number, so that one join serves both."""
    low = F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
    high = F.shiftrightunsigned("fp", 32)
    return [low, high + F.lit(1 << 32)]


def _ball(radius: int) -> Column:
    """Masks of all 32-bit points within ``radius`` of zero, as (mask, distance)."""
    masks = [
        (sum(1 << b for b in bits), r) for r in range(radius + 1) for bits in combinations(range(32), r)
    ]
    return F.expr(
        "array(" + ", ".join(f"named_struct('mask', {m}L, 'r', {r})" for m, r in masks) + ")"
    )


def _table(distinct: DataFrame) -> DataFrame:
    """(key, fp): each fingerprint under both of its segments."""
    return distinct.select("fp", F.explode(F.array(*_halves())).alias("key"))


def _probes(distinct: DataFrame) -> DataFrame:
    """(key, fp): each fingerprint under the ball of radius one around its segments.

    Of two segments one bit apart, one lacks the bit that the other has; it alone probes, so
    only flips that set a bit are made. The segment itself (distance zero) is not repeated
    here: ``_table`` joined with itself has it.
    """
    bit = F.explode(F.sequence(F.lit(0), F.lit(31))).alias("bit")
    flip = F.expr("shiftleft(1L, bit)")
    return (
        _table(distinct)
        .select("fp", "key", bit)
        .where(F.col("key").bitwiseAND(flip) == 0)
        .select("fp", F.col("key").bitwiseOR(flip).alias("key"))
    )


def links(distinct: DataFrame, max_distance: int = 3, hot_segment: int = HOT_SEGMENT) -> DataFrame:
    """(a, b) of linked different fingerprints, enough of them to connect every linked pair.

    ``distinct``: one row per fingerprint, column ``fp``. Where no segment value is hot these
    are all links; a hot value contributes its members' links to one member per ball point.
    ``max_distance`` is at most 3: two segments and radius one promise no more.
    """
    if not 0 <= max_distance <= 3:
        raise ValueError("two segments with balls of radius one find distances up to 3")
    table = _table(distinct)
    sizes = table.groupBy("key").agg(F.count("*").alias("members"))
    hot = cut(sizes.where(F.col("members") > hot_segment).select("key"))
    any_hot = not hot.isEmpty()
    probes = _probes(distinct).unionByName(table)
    cool_table = table.join(hot, "key", "left_anti") if any_hot else table
    near = (
        probes.alias("p")
        .join(cool_table.alias("t"), "key")
        .where("p.fp <> t.fp")
        .where(F.bit_count(F.col("p.fp").bitwiseXOR(F.col("t.fp"))) <= max_distance)
        .select(F.least("p.fp", "t.fp").alias("a"), F.greatest("p.fp", "t.fp").alias("b"))
    )
    if any_hot:
        near = near.unionByName(_hot_links(table, _probes(distinct), hot, max_distance))
    return near.distinct()


def _hot_links(table: DataFrame, probes: DataFrame, hot: DataFrame, most: int) -> DataFrame:
    """Links inside hot segment values, through points of balls around the other segment."""
    low = F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF).cast("long"))
    other = F.when(F.col("key") < F.lit(1 << 32), F.shiftrightunsigned("fp", 32)).otherwise(low)
    members = table.withColumn("near", F.lit(0)).unionByName(probes.withColumn("near", F.lit(1)))
    # members at `near` in this segment may differ by the rest in the other one: up to half of
    # it from a hub to the point, so that two hubs are linked too, the other half from a member
    hub_radius = most // 2
    points = (
        members.join(hot, "key", "left_semi")
        .withColumn("other", other)
        .withColumn("ball", F.explode(_ball(most - hub_radius)))
        .where(F.col("ball.r") <= F.lit(most - hub_radius) - F.col("near"))
        .select("key", F.col("other").bitwiseXOR(F.col("ball.mask")).alias("point"), "fp", "near", "ball.r")
    )
    hubs = (
        points.where((F.col("near") == 0) & (F.col("r") <= hub_radius))
        .groupBy("key", "point")
        .agg(F.min("fp").alias("hub"))
    )
    return (
        points.join(hubs, ["key", "point"])
        .where("fp <> hub")
        .select(F.least("fp", "hub").alias("a"), F.greatest("fp", "hub").alias("b"))
    )


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root): the smallest node that each node of ``edges`` (a, b) can reach.

    Alternating star contraction: rounds grow with the logarithm of a component's size, each
    round is two aggregations with map-side minima, and lineage is cut by a checkpoint.
    """
    edges = cut(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    before = None
    for _ in range(max_rounds):
        edges = cut(_small_star(_large_star(edges)))
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before or now[0] == 0:
            break
        before = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return edges.select(F.col("b").alias("node"), F.col("a").alias("root")).unionByName(
        edges.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct()
    )


def _large_star(edges: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is tied to the smallest node around it."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.min("b").alias("m"))
    return (
        both.join(low, "a")
        .where("b > a")
        .select(F.least("a", "m").alias("a"), "b")
        .distinct()
    )


def _small_star(edges: DataFrame) -> DataFrame:
    """A node and its smaller neighbours are tied to the smallest of them (edges have a < b)."""
    low = edges.groupBy("b").agg(F.min("a").alias("m"))
    return (
        edges.join(low, "b")
        .select("m", F.explode(F.array("a", "b")).alias("x"))
        .where("m <> x")
        .select(F.col("m").alias("a"), F.col("x").alias("b"))
        .distinct()
    )


def near_duplicates(
    docs: DataFrame, shingle: int = 3, max_distance: int = 3, hot_segment: int = HOT_SEGMENT
) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of ``docs`` (doc_id, text, ...).

    fingerprint: 16 lowercase hex digits. component_id: smallest doc_id reachable through
    links, the own one included. Null texts count as empty; empty texts have fingerprint zero
    and are linked like any other. Repeated rows each get a row. A null doc_id is never a
    component's id unless nothing else is in the component. Other columns are ignored. An
    empty table gives an empty result.
    """
    prints = cut(fingerprints(docs, shingle))
    distinct = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("first")))
    roots = cut(components(links(distinct.select("fp"), max_distance, hot_segment)))
    named = roots.join(distinct, roots.node == distinct.fp).select("root", "node", "first")
    smallest = named.groupBy("root").agg(F.min("first").alias("component_id"))
    linked = named.join(smallest, "root").select(F.col("node").alias("fp"), "component_id")
    labels = distinct.join(linked, "fp", "left").select(
        "fp", F.coalesce("component_id", "first").alias("component_id")
    )
    # a fingerprint of very many copies takes its label from a broadcast
    return join_hot(prints, labels, "fp", hot_keys(prints, "fp")).select(
        "doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id"
    )


def survivors(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """One row of ``docs`` for each component in ``rows`` (doc_id, content, component).

    It is the row of smallest doc_id, null last, then of smallest hash of the text (``content``).
    All columns are kept as they are.
    """
    number = F.col("doc_id").cast("long")
    keys = [number.isNull().alias("none"), F.coalesce(number, F.lit(0).cast("long")).alias("id")]
    order = F.struct("none", "id", "content")
    best = rows.select(*keys, "content", "component").groupBy("component").agg(F.min(order).alias("best")).select("best.*")
    boxed = docs.select(*keys, F.xxhash64(whole()).alias("content"), F.struct("*").alias("row"))
    # rows of one id and text are in one component, and lie together after the join
    at = ["none", "id", "content"]
    return boxed.join(best, at).dropDuplicates(at).select("row.*")


def keep_one(docs: DataFrame, shingle: int = 3, max_distance: int = 3) -> DataFrame:
    """``docs`` with one row of each near-duplicate group: the one of smallest doc_id, null last.

    All columns are kept as they are. Groups are of rows, not of ids: rows with a null doc_id,
    or with one that repeats, are told apart by their texts.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(whole()).alias("content"), whole().alias("text"))
    texts = cut(rows.groupBy("content").agg(F.first("text").alias("text")))
    prints = cut(fingerprints(texts.select(F.col("content").alias("doc_id"), "text"), shingle))
    roots = components(links(prints.select("fp").distinct(), max_distance)).distinct()
    named = prints.join(roots, prints.fp == roots.node, "left").select(
        F.col("doc_id").alias("content"), F.coalesce("root", "fp").alias("component")
    )
    return survivors(docs, rows.select("doc_id", "content").join(named, "content"))
