"""Near copies: texts whose sets of five-word shingles have Jaccard similarity 0.8 or more.

The fingerprints of ``simhash`` cannot see this similarity: at 0.8 two fingerprints differ in 15 % of
their bits, so that 99 % of such pairs ask for 40 segments of 24 bits with balls of radius one (some 520
rows a document, and segments so short that unlike texts meet), or 126 segments of 32 bits (some 2,100 rows).
The method's own step comes first all the same: 64-bit fingerprints of the five-word shingles meet within three bits through
segments and balls, as in ``simhash``, and the pairs they give are checked. What they cannot see
meets in bands of minima of hashed shingles, 30 rows a document. At similarity 0.8 a band of five minima is
shared with probability 0.33, so that 30 bands miss a pair with probability 7e-6, and a closer
pair more rarely still. Every candidate pair is then checked on the complete sets of shingles.

Texts of the same words are one node. The nodes of a band are compared with one of them, picked by
hash band by band, so that a large family meets as many of its members as it has bands and hangs together
after a round or two; each round is linear in the bands' rows. Pairs are made only of nodes that this does not bring
together, and only in bands of few nodes. A band that still has more, such as the outliers of a family or texts
around one common passage, makes no pairs: its nodes meet at their rarest shingles instead. Two
sets at similarity 0.8 share one of the rarest fifth of either's, so nothing is lost. An outlier's rarest fifth is
its own, and a passage that many texts share is among the rarest of none but those that are little else.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import settings
from .common import HINTED_ONLY, cut, hot_keys, join_hot, whole
from .simhash import components, count_bits, links, survivors

#: Words of a shingle, and the least similarity as a fraction.
SHINGLE = 5
LEAST = (4, 5)
ROWS, BANDS = 5, 30
_BLOCK = 1 << 11
#: Rounds of comparisons with one node of each band.
ROUNDS = 2
#: Bands with more nodes than this after these rounds meet at rare shingles.
HOT_BAND = 8
#: Links that are followed on the driver (1 MB); more are followed by rounds of joins.
FEW_LINKS = 1 << 16
#: Tallies that shingles of crowded bands are counted in; more shingles than this share them.
TALLIES = 1 << 20

_RNG = np.random.default_rng(42)
_FLIPS = _RNG.integers(0, 1 << 63, ROWS * BANDS, dtype=np.uint64)
_FACTORS = _RNG.integers(0, 1 << 63, ROWS * BANDS, dtype=np.uint64) | np.uint64(1)
_POWER = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def node_of(words: list[bytes]) -> int:
    """The hash that stands for a sequence of words."""
    return int(np.uint64(xxhash.xxh64_intdigest(b" ".join(words), 42)).astype(np.int64))


def _fold(parts: list[np.ndarray]) -> np.ndarray:
    """One well-mixed hash of several, in order."""
    out = parts[0].copy()
    for p in parts[1:]:
        out = out * _POWER + p
    out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    return out ^ (out >> np.uint64(32))


def shingles(words: list[bytes]) -> np.ndarray:
    """Different shingles as sorted hashes; fewer words than a shingle: the whole sequence."""
    if not words:
        return np.zeros(0, np.uint64)
    hashes = np.fromiter((xxhash.xxh64_intdigest(w, 42) for w in words), np.uint64, len(words))
    n, wide = max(1, len(words) - SHINGLE + 1), min(SHINGLE, len(words))
    return np.unique(_fold([hashes[i : i + n] for i in range(wide)]))


def bands(found: np.ndarray) -> np.ndarray:
    """Keys of the bands of a set of shingles; an empty set has none."""
    if not len(found):
        return np.zeros(0, np.int64)
    least = np.full(ROWS * BANDS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(found), _BLOCK):
        some = (found[at : at + _BLOCK, None] ^ _FLIPS) * _FACTORS
        np.minimum(least, some.min(axis=0), out=least)
    parts = least.reshape(BANDS, ROWS)
    return _fold([np.arange(BANDS, dtype=np.uint64), *(parts[:, r] for r in range(ROWS))]).view(np.int64)


def similar(x: np.ndarray, y: np.ndarray) -> bool:
    """Whether two sets have at least the least similarity."""
    both = len(np.intersect1d(x, y, assume_unique=True))
    return LEAST[1] * both >= LEAST[0] * (len(x) + len(y) - both)


def print_of(found: np.ndarray) -> int:
    """The 64-bit fingerprint of a set of shingles; an empty set has zero."""
    bits = np.flatnonzero(2 * count_bits(found) > len(found)) if len(found) else []
    return int(np.uint64(sum(1 << int(b) for b in bits)).astype(np.int64))


def _nodes(docs: DataFrame) -> DataFrame:
    """(doc_id, content, words, size, print, bands) for every row of ``docs``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            nodes, sizes, prints, keys = [], [], [], []
            for t in batch.column(2):
                words = words_of(t.as_py())
                found = shingles(words)
                nodes.append(node_of(words))
                sizes.append(len(found))
                prints.append(print_of(found))
                keys.append(bands(found))
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    batch.column(1),
                    pa.array(nodes, pa.int64()),
                    pa.array(sizes, pa.int64()),
                    pa.array(prints, pa.int64()),
                    pa.array(keys, pa.list_(pa.int64())),
                ],
                ["doc_id", "content", "words", "size", "print", "bands"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(whole()).alias("content"), whole().alias("text"))
    return rows.mapInArrow(run, "doc_id long, content long, words long, size long, print long, bands array<long>")


def _sets(docs: DataFrame, needed: DataFrame) -> DataFrame:
    """(node, found BINARY: sorted shingles) for the texts whose ``content`` is needed as a node.

    Dealt by node once, so that a checkpoint of it joins again and again without moving. Texts that nothing
    needs have no set.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [shingles(words_of(t.as_py())).tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.binary())], ["node", "found"])

    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    texts = docs.select(F.xxhash64(whole()).alias("node"), whole().alias("text"))
    # one row of each text before it is dealt: a group of exact copies would go to one task
    wanted = texts.groupBy("node").agg(F.first("text").alias("text")).join(needed, "node", "left_semi")
    return wanted.select("node", "text").mapInArrow(run, "node long, found binary").repartition(parts, "node")


def _checked(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of ``pairs`` (a, b) whose sets of shingles are similar."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (([np.frombuffer(v.as_buffer(), np.uint64) for v in batch.column(c)]) for c in (2, 3))
            keep = pa.array([similar(p, q) for p, q in zip(x, y)], pa.bool_())
            yield batch.select([0, 1]).filter(keep)

    left = sets.select(F.col("node").alias("a"), F.col("found").alias("x"))
    right = sets.select(F.col("node").alias("b"), F.col("found").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _sized(pairs: DataFrame) -> DataFrame:
    """Different pairs (a, b) of (a, b, m, n) whose sizes m, n allow the least similarity."""
    low, high = F.least("m", "n"), F.greatest("m", "n")
    return (
        pairs.where(LEAST[1] * low >= LEAST[0] * high)
        .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        .distinct()
    )


def _rare_pairs(nodes: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, m, n): pairs of ``nodes`` (node, size, root) of different roots that share a rare shingle.

    Shingles stand in order of how many of the nodes have them, or others of their tally: any order that
    all sets share loses nothing. Sets of m and n shingles at similarity
    0.8 share 4/9 of m + n or more; so some shared one stands among the first m, and n, less that
    many and one more. A set's first fifth and one more is looked at, then both sizes narrow the places.
    """

    chosen = nodes.select("node", "root")
    held = sets.join(chosen, "node").select("node", "root", "found")

    def tally(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        many = np.zeros(TALLIES, np.int64)
        for batch in batches:
            for found in batch.column(0):
                many += np.bincount(np.frombuffer(found.as_buffer(), np.uint64) % np.uint64(TALLIES), minlength=TALLIES)
        used = np.flatnonzero(many)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(many[used])], ["at", "many"])

    many = np.zeros(TALLIES, np.int64)
    counts = held.select("found").mapInArrow(tally, "at long, many long").groupBy("at").agg(F.sum("many").alias("many")).toPandas()
    many[counts["at"].to_numpy(np.int64)] = counts["many"].to_numpy(np.int64)
    tallies = sets.sparkSession.sparkContext.broadcast(many)

    def first_places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for node, root, found in zip(*(batch.column(c) for c in range(3))):
                grams = np.frombuffer(found.as_buffer(), np.uint64)
                n = len(grams)
                looked_at = n - -(-n * LEAST[0] // LEAST[1]) + 1
                rare = grams[np.lexsort((grams, tallies.value[grams % np.uint64(TALLIES)]))[:looked_at]].view(np.int64)
                same = lambda v: pa.array(np.full(len(rare), v, np.int64))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(rare), pa.array(np.arange(1, len(rare) + 1)), same(node.as_py()), same(n), same(root.as_py())],
                    ["gram", "place", "node", "size", "root"],
                )

    rare = cut(held.mapInArrow(first_places, "gram long, place long, node long, size long, root long"))
    both = LEAST[0] + LEAST[1]
    shared = F.expr(f"((p.size + q.size) * {LEAST[0]} + {both - 1}) div {both}")
    early = (F.col("p.place") + shared <= F.col("p.size") + 1) & (F.col("q.place") + shared <= F.col("q.size") + 1)
    return (
        rare.alias("p")
        .join(rare.alias("q"), "gram")
        .where("p.node < q.node and p.root <> q.root")
        .where(early)
        .select(F.col("p.node").alias("a"), F.col("q.node").alias("b"), F.col("p.size").alias("m"), F.col("q.size").alias("n"))
    )


def _mixed(named: DataFrame) -> DataFrame:
    """Rows (key, node, size, root) of the bands that hold nodes of several roots."""
    several = named.groupBy("key").agg(F.min("root").alias("low"), F.max("root").alias("high")).where("low <> high")
    return named.join(several.select("key"), "key", "left_semi").select("key", "node", "size", "root")


def _roots(found: DataFrame) -> DataFrame:
    """(node, root): the smallest node that each node of the written links ``found`` (a, b) reaches.

    Few links are followed on the driver; star contraction would write and deal them in every round.
    """
    if found.count() > FEW_LINKS:
        return cut(components(found).distinct())
    links_here, parent = found.select("a", "b").toArrow(), {}

    def root(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = parent[up]
            x = up
        return x

    for a, b in zip(*(links_here.column(c).to_pylist() for c in ("a", "b"))):
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    nodes = sorted(parent)
    columns = [pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())]
    return found.sparkSession.createDataFrame(pa.Table.from_arrays(columns, ["node", "root"]))


def _apart(shared: DataFrame, roots: DataFrame) -> DataFrame:
    """Rows of ``shared`` under the ``roots`` that the links found so far give, in bands of several roots."""
    named = shared.drop("root").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    return cut(_mixed(named))


def _joined(roots: DataFrame, links: DataFrame) -> DataFrame:
    """``links`` and one link for each node that has a root already, which stand for all links found before."""
    return roots.where("node <> root").select(F.col("root").alias("a"), F.col("node").alias("b")).unionByName(links)


def near_copies(docs: DataFrame, hot_band: int = HOT_BAND) -> DataFrame:
    """(doc_id, content, component) for every row of ``docs`` (doc_id, text, ...).

    ``content`` is a hash of the text; rows that similar pairs connect have one ``component``.
    Null texts count as empty, and texts without words are copies of each other.
    """
    spark = docs.sparkSession
    with settings(spark, spark__sql__classic__shuffleDependency__fileCleanup__enabled="true", **HINTED_ONLY):
        return _near_copies(docs, hot_band)


def _print_pairs(nodes: DataFrame) -> DataFrame:
    """(a, b, m, n): ``nodes`` (node, size, print) whose fingerprints link, through one node of each fingerprint."""
    prints = cut(nodes.groupBy("print").agg(F.min(F.struct("node", "size")).alias("first")))
    near = links(prints.select(F.col("print").alias("fp")))
    one = lambda side: prints.select(F.col("print").alias(side), F.col("first").alias(f"{side}_first"))
    across = near.join(one("a"), "a").join(one("b"), "b").select("a_first", "b_first")
    same = nodes.join(prints, "print").where("node <> first.node").select(F.struct("node", "size").alias("a_first"), F.col("first").alias("b_first"))
    return across.unionByName(same).select(
        F.col("a_first.node").alias("a"), F.col("b_first.node").alias("b"), F.col("a_first.size").alias("m"), F.col("b_first.size").alias("n")
    )


def _near_copies(docs: DataFrame, hot_band: int) -> DataFrame:
    rows = cut(_nodes(docs))
    # the node of a sequence of words is the smallest hash of the texts that have it
    nodes = cut(rows.groupBy("words").agg(F.min(F.struct("content", "size", "print", "bands")).alias("n")).select("words", F.col("n.content").alias("node"), "n.size", "n.print", "n.bands"))
    keyed = nodes.select("node", "size", F.explode("bands").alias("key")).distinct()
    shared = cut(_mixed(keyed.withColumn("root", F.col("node"))))
    printed = cut(_sized(_print_pairs(nodes.where("size > 0"))))
    needed = shared.select("node").unionByName(printed.select(F.explode(F.array("a", "b")).alias("node"))).distinct()
    sets = cut(_sets(docs, needed))
    hot_bands = hot_keys(shared, "key")
    roots = _roots(cut(_checked(printed, sets)))
    apart = _apart(shared, roots)
    for round_no in range(ROUNDS):
        rank = F.xxhash64(F.lit(round_no), "key", "node")
        hubs = apart.groupBy("key").agg(F.min(F.struct(rank.alias("rank"), "node", "size", "root")).alias("hub"))
        met = join_hot(apart, hubs, "key", hot_bands).where("root <> hub.root")
        pairs = met.select(F.col("hub.node").alias("a"), F.col("node").alias("b"), F.col("hub.size").alias("m"), F.col("size").alias("n"))
        # written: every later use would check the pairs again
        roots = _roots(_joined(roots, cut(_checked(_sized(pairs), sets))))
        apart = _apart(shared, roots)
    hot = cut(apart.groupBy("key").agg(F.count("*").alias("many")).where(F.col("many") > hot_band).select("key"))
    cool = apart
    if not hot.isEmpty():
        cool = apart.join(hot, "key", "left_anti")
    second = (
        cool.alias("p")
        .join(cool.alias("q"), "key")
        .where("p.node < q.node and p.root <> q.root")
        .select(F.col("p.node").alias("a"), F.col("q.node").alias("b"), F.col("p.size").alias("m"), F.col("q.size").alias("n"))
    )
    if not hot.isEmpty():
        crowded = cut(apart.join(hot, "key", "left_semi").select("node", "size", "root").distinct())
        second = second.unionByName(_rare_pairs(crowded, sets))
    roots = _roots(_joined(roots, cut(_checked(_sized(second), sets))))
    labels = nodes.join(roots, "node", "left").select("words", F.coalesce("root", "node").alias("component"))
    return rows.join(labels, "words").select("doc_id", "content", "component")


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` with one row of each group of near copies: the one of smallest doc_id, null last."""
    return survivors(docs, near_copies(docs))
