"""Mixing sources to target weights by a multivariate-hypergeometric splitting tree.

Each source is dealt into blocks of documents, and every pass over a source goes through its
blocks in a permuted order of its own. The words that a source must give fix its quota of block
draws: whole passes, then as many blocks of one more pass as fill the rest, the last of them cut.
A splitting tree divides all sources' quotas among the output shards by hypergeometric draws.
A shard draws its own stretch of each source's permuted blocks, disjoint from all others', and
orders the documents in it at random. What a document gives to the mix is the sum over the
shards that draw its block; a block that no shard draws gives nothing.

Only sums by source and block are gathered, in distributed tables; texts never move for it.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import WORD, cut, whole

#: Weights of the sources in order, repeated as often as needed.
WEIGHTS = (5.0, 2.0, 1.0)
#: Words of the mix as a multiple of all words, and most passes over a source.
SHARE, MOST = 1.5, 2.0
SEED = 20240229
SHARDS = 16
#: Documents in a block, on average.
BLOCK = 256
_SPACE = r"[\x20\x09-\x0D]"
#: Sources that one task of the splitting tree holds; more are split tree by tree.
SOURCES_PER_TREE = 10_000
#: Tables of at most so many rows about sources and their last blocks are broadcast; larger ones are joined by shuffle.
BROADCAST_ROWS = 500_000
#: Blocks in a chunk of the two-level running sum.
CHUNK = 4096
#: Fixed value: a prime above any number of blocks; multiplying by it permutes their numbers.
_PRIME = 1_500_450_271


def words_in(text: Column) -> Column:
    """Number of words of a text, as a long."""
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def targets(sizes: list[int], weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> list[float]:
    """Words that each source gives, for source sizes in order.

    The shared amount goes out by weight; a source that would pass ``most`` times its size
    stops there, and what is over is shared by weight among the others until none is above.
    """
    w = np.array([weights[i % len(weights)] for i in range(len(sizes))], dtype=float)
    cap = most * np.array(sizes, dtype=float)
    level = 0.0
    while len(w):
        over = w * level >= cap
        left = share * cap.sum() / most - cap[over].sum()
        if over.all() or left <= 0 or left / w[~over].sum() <= level:
            break
        level = left / w[~over].sum()
    return np.minimum(cap, w * level).tolist()


def split_quotas(quotas: np.ndarray, shards: int, seed: int = SEED) -> np.ndarray:
    """(shards, sources) whole numbers that add up to ``quotas``, shards of even size.

    A node of the tree with several shards draws, without replacement, the part of its first
    half from all its blocks at once, so each shard's mixture is that of a random sample.
    """
    out = np.zeros((shards, len(quotas)), dtype=np.int64)

    def node(counts: np.ndarray, first: int, many: int) -> None:
        if many == 1:
            out[first] = counts
            return
        left = many // 2
        generator = np.random.default_rng([seed, first, many])
        total = int(counts.sum())
        draw = total * left // many
        part = np.zeros(len(counts), dtype=np.int64)
        rest = total
        for s, n in enumerate(counts.tolist()):  # marginals one source at a time
            take = generator.hypergeometric(n, rest - n, draw) if 0 < draw and n else 0
            part[s] = take
            rest, draw = rest - n, draw - int(take)
        node(part, first, left)
        node(counts - part, first + left, many - left)

    node(np.asarray(quotas, dtype=np.int64), 0, shards)
    return out


def _numbered(sources: DataFrame) -> tuple[DataFrame, int]:
    """``sources`` with ``source_no`` from 0 by code point, null last, and their number: ranges are counted, not gathered."""
    sources = cut(sources)
    n = sources.count()
    parts = max(1, -(-n // 200_000))
    ordered = sources.withColumn("none", F.col("source").isNull())
    if parts > 1:
        ordered = ordered.repartitionByRange(parts, "none", "source")
    else:
        ordered = ordered.coalesce(1)
    placed = cut(ordered.sortWithinPartitions("none", "source").withColumn("at", F.monotonically_increasing_id()))
    part = F.shiftright("at", 33)
    sizes = [(0, n)]
    if parts > 1:
        sizes = sorted((r["part"], r["n"]) for r in placed.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    before, total = F.lit(0).cast("long"), 0
    for p, many in sizes:  # one entry for each 200,000 sources
        before = F.when(part == p, F.lit(total)).otherwise(before)
        total += many
    number = before + F.col("at").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.select("source", "words", "docs", number.cast("long").alias("source_no")), n


def _with_targets(sources: DataFrame, weights: tuple[float, ...], share: float, most: float) -> DataFrame:
    """``sources`` with their targets: the water level rises until no source is above its stop."""
    weight = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod("source_no", F.lit(len(weights))) + 1).cast("int"))
    table = sources.withColumn("w", weight).withColumn("cap", F.col("words") * float(most))
    level = 0.0
    while True:
        over = F.col("w") * F.lit(level) >= F.col("cap")
        total, stopped, free = table.agg(F.sum("words"), F.sum(F.when(over, F.col("cap"))), F.sum(F.when(~over, F.col("w")))).first()
        left = share * (total or 0) - (stopped or 0.0)
        if not free or left <= 0 or left / free <= level:
            break
        level = left / free
    return table.withColumn("target", F.least("cap", F.col("w") * F.lit(level)))


def _key(seed: int) -> list[Column]:
    """Two 64-bit hashes of a row's id, text and source, by which rows are told apart."""
    parts = [F.col("doc_id").cast("string"), F.col("doc_id").isNull(), whole(), F.col("source"), F.col("source").isNull()]
    return [F.xxhash64(F.lit(seed + n), *parts).alias(f"key{n}") for n in range(2)]


def _rank(block: Column, passes: Column, seed: int) -> Column:
    """Place of a block in the permuted order of one pass over its source."""
    shift = F.pmod(F.xxhash64(F.lit(seed), F.col("source_no"), passes.cast("long")), F.col("blocks"))
    return F.pmod(block * _PRIME + shift, F.col("blocks"))


class Plan:
    """What the mix takes of a table: per source its draws, and shares of rows in cut blocks.

    sources: (source, source_no, source_size, target, blocks, passes, whole_blocks, quota, ends):
    ``quota`` draws are ``passes`` times all blocks and one more pass's first blocks, of which
    ``whole_blocks`` are whole and one may be cut; shard s has draws ends[s-1] to ends[s].
    shares: (source_no, key0, key1, share): words that each row with that key gives to its cut block.
    """

    def __init__(self, sources: DataFrame, many: int, shares: DataFrame, shards: int, seed: int) -> None:
        self.sources, self.many, self.shares, self.shards, self.seed = sources, many, shares, shards, seed


def plan(
    docs: DataFrame,
    weights: tuple[float, ...] = WEIGHTS,
    share: float = SHARE,
    most: float = MOST,
    shards: int = SHARDS,
    seed: int = SEED,
    block: int = BLOCK,
) -> Plan:
    """The mix of ``docs`` (doc_id, text, source, ...).

    Sources are ordered by code point, null last; a null source is one like any other. Targets
    are met to the word by cutting the last block of a source: its rows, ordered by their hash,
    give whole texts until the words are full, the next one its first words. Rows that agree in
    id, text and source share what is left for them evenly, so a target may be missed by fewer
    words than such copies. Null and empty texts have no words. An empty table gives an empty mix.
    """
    keys = _key(seed)
    sized = cut(docs.select(*keys, "source", words_in(whole()).alias("size")))
    totals = sized.groupBy("source").agg(F.sum("size").alias("words"), F.count("*").alias("docs"))
    numbered, many = _numbered(totals)
    table = _with_targets(numbered, weights, share, most)
    passes = F.when(F.col("words") > 0, F.least(F.floor(F.col("target") / F.col("words")), F.lit(int(most)))).otherwise(0)
    blocks = F.greatest(F.lit(1), F.ceil(F.col("docs") / block))
    table = table.select(
        "source", "source_no", "words", "target", blocks.cast("long").alias("blocks"), passes.cast("long").alias("passes")
    ).withColumn("over", F.round(F.col("target") - F.col("passes") * F.col("words")).cast("long"))
    # words of each block, in the permuted order of the pass that is not taken whole
    rows = _with_source(sized, table, many).withColumn("block", F.pmod("key0", F.col("blocks")))
    by_rank = cut(
        rows.withColumn("rank", _rank(F.col("block"), F.col("passes"), seed))
        .groupBy("source_no", "rank", "over")
        .agg(F.sum("size").alias("s"))
        .where("s > 0")
        .withColumn("chunk", F.expr(f"rank div {CHUNK}"))
    )
    last = _crossing(by_rank).select("source_no", "rank", "before")
    with_last = table.join(last, "source_no", "left")
    cut_rank = F.when(F.col("over") > 0, F.col("rank"))
    quotas = with_last.select(
        "source", "source_no", F.col("words").alias("source_size"), "target", "blocks", "passes", cut_rank.alias("cut_rank"),
        F.when(F.col("over") > 0, F.col("over") - F.col("before")).otherwise(0).alias("left_over"),
        (F.col("passes") * F.col("blocks") + F.coalesce(cut_rank + 1, F.lit(0))).cast("long").alias("quota"),
    )
    sources = cut(quotas.join(_ends(quotas, shards, seed), "source_no"))
    # rows of each source's cut block, equal ones as one: what is left for them
    block_rows = (
        _with_source(sized, sources.select("source", "source_no", "blocks", "passes", "cut_rank", "left_over"), many)
        .where(F.col("cut_rank") == _rank(F.pmod("key0", F.col("blocks")), F.col("passes"), seed))
        .groupBy("source_no", "key0", "key1", "size", "left_over")
        .agg(F.count("*").alias("copies"))
    )
    before = Window.partitionBy("source_no").orderBy("key0", "key1").rowsBetween(Window.unboundedPreceding, -1)
    given = F.col("left_over") - F.coalesce(F.sum(F.col("size") * F.col("copies")).over(before), F.lit(0))
    each = F.floor(F.least(F.greatest(given, F.lit(0)) / F.col("copies"), F.col("size")))
    shares = cut(block_rows.withColumn("share", each.cast("long")).select("source_no", "key0", "key1", "share"))
    return Plan(sources, many, shares, shards, seed)


def _with_source(rows: DataFrame, table: DataFrame, many: int) -> DataFrame:
    """``rows`` with their source's columns; a small table is broadcast, skew of a large one is left to adaptive joins."""
    other = table.withColumnRenamed("source", "of_source")
    if many <= BROADCAST_ROWS:
        other = F.broadcast(other)
    return rows.join(other, F.col("source").eqNullSafe(F.col("of_source"))).drop("of_source")


def _crossing(by_rank: DataFrame) -> DataFrame:
    """(source_no, rank, before) of the block in which a source's running sum reaches ``over``.

    Sums of chunks are added up first, then blocks inside the one chunk that reaches it.
    """
    def running(name: str, order: str) -> Column:
        window = Window.partitionBy("source_no").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
        return F.coalesce(F.sum(name).over(window), F.lit(0))

    chunks = by_rank.groupBy("source_no", "chunk", "over").agg(F.sum("s").alias("s"))
    reached = (F.col("before") < F.col("over")) & (F.col("before") + F.col("s") >= F.col("over"))
    here = chunks.withColumn("before", running("s", "chunk")).where(reached).select("source_no", "chunk", F.col("before").alias("start"))
    inside = by_rank.join(here, ["source_no", "chunk"])
    return inside.withColumn("before", F.col("start") + running("s", "rank")).where(reached)


def _ends(quotas: DataFrame, shards: int, seed: int) -> DataFrame:
    """(source_no, ends ARRAY<LONG>): where each shard's stretch of a source's draws ends."""

    def tree(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("source_no")
        parts = split_quotas(rows["quota"].to_numpy(), shards, seed + int(rows["tree"].iloc[0]))
        return pd.DataFrame({"source_no": rows["source_no"], "ends": list(np.cumsum(parts, axis=0).T)})

    grouped = quotas.select("source_no", "quota", F.expr(f"source_no div {SOURCES_PER_TREE}").alias("tree"))
    return grouped.groupBy("tree").applyInPandas(tree, "source_no long, ends array<long>")


def with_draws(docs: DataFrame, mix_plan: Plan) -> DataFrame:
    """``docs`` with source_size, target and ``draws``: what shards take of each row.

    draws: array of (shard INT, pass INT, words LONG, place LONG), one for each shard and pass that
    draws the row's block and gets any words of it; ``place`` orders a shard. The columns key0 and
    key1 are added too. Rows stay where they are unless there are very many sources.
    """
    seed = mix_plan.seed
    keyed = docs.select("*", *_key(seed), words_in(whole()).alias("size"))
    rows = _with_source(keyed, mix_plan.sources, mix_plan.many).withColumn("block", F.pmod("key0", F.col("blocks")))
    shares = mix_plan.shares
    if shares.count() <= BROADCAST_ROWS:
        shares = F.broadcast(shares)
    rows = rows.join(shares, ["source_no", "key0", "key1"], "left")
    # the tree decides: a draw counts where its place lies in some shard's stretch
    ends = F.col("ends")

    def draw(p: Column) -> Column:
        rank = _rank(F.col("block"), p, seed)
        place = p * F.col("blocks") + rank
        shard = F.size(F.filter(ends, lambda e: e <= place))
        is_cut = (p == F.col("passes")) & F.coalesce(rank == F.col("cut_rank"), F.lit(False))
        words = F.when(is_cut, F.coalesce("share", F.lit(0))).otherwise(F.col("size"))
        return F.struct(
            shard.cast("int").alias("shard"),
            p.cast("int").alias("pass"),
            words.cast("long").alias("words"),
            F.xxhash64(F.lit(seed + 2), "key0", p.cast("long")).alias("place"),
        )

    drawn = F.filter(F.transform(F.sequence(F.lit(0).cast("long"), "passes"), draw), lambda d: (d["shard"] < mix_plan.shards) & (d["words"] > 0))
    return rows.withColumn("draws", drawn)


def taken_words(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, size, source_size, target, taken, shards) for every row of ``docs``; see ``plan``.

    ``taken`` adds up the shards' draws; ``shards`` lists them as shard:words, comma-joined.
    """
    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text"), "source")
    rows = with_draws(narrow, plan(narrow, **options))
    taken = F.aggregate("draws", F.lit(0).cast("long"), lambda total, d: total + d["words"])
    listed = F.transform("draws", lambda d: F.concat_ws(":", d["shard"].cast("string"), d["words"].cast("string")))
    return rows.select("doc_id", "size", "source_size", "target", taken.alias("taken"), F.array_join(listed, ",").alias("shards"))


def mixed(docs: DataFrame, **options) -> DataFrame:
    """``docs`` as the mix takes them: a row for each draw, cut to its words, in shuffled shards.

    All columns stay; ``n_chars``, where there is one, follows a cut text. Rows are dealt at
    random, and a partition holds each shard's rows as one run in the order of their places.
    """
    boxed = docs.select("doc_id", "text", "source", F.struct("*").alias("row"))
    drawn = with_draws(boxed, plan(docs, **options)).select("row", "size", F.explode("draws").alias("d"))
    # the first n words: white space and words in turn; possessive, so that Java loops and does not recurse
    pattern = F.concat(F.lit(f"^(?:{_SPACE}*+{WORD}+){{"), F.col("d.words").cast("string"), F.lit("}+"))
    first = F.call_function("regexp_extract", F.col("row.text"), pattern, F.lit(0))
    all_of_it = F.col("d.words") >= F.col("size")
    taken = drawn.select("row", "d.shard", "d.place", all_of_it.alias("whole"), F.when(all_of_it, F.col("row.text")).otherwise(first).alias("taken"))
    dealt = taken.repartition("shard", "place").sortWithinPartitions("shard", "place")
    fields = []
    for name in docs.columns:
        column = F.col(f"row.`{name}`")
        if name == "text":
            column = F.col("taken")
        elif name == "n_chars":
            column = F.when(F.col("whole"), column).otherwise(F.length("taken")).cast(docs.schema[name].dataType)
        fields.append(column.alias(name))
    return dealt.select(*fields)
