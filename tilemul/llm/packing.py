"""Best-fit packing of tokenized documents with certified bin counts.

Texts become token ids, longer documents are cut into full pieces, and only the remainders
need packing. Every partition packs its own pieces by best-fit decreasing and certifies the
number of bins with lower bounds from dual-feasible functions. Where a partition misses its bound
all its bins with room are opened, elsewhere only bins with much room; the pieces of opened bins are
exchanged between fewer partitions and packed again, until one partition of bounded size
is left. Every sequence carries the certificate of the partition that settled it.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, whole

SEQUENCE = 1024
END_ID = 2
#: Pieces that one partition packs: so few that even a small table has many partitions.
PIECES_PER_PARTITION = 4000
#: Rounds at most; each leaves the pieces of a few bins per partition, so few are ever needed.
ROUNDS = 12
#: A settled partition gives up bins with this share of room or more.
ROOMY = 1 / 16
#: Up to so many partitions each get a task of their own; more are dealt by hash, which is even then.
OWN_TASKS = 20_000

class Encoder:
    """Ids of the byte-level BPE in a ``tokenizers`` file, the same as that library gives.

    Where ids follow the order of merges, texts of plain Latin characters go to ``tiktoken``
    with the same vocabulary and pattern, which is several times faster. Other texts, and texts
    with a special token's string in them, are encoded by ``tokenizers`` itself.
    """

    def __init__(self, path: str) -> None:
        import json
        import os
        import re

        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        import tiktoken

        self.path, self.slow, self.fast = path, None, None
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        special = [re.escape(t["content"]) for t in spec.get("added_tokens", [])]
        self.odd = re.compile("|".join([r"[^\t\n\r\x20-\x7e\xa1-\u024f]", *special]))
        model = spec["model"]
        merged = ["".join(m.split(" ") if isinstance(m, str) else m) for m in model.get("merges", [])]
        if all(model["vocab"].get(m) == 256 + i for i, m in enumerate(merged)) and (
            spec["pre_tokenizer"] or {}
        ).get("type") == "ByteLevel":
            octets = _printable_octets()
            taken = {t["id"] for t in spec.get("added_tokens", [])}
            self.fast = tiktoken.Encoding(
                "plain",
                pat_str=PATTERN,
                mergeable_ranks={
                    bytes(octets[c] for c in word): i for word, i in model["vocab"].items() if i not in taken
                },
                special_tokens={},
            )

    def ids(self, text: str) -> np.ndarray:
        """Ids of a whole text as unsigned little-endian 32-bit numbers."""
        if self.fast is not None and not self.odd.search(text):
            return self.fast.encode_to_numpy(text, disallowed_special=()).astype("<u4", copy=False)
        if self.slow is None:  # most workers never need it
            from tokenizers import Tokenizer

            self.slow = Tokenizer.from_file(self.path)
        return np.array(self.slow.encode(text, add_special_tokens=False).ids, dtype="<u4")


#: Fixed value: how byte-level BPE of this family cuts a text before merging.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def _printable_octets() -> dict[str, int]:
    """The printable characters that stand for the 256 octets in byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


_PIECE_DDL = "doc_id long, piece int, start long, length long, ids binary"


def pieces(docs: DataFrame, tokenizer: str | None = None, sequence: int = SEQUENCE) -> DataFrame:
    """(doc_id, piece, start, length, ids BINARY) for every document of ``docs``.

    A document is its token ids and the end id, as little-endian unsigned 32-bit numbers. One of more
    than ``sequence`` ids is cut into pieces of that length, the first of which takes the remainder.
    A null or empty text is the end id alone. Repeated rows each get their pieces; other columns
    are ignored.
    """
    path = tokenizer or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(path)
        for batch in batches:
            columns: list[list] = [[], [], [], [], []]
            for doc_id, text in zip(batch.column(0), batch.column(1)):
                doc_id, ids = doc_id.as_py(), np.append(encoder.ids(text.as_py()), np.uint32(END_ID)).astype("<u4")
                first = len(ids) % sequence or sequence
                ends = [first, *range(first + sequence, len(ids) + 1, sequence)]
                for n, end in enumerate(ends):
                    start = ends[n - 1] if n else 0
                    for column, value in zip(columns, (doc_id, n, start, end - start, ids[start:end].tobytes())):
                        column.append(value)
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, k) for c, k in zip(columns, kinds)], ["doc_id", "piece", "start", "length", "ids"]
            )

    return docs.select(F.col("doc_id").cast("long"), whole().alias("text")).mapInArrow(run, _PIECE_DDL)


def crc_of_ids() -> Column:
    """The digest of a piece's ids: CRC-32 of their octets, unsigned."""
    return F.crc32("ids").alias("ids_crc32")


def lower_bound(counts: np.ndarray, sequence: int = SEQUENCE) -> int:
    """Fewest bins that any packing of pieces needs; ``counts[n]`` pieces have length n.

    The largest over a family of dual-feasible functions: for a threshold t up to half of the
    bin, pieces over ``sequence - t`` count as a bin, pieces under t as nothing, the others by
    their length; and for k parts, lengths rounded down to multiples of 1/(k+1) of a bin
    unless exact.
    """
    lengths = np.arange(sequence + 1)
    best = -(-int(counts @ lengths) // sequence)
    amount = np.cumsum(counts * lengths)
    number = np.cumsum(counts)
    for t in range(1, sequence // 2 + 1):
        middle = int(amount[sequence - t] - amount[t - 1])
        best = max(best, int(number[sequence] - number[sequence - t]) + -(-middle // sequence))
    for k in range(1, 101):
        scaled = lengths * (k + 1)
        value = np.where(scaled % sequence == 0, lengths * k, (scaled // sequence) * sequence)
        best = max(best, -(-int(counts @ value) // (k * sequence)))
    return best


def best_fit_decreasing(lengths: np.ndarray, sequence: int = SEQUENCE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bin of each piece, offset of each piece in its bin, free room of each bin)."""
    order = np.argsort(-lengths, kind="stable")
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)
    rooms: list[int] = []
    by_room: list[list[int]] = [[] for _ in range(sequence + 1)]
    open_rooms = 0  # bit r is set where a bin with room r is open
    for i, n in zip(order.tolist(), lengths[order].tolist()):
        fits = open_rooms >> n
        if fits:
            room = n + (fits & -fits).bit_length() - 1
            at = by_room[room].pop()
            if not by_room[room]:
                open_rooms ^= 1 << room
        else:
            room, at = sequence, len(rooms)
            rooms.append(sequence)
        bins[i], offsets[i] = at, sequence - room
        room -= n
        rooms[at] = room
        if room:
            by_room[room].append(at)
            open_rooms |= 1 << room
    return bins, offsets, np.array(rooms, dtype=np.int64)


_PACKED_DDL = "row long, length long, part int, bin long, offset long, room long, bins long, bound long"


def _pack_partitions(parts: DataFrame, many: int, sequence: int) -> DataFrame:
    """Each partition packed by itself, with its number of bins and its certified bound."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["length", "row"], ascending=[False, True])
        lengths = rows["length"].to_numpy(np.int64)
        bins, offsets, rooms = best_fit_decreasing(lengths, sequence)
        bound = lower_bound(np.bincount(lengths, minlength=sequence + 1), sequence)
        return rows.assign(bin=bins, offset=offsets, room=rooms[bins], bins=len(rooms), bound=bound)

    if many <= OWN_TASKS:
        parts = parts.repartitionById(many, F.col("part"))
    return parts.groupBy("part").applyInPandas(run, _PACKED_DDL)


def pack(
    some: DataFrame,
    sequence: int = SEQUENCE,
    pieces_per_partition: int = PIECES_PER_PARTITION,
    rounds: int = ROUNDS,
) -> DataFrame:
    """``some`` pieces with sequence_id, offset, round, part_bins and part_bound, in as few sequences as found.

    ``some`` has a column ``length`` from 1 to ``sequence``; all its columns stay. Full pieces are
    sequences of their own. The rest is dealt to partitions at random and packed; a partition
    that reaches its bound keeps all its bins but roomy ones, another one only its full bins, and
    the others' pieces go, over fewer partitions, into the next round. ``round`` says when a sequence
    was settled, ``part_bins`` and ``part_bound`` are the bins and the lower bound of its partition
    then. Ties and repeated rows are pieces of their own; an empty table gives an empty result.
    """
    kept = cut(some.withColumn("row", F.monotonically_increasing_id()))
    rest = kept.where(F.col("length") < sequence).select("row", "length")
    done: DataFrame | None = None
    for round_no in range(rounds):
        n = rest.count()
        if n == 0:
            break
        parts = max(1, -(-n // pieces_per_partition))
        part = F.pmod(F.xxhash64("row", F.lit(round_no)), F.lit(parts)).cast("int")
        packed = cut(_pack_partitions(rest.select("row", "length", part.alias("part")), parts, sequence))
        last = parts == 1 or round_no == rounds - 1
        opened = (F.col("room") > 0) & ((F.col("bins") > F.col("bound")) | (F.col("room") >= sequence * ROOMY))
        settled = (packed if last else packed.where(~opened)).withColumn("round", F.lit(round_no))
        done = settled if done is None else done.unionByName(settled)
        if last:
            break
        rest = packed.where(opened).select("row", "length")
    certificate = ["sequence_id", "offset", "round", "part_bins", "part_bound"]
    # a full piece is settled before the first round; its number is negative, all others' are not
    alone = kept.where(F.col("length") == sequence).select(
        *some.columns, (-1 - F.col("row")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"),
        F.lit(-1).alias("round"), F.lit(1).cast("long").alias("part_bins"), F.lit(1).cast("long").alias("part_bound"),
    )
    if done is None:
        return alone
    # a sequence's number: round and partition above, bin below
    number = F.shiftleft(F.col("round").cast("long"), 58) + F.shiftleft(F.col("part").cast("long"), 27) + F.col("bin")
    placed = done.select("row", number.alias("sequence_id"), "offset", "round", F.col("bins").alias("part_bins"), F.col("bound").alias("part_bound"))
    return kept.where(F.col("length") < sequence).join(placed, "row").select(*some.columns, *certificate).unionByName(alone)
