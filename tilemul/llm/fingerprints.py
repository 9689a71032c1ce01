"""Document fingerprints by winnowing.

Every window of ``window`` consecutive k-gram hashes gives its minimum, the rightmost one of
equal minima; the chosen hashes with their positions are the fingerprint. Two texts that share
``window + k - 1`` consecutive code points share a chosen hash, and no shared run shorter than
``k`` is ever reported.

The edited texts of the query need each document's successor. Documents are dealt into ranges
of doc_id once, each range gets a copy of the document that follows it, and a task streams its
ranges in order: one shuffle of the texts, no window over a single partition.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import whole

K_GRAM = 24
WINDOW = 40
#: Documents in a range; the ranges are what a task reads in order.
ROWS_PER_RANGE = 2000
#: Ranges at most; more rows make longer ranges, which are streamed, not held.
MAX_RANGES = 20_000

_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


def gram_hashes(codes: np.ndarray, k: int = K_GRAM) -> np.ndarray:
    """32-bit hashes of all k-grams of code points; a shorter text is one gram."""
    n = len(codes)
    if n == 0:
        return np.empty(0, dtype=np.uint64)
    k = min(k, n)
    rolled, length, power = codes.astype(np.uint64) + np.uint64(1), 1, _BASE
    result, covered = None, 0
    while True:  # grams of length 1, 2, 4, ..., joined for the bits of k
        if k & length:
            if result is None:
                result, covered = rolled, length
            else:
                m = n - covered - length + 1
                result = result[:m] * np.uint64(power) + rolled[covered : covered + m]
                covered += length
        if covered == k:
            break
        m = n - 2 * length + 1
        rolled = rolled[:m] * np.uint64(power) + rolled[length : length + m]
        power = power * power & _MASK
        length *= 2
    result = result ^ (result >> np.uint64(32))
    result = result * np.uint64(0xD6E8FEB86659FD93)
    return result >> np.uint64(32)


def winnow(codes: np.ndarray, k: int = K_GRAM, window: int = WINDOW) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, positions) chosen from an array of code points, by position."""
    hashes = gram_hashes(codes, k)
    n = len(hashes)
    if n == 0:
        return hashes, np.empty(0, dtype=np.int64)
    # the low half makes equal hashes at later positions smaller: the rightmost wins
    low = (hashes << np.uint64(32)) | np.arange(0xFFFFFFFF, 0xFFFFFFFF - n, -1, dtype=np.uint64)
    window, length = min(window, n), 1
    while 2 * length <= window:
        low = np.minimum(low[:-length], low[length:])
        length *= 2
    if length < window:
        low = np.minimum(low[: length - window or None], low[window - length :])
    chosen = low[np.r_[True, low[1:] != low[:-1]]]
    return chosen >> np.uint64(32), 0xFFFFFFFF - (chosen & np.uint64(0xFFFFFFFF)).astype(np.int64)


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard likeness of two sets of hashes; two empty sets are alike."""
    a, b = np.unique(a), np.unique(b)
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both) if len(a) + len(b) else 1.0


def spelled(hashes: np.ndarray) -> str:
    """Hashes as eight hex digits each, by position."""
    return hashes.astype(">u4").tobytes().hex()


def fingerprints(docs: DataFrame, k: int = K_GRAM, window: int = WINDOW) -> DataFrame:
    """(doc_id, hashes ARRAY<LONG>, positions ARRAY<LONG>) for every row of ``docs``.

    Positions are code points from 0. A null or empty text has empty arrays, a text shorter
    than ``k`` one hash of all of it. Repeated rows each get a row; other columns are ignored.
    """
    if k < 1 or window < 1:
        raise ValueError("k and window are at least 1")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [winnow(code_points(t.as_py()), k, window) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0).cast(pa.int64()),
                    pa.array([h.astype(np.int64) for h, _ in found], pa.list_(pa.int64())),
                    pa.array([p for _, p in found], pa.list_(pa.int64())),
                ],
                ["doc_id", "hashes", "positions"],
            )

    return docs.select(F.col("doc_id").cast("long"), whole().alias("text")).mapInArrow(
        run, "doc_id long, hashes array<long>, positions array<long>"
    )


class _Compare:
    """Streams documents in order and yields one row for each that has met its successor."""

    def __init__(self, k: int, window: int) -> None:
        self.k, self.window, self.rows = k, window, []
        self.held: tuple | None = None

    def add(self, at: int, guest: bool, doc_id: int | None, text: str) -> None:
        if self.held and self.held[0] == at:
            codes = code_points(text)
            found = winnow(codes, self.k, self.window)
            self._meet(codes, found)
            self.held = None if guest else (at, doc_id, text, codes, found)
        elif not guest:
            codes = code_points(text)
            self.held = (at, doc_id, text, codes, winnow(codes, self.k, self.window))

    def _meet(self, codes: np.ndarray, found: tuple[np.ndarray, np.ndarray]) -> None:
        _, doc_id, _, own, own_found = self.held
        half = len(own) // 2
        edited = np.concatenate([own[: len(own) - half], codes[:half]])
        edited_found = winnow(edited, self.k, self.window)
        text = edited.tobytes().decode("utf-32-le", "surrogatepass").encode("utf-8", "surrogatepass")
        self.rows.append(
            (
                doc_id,
                len(own),
                hashlib.sha256(text).hexdigest(),
                spelled(own_found[0]),
                spelled(edited_found[0]),
                likeness(own_found[0], edited_found[0]),
                likeness(own_found[0], found[0]),
                own_found[1].astype(np.int32),
                edited_found[1].astype(np.int32),
            )
        )

    def flush(self) -> pa.RecordBatch:
        rows, self.rows = self.rows, []
        return pa.RecordBatch.from_pylist([dict(zip(_RESULT.names, r)) for r in rows], schema=_RESULT)


_RESULT = pa.schema(
    [
        ("doc_id", pa.int64()),
        ("n_chars", pa.int64()),
        ("edited_sha256", pa.string()),
        ("fingerprint", pa.string()),
        ("edited_fingerprint", pa.string()),
        ("near_edited", pa.float64()),
        ("near_next", pa.float64()),
        ("positions", pa.list_(pa.int32())),
        ("edited_positions", pa.list_(pa.int32())),
    ]
)
_RESULT_DDL = (
    "doc_id long, n_chars long, edited_sha256 string, fingerprint string, "
    "edited_fingerprint string, near_edited double, near_next double, positions array<int>, edited_positions array<int>"
)
_LEAST = -(1 << 63)


def compare_with_edits(
    docs: DataFrame, k: int = K_GRAM, window: int = WINDOW, rows_per_range: int = ROWS_PER_RANGE
) -> DataFrame:
    """Each text's fingerprint, that of its edited text, how alike they are, and where the chosen grams start.

    The edited text is the text with its last floor(n/2) code points replaced by the first as
    many of the next document in descending doc_id (null last; after the last the first; equal
    ids by text). A null text is empty. A single document is its own successor. Repeated rows
    each get a row. An empty table gives an empty result; other columns are ignored.
    """
    spark = docs.sparkSession
    order = F.coalesce(F.col("doc_id").cast("long"), F.lit(_LEAST))
    ids = docs.select(order.alias("id"))
    n = ids.count()
    if n == 0:
        return spark.createDataFrame([], _RESULT_DDL)
    ranges = max(1, min(MAX_RANGES, -(-n // rows_per_range)))
    cuts = np.unique(
        np.array(
            ids.select(
                F.percentile_approx("id", [i / ranges for i in range(1, ranges)] or [0.5], 100_000)
            ).first()[0],
            dtype=np.int64,
        )
    )

    @F.pandas_udf("long")
    def range_of(id: pd.Series) -> pd.Series:
        return pd.Series(len(cuts) - np.searchsorted(cuts, id.to_numpy(), side="right"))

    # the first document of each range follows the last one of the range before
    heads = dict(
        ids.select(range_of("id").alias("at"), "id").groupBy("at").agg(F.max("id")).collect()
    )
    full = sorted(heads)
    guest_of = {heads[b]: a for a, b in zip(full, full[1:] + full[:1])}
    head_ids = np.array(sorted(guest_of), dtype=np.int64)
    guest_at = np.array([guest_of[h] for h in head_ids.tolist()], dtype=np.int64)

    @F.pandas_udf("array<long>")
    def places(id: pd.Series) -> pd.Series:
        values = id.to_numpy()
        own = len(cuts) - np.searchsorted(cuts, values, side="right")
        slot = np.minimum(np.searchsorted(head_ids, values), len(head_ids) - 1)
        also = np.where(head_ids[slot] == values, guest_at[slot], -1)
        return pd.Series([[o] if a < 0 else [o, a] for o, a in zip(own.tolist(), also.tolist())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = _Compare(k, window)
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                state.add(*row)
                if len(state.rows) >= 256:
                    yield state.flush()
        yield state.flush()

    dealt = (
        docs.select(F.col("doc_id").cast("long"), whole().alias("text"), order.alias("id"))
        .select("doc_id", "text", "id", F.posexplode(places("id")).alias("guest", "at"))
        .select(F.col("at"), (F.col("guest") == 1).alias("guest"), "doc_id", "text", "id")
    )
    return (
        dealt.repartitionById(len(full), F.pmod(F.col("at"), F.lit(len(full))).cast("int"))
        .sortWithinPartitions("at", "guest", F.desc("id"), "text")
        .select("at", "guest", "doc_id", "text")
        .mapInArrow(run, _RESULT_DDL)
    )
