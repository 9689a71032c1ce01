"""Exact top-k by inner product with multi-resolution segment statistics.

A vector's segments are summed up by their means and deviations. For two vectors the squared
distance is at least the sum over segments of length times (difference of means squared plus
difference of deviations squared); with both norms known that bounds the inner product from
above. Bounds go from coarse segments to fine ones, a running k-th best score prunes, and
only survivors are computed whole, in exact integers.

Vectors are packed into blocks of bounded size. Query blocks meet candidate blocks, each pair
gives at most k rows per query, and a ranked window keeps the k best.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import cut

K = 20
SCALE = 64
QUERY_BLOCK, CANDIDATE_BLOCK = 4096, 8192
#: Copies of the query blocks, so that many tasks share the work of one.
SALTS = 24
#: Segments of the coarse and the fine level.
LEVELS = (4, 16)
_AT_ONCE = 256
#: Share of pairs above which survivors of the coarse bound are computed as one product.
DENSE = 0.05


class Segments:
    """Means and deviations of the segments of many vectors at one resolution."""

    def __init__(self, vectors: np.ndarray, segments: int) -> None:
        dim = vectors.shape[1]
        cuts = np.linspace(0, dim, min(segments, dim) + 1).astype(int)[:-1] if dim else np.zeros(0, int)
        lengths = np.diff(np.append(cuts, dim)).astype(float)
        if dim:
            mean = np.add.reduceat(vectors, cuts, axis=1) / lengths
            square = np.add.reduceat(vectors * vectors, cuts, axis=1) / lengths
        else:
            mean = square = np.zeros((len(vectors), 0))
        deviation = np.sqrt(np.maximum(square - mean * mean, 0.0))
        self.both = np.concatenate([mean, deviation], axis=1)
        self.weighted = self.both * np.concatenate([lengths, lengths])


#: Doubles hold whole numbers up to here, and longs up to there, without rounding.
_DOUBLE, _LONG = 2.0**52, 2.0**62


class _Exact:
    """Inner products of whole numbers, by the narrowest arithmetic that does not round.

    Vectors are doubles that hold whole numbers. Where sums of products fit doubles, doubles are
    used, else longs, else Python's integers of any size. A score that a caller is given must
    fit a long; one that does not is an error.
    """

    def __init__(self, asked: np.ndarray, points: np.ndarray) -> None:
        self.most = float(np.abs(points).max(initial=0)) * float(np.abs(asked).max(initial=0)) * max(1, points.shape[1])
        self.kind = np.dtype(float) if self.most < _DOUBLE else np.dtype(np.int64) if self.most < _LONG else np.dtype(object)
        self.asked, self.points = self._as(asked), self._as(points)

    def _as(self, x: np.ndarray) -> np.ndarray:
        if self.kind != object:
            return x.astype(self.kind)
        return np.array([[int(v) for v in row] for row in x.tolist()], dtype=object).reshape(x.shape)

    def pairs(self, q: np.ndarray, c: np.ndarray) -> np.ndarray:
        """Scores of pairs (query row, candidate row)."""
        if self.kind != object:
            out = np.empty(len(q), dtype=np.int64)
            for at in range(0, len(q), 1 << 16):
                part = slice(at, at + (1 << 16))
                out[part] = np.einsum("pd,pd->p", self.asked[q[part]], self.points[c[part]])
            return out
        return np.array([int(self.asked[i] @ self.points[j]) if self.points.shape[1] else 0 for i, j in zip(q.tolist(), c.tolist())], dtype=object)

    def product(self, first: int, last: int) -> np.ndarray:
        return (self.asked[first:last] @ self.points.T).astype(np.int64)


def best_of_block(
    query_rows: np.ndarray, queries: np.ndarray, rows: np.ndarray, ids: np.ndarray, vectors: np.ndarray, k: int = K, levels: tuple[int, ...] = LEVELS
) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(query row, ids, scores) of the k best of a block for each query, ties to smaller ids.

    Vectors are doubles that hold whole numbers; ``rows`` number vectors, since ids may repeat, and
    the candidate of the query's own row takes no part.
    """
    order = np.argsort(ids, kind="stable")
    rows, ids, points = rows[order], ids[order], vectors[order].astype(float)
    asked = queries.astype(float)
    exact = _Exact(asked, points)
    theirs = [Segments(points, n) for n in levels]
    slack = 1e-9 * (1.0 + exact.most)
    for at in range(0, len(asked), _AT_ONCE):
        some = asked[at : at + _AT_ONCE]
        mine = [Segments(some, n) for n in levels]
        own = query_rows[at : at + _AT_ONCE, None] == rows[None, :]
        bound = mine[0].weighted @ theirs[0].both.T
        bound[own] = -np.inf
        # the k best by bound give a first k-th score
        take = min(k + 1, len(ids))
        lead = np.argpartition(-bound, take - 1, axis=1)[:, :take]
        scored = np.einsum("qd,qcd->qc", some, points[lead])
        scored[np.take_along_axis(own, lead, 1)] = -np.inf
        least = np.sort(scored, axis=1)[:, ::-1][:, min(k, take) - 1] if take >= k else np.full(len(some), -np.inf)
        least = least - 2 * slack
        alive = (bound >= least[:, None]) & ~own
        if exact.kind != object and np.count_nonzero(alive) > DENSE * alive.size:
            # little is pruned: one product of matrices is cheaper than pairs one by one
            whole = exact.product(at, at + len(some))
            for q in range(len(some)):
                at_c = np.flatnonzero(alive[q])
                yield int(query_rows[at + q]), *_first(ids[at_c], whole[q, at_c], k)
            continue
        alive_q, alive_c = np.nonzero(alive)
        for my, their in zip(mine[1:], theirs[1:]):
            fine = np.empty(len(alive_q))
            for part in range(0, len(alive_q), 1 << 16):
                s = slice(part, part + (1 << 16))
                fine[s] = np.einsum("ps,ps->p", my.weighted[alive_q[s]], their.both[alive_c[s]])
            keep = fine >= least[alive_q]
            alive_q, alive_c = alive_q[keep], alive_c[keep]
        scores = exact.pairs(alive_q + at, alive_c)
        ends = np.searchsorted(alive_q, np.arange(len(some) + 1))
        for q in range(len(some)):
            own_part = slice(ends[q], ends[q + 1])
            yield int(query_rows[at + q]), *_first(ids[alive_c[own_part]], scores[own_part], k)


def _first(ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k best of scores whose ids are in order, ties to smaller ids."""
    if scores.dtype == object:
        top = np.array(sorted(range(len(scores)), key=lambda n: -scores[n])[:k], dtype=int)
        if any(not -(1 << 63) <= s < 1 << 63 for s in scores[top]):
            raise OverflowError("an inner product among the best does not fit a 64-bit score")
        return ids[top], scores[top].astype(np.int64)
    if len(scores) > k:
        least = np.partition(scores, len(scores) - k)[len(scores) - k]
        near = np.flatnonzero(scores >= least)
        ids, scores = ids[near], scores[near]
    top = np.argsort(-scores, kind="stable")[:k]
    return ids[top], scores[top]


def taking_part(vectors: DataFrame) -> DataFrame:
    """(row, vec_id, v): numbered vectors without those null or holding null or non-finite components."""
    finite = F.forall("embedding", lambda x: F.coalesce(F.abs(x) < F.lit(float("inf")), F.lit(False)) & ~F.isnan(x))
    return (
        vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v"), finite.alias("finite"))
        .where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & F.col("finite"))
        .select(F.monotonically_increasing_id().alias("row"), "vec_id", "v")
    )


_BLOCK_DDL = "block int, dim int, rows binary, ids binary, vectors binary"


def _packed(matrix: np.ndarray) -> bytes:
    """Whole numbers as 32-bit integers where they fit, else as doubles."""
    if np.abs(matrix).max(initial=0) < 1 << 31:
        return matrix.astype("<i4").tobytes()
    return matrix.astype("<f8").tobytes()


def _unpacked(octets: bytes, count: int, dim: int) -> np.ndarray:
    wide = len(octets) > 4 * count * dim
    return np.frombuffer(octets, "<f8" if wide else "<i4").reshape(count, dim)


def _blocks(vectors: DataFrame, blocks: int, scale: int) -> DataFrame:
    """Vectors floor(scale * x) packed into rows, dealt at random; one row for each dimension in a block."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        dims = rows["v"].map(len)
        packed = []
        for dim, some in rows.groupby(dims):
            matrix = np.concatenate(some["v"].to_list()).astype(float) if dim else np.zeros(0)
            scaled = np.floor(matrix * scale)
            if not np.isfinite(scaled).all():
                raise OverflowError("a scaled component does not fit a double")
            packed.append(
                (rows["block"].iloc[0], dim, some["row"].to_numpy("<i8").tobytes(), some["vec_id"].to_numpy("<i8").tobytes(), _packed(scaled))
            )
        return pd.DataFrame(packed, columns=["block", "dim", "rows", "ids", "vectors"])

    dealt = vectors.withColumn("block", F.pmod(F.xxhash64("row"), F.lit(blocks)).cast("int"))
    return dealt.groupBy("block").applyInPandas(run, _BLOCK_DDL)


def top_k(vectors: DataFrame, is_query: str, k: int = K, scale: int = SCALE, levels: tuple[int, ...] = LEVELS) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` best inner products of every query.

    ``is_query``: SQL condition on vec_id. Candidates are all other rows of the same dimension,
    also such as repeat the query's id; ties go to the smaller vec_id. A query id that repeats
    has the results of each of its rows. Vectors null or with null or non-finite
    components, and rows with a null id, take no part. Fewer than ``k`` candidates: all of them.
    Scores are exact for components of any size; one that does not fit a long is an error. An
    empty table gives an empty result. Other columns are ignored.
    """
    rows = cut(taking_part(vectors))
    n, asked = rows.agg(F.count("*"), F.count_if(F.expr(is_query))).first()
    query_blocks = max(1, -(-asked // QUERY_BLOCK))
    candidates = _blocks(rows, max(1, -(-n // CANDIDATE_BLOCK)), scale).select(
        F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))).alias("query_block"),
        F.pmod("block", F.lit(SALTS)).cast("int").alias("salt"),
        "dim",
        "rows",
        "ids",
        "vectors",
    )
    queries = _blocks(rows.where(is_query), query_blocks, scale).select(
        F.col("block").alias("query_block"),
        F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"),
        "dim",
        F.col("rows").alias("query_rows"),
        F.col("ids").alias("query_ids"),
        F.col("vectors").alias("queries"),
    )
    names = ("dim", "rows", "ids", "vectors", "query_rows", "query_ids", "queries")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = {name: batch.column(name)[i].as_py() for name in names}
                numbers, ids, query_rows, query_ids = (np.frombuffer(row[c], "<i8") for c in ("rows", "ids", "query_rows", "query_ids"))
                matrix = _unpacked(row["vectors"], len(ids), row["dim"])
                asked_matrix = _unpacked(row["queries"], len(query_ids), row["dim"])
                found = list(best_of_block(query_rows, asked_matrix, numbers, ids, matrix, k, levels))
                counts = [len(c) for _, c, _ in found]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.repeat([q for q, _, _ in found], counts).astype(np.int64)),
                        pa.array(np.repeat(query_ids, counts)),
                        pa.array(np.concatenate([c for _, c, _ in found])),
                        pa.array(np.concatenate([s for _, _, s in found])),
                    ],
                    ["query_row", "query_id", "vec_id", "score"],
                )

    pairs = candidates.join(queries, ["query_block", "salt", "dim"])
    partial = pairs.mapInArrow(run, "query_row long, query_id long, vec_id long, score long")
    best = Window.partitionBy("query_row").orderBy(F.desc("score"), "vec_id")
    return (
        partial.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
    )
