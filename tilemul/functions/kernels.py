"""Local products and sums of tiles in numpy, for the tile backend.

A sparse tile is (row pointers, column indices, values); a dense one a 2-D array. Products are
row-wise: every entry of a row of A brings a row of B, and equal places are gathered by sorting.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np

from .semirings import Semiring, semiring


class Csr(NamedTuple):
    row_ptr: np.ndarray
    col_idx: np.ndarray
    vals: np.ndarray
    cols: int

    @property
    def rows(self) -> int:
        return len(self.row_ptr) - 1

    def row_numbers(self) -> np.ndarray:
        return np.repeat(np.arange(self.rows), np.diff(self.row_ptr))


def pack(rows: np.ndarray, cols: np.ndarray, vals: np.ndarray, n_rows: int, n_cols: int) -> Csr:
    """CSR of entries in any order; places are taken as unique."""
    order = np.lexsort((cols, rows))
    counts = np.bincount(rows, minlength=n_rows)
    return Csr(np.concatenate([[0], np.cumsum(counts)]).astype(np.int64), cols[order], vals[order], n_cols)


def _gather(rows: np.ndarray, cols: np.ndarray, vals: np.ndarray, width: int, r: Semiring) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    if not len(rows):
        return rows, cols, vals
    keys = rows.astype(np.int64) * width + cols
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[starts] // width, keys[starts] % width, r.np_plus.reduceat(vals[order], starts)


def csr_csr(a: Csr, b: Csr, ring: str = "plus_times") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows, columns, values) of A·B at all places that any pair of entries reaches."""
    r = semiring(ring)
    many = np.diff(b.row_ptr)[a.col_idx]
    rows = np.repeat(a.row_numbers(), many)
    first = np.repeat(b.row_ptr[a.col_idx] - np.concatenate([[0], np.cumsum(many)[:-1]]), many)
    at = first + np.arange(len(rows))
    vals = r.np_times(np.repeat(a.vals, many), b.vals[at])
    return _gather(rows, b.col_idx[at], vals, b.cols, r)


def csr_dense(a: Csr, b: np.ndarray) -> np.ndarray:
    """A·B for plus-times with a dense B."""
    out = np.zeros((a.rows, b.shape[1]), dtype=np.result_type(a.vals, b))
    if len(a.col_idx):
        filled = np.flatnonzero(np.diff(a.row_ptr))
        out[filled] = np.add.reduceat(a.vals[:, None] * b[a.col_idx], a.row_ptr[filled], axis=0)
    return out


def add_tiles(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]], width: int, ring: str = "plus_times") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sum of sparse partial results as (rows, columns, values)."""
    rows, cols, vals = (np.concatenate([p[n] for p in parts]) for n in range(3))
    return _gather(rows, cols, vals, width, semiring(ring))
