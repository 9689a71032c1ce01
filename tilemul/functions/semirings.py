"""Semirings: how two entries are combined and how combined entries are gathered."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    times: Callable[[Column, Column], Column]
    plus: Callable[[Column], Column]
    #: The same pair for numpy kernels: elementwise times, and the ufunc that gathers.
    np_times: Callable
    np_plus: np.ufunc


SEMIRINGS = {
    "plus_times": Semiring(lambda a, b: a * b, F.sum, lambda a, b: a * b, np.add),
    "or_and": Semiring(
        lambda a, b: F.when((a != 0) & (b != 0), 1).otherwise(0).cast("long"),
        F.max,
        lambda a, b: ((a != 0) & (b != 0)).astype(a.dtype),
        np.maximum,
    ),
    "min_plus": Semiring(lambda a, b: a + b, F.min, lambda a, b: a + b, np.minimum),
    "max_min": Semiring(F.least, F.max, np.minimum, np.maximum),
    "plus_pair": Semiring(
        lambda a, b: F.lit(1).cast("long"), F.sum, lambda a, b: np.ones_like(a), np.add
    ),
}


def semiring(name: str) -> Semiring:
    try:
        return SEMIRINGS[name]
    except KeyError:
        raise ValueError(f"no semiring {name!r}; there are {', '.join(SEMIRINGS)}") from None
