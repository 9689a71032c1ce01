"""The engine from SQL text: fixture views, functions, and products as statements."""

from __future__ import annotations

from pyspark.sql import SparkSession

from .functions import udfs
from .sources import tables

FIXTURES = ("order_part", "supp_part", "cust_supp", "nation_trade", "user_follow", "user_event", "copurchase", "banded", "doc_term", "emb_graph")
_GATHER = {
    "plus_times": "sum(a.v * b.v)",
    "or_and": "max(if(a.v <> 0 and b.v <> 0, 1L, 0L))",
    "min_plus": "min(a.v + b.v)",
    "max_min": "max(least(a.v, b.v))",
    "plus_pair": "count(*)",
}
#: Join hints that ask Spark for the placement a strategy has.
_HINTS = {"plain": "", "c": "/*+ SHUFFLE_HASH(b) */ ", "a": "/*+ BROADCAST(b) */ ", "b": "/*+ BROADCAST(a) */ ", "merge": "/*+ MERGE(a, b) */ "}


def register(spark: SparkSession, sf_dir: str) -> dict[str, tuple[int, int]]:
    """Views (i, j, v) of the fixtures and the engine's functions; returns dimensions by view."""
    udfs.register(spark)
    dims = {}
    for name in FIXTURES:
        a = getattr(tables, name)(spark, sf_dir)
        a.df.createOrReplaceTempView(name)
        dims[name] = (a.rows, a.cols)
    return dims


def multiply_sql(a: str, b: str, strategy: str = "plain", ring: str = "plus_times", mask: str | None = None) -> str:
    """The statement that multiplies two views (i, j, v).

    Strategies differ in join hints only: ``a`` and ``b`` broadcast the other operand and so
    keep the named one where it is; use them where that operand is known to be small.
    """
    if strategy not in _HINTS or ring not in _GATHER:
        raise ValueError(f"no strategy {strategy!r} or semiring {ring!r}")
    kept = f" JOIN {mask} m ON m.i = a.i AND m.j = b.j" if mask else ""
    return f"SELECT {_HINTS[strategy]}a.i AS i, b.j AS j, {_GATHER[ring]} AS v FROM {a} a JOIN {b} b ON a.j = b.i{kept} GROUP BY a.i, b.j"
