"""What the corpus operators share: cutting lineage, reading tables, joins with hot keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialise

#: Settings for loops of many joins. On small tables Spark would broadcast nearly every side of every round, each with
#: pages of its own on the driver; with these only the few rows that a hint names go that way.
HINTED_ONLY = {"spark__sql__autoBroadcastJoinThreshold": "-1", "spark__sql__adaptive__autoBroadcastJoinThreshold": "-1"}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table of a data folder; the path goes to Spark's reader unopened."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """``df`` written once to the reliable checkpoint folder and read from there; see ``session``."""
    return materialise(df)


def whole(name: str = "text") -> Column:
    """A text column with null as the empty text."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def lower_ascii(text: Column) -> Column:
    """A-Z lower-cased, every other code point left alone (locale-free)."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


#: The repository's definition of a word: anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

#: A key is hot where it holds more than one in so many of all rows: fewer than this many keys can.
HOT_SHARE = 1000


def hot_keys(df: DataFrame, key: str, share: int = HOT_SHARE) -> DataFrame:
    """(key) of the keys that hold more than one row in ``share``: fewer than ``share`` rows.

    Counted with map-side sums over all of ``df``; the bound on the rows does not depend on the
    data, so the table may be broadcast.
    """
    sizes = cut(df.groupBy(key).agg(F.count("*").alias("n")))
    total = sizes.agg(F.sum("n")).first()[0] or 0
    return cut(sizes.where(F.col("n") * share > total).select(key))


def join_hot(left: DataFrame, right: DataFrame, key: str, hot: DataFrame) -> DataFrame:
    """Inner join of ``left`` with ``right``, which has one row per key.

    Rows of hot keys stay where they are and meet a broadcast of fewer than ``HOT_SHARE`` rows;
    the rest are joined by shuffle, so that no task gets all rows of a hot key.
    """
    few = right.join(F.broadcast(hot), key, "left_semi")
    spread = left.join(F.broadcast(few), key)
    rest = left.join(F.broadcast(hot), key, "left_anti").join(right, key)
    return spread.unionByName(rest)
