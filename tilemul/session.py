"""Settings that the engine reads or changes for a while, and durable cuts of lineage."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


@contextmanager
def settings(spark: SparkSession, **values: str) -> Iterator[None]:
    """Runtime settings for the block, as they were afterwards; ``_`` stands for a dot."""
    before = {}
    for name, value in values.items():
        key = name.replace("__", ".")
        before[key] = spark.conf.get(key, None)
        spark.conf.set(key, value)
    try:
        yield
    finally:
        for key, value in before.items():
            if value is None:
                spark.conf.unset(key)
            else:
                spark.conf.set(key, value)


def scratch(spark: SparkSession) -> str:
    """The shared folder for written intermediates: the one that the cluster names.

    Only a local master, where all tasks share one machine, gets a folder of our own when none
    is named; elsewhere executors could not see it, so that is an error.
    """
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if folder:
        return folder
    if not context.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return tempfile.mkdtemp(prefix="tilemul-")


def materialise(df: DataFrame) -> DataFrame:
    """``df`` computed once and read back from reliable storage: a barrier, and a cut of lineage."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(scratch(df.sparkSession))
    return df.checkpoint(eager=True)
