"""Measured runs: seconds by number of workers, and what an event log says of a run."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window


def seconds(df: DataFrame) -> float:
    """Seconds to compute a result without keeping it."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def strong_scaling(spark: SparkSession, run: Callable[[int], DataFrame], workers: list[int], label: str = "run") -> DataFrame:
    """(label, p, seconds, speedup, efficiency) of one problem on growing numbers of workers."""
    rows = [(label, p, seconds(run(p))) for p in workers]
    return speedups(spark.createDataFrame(rows, "label string, p int, seconds double"), "seconds", ["label"])


def speedups(runs: DataFrame, time_column: str, series: list[str]) -> DataFrame:
    """Adds speedup and efficiency against the smallest p of each series."""
    by = Window.partitionBy(*series).orderBy("p")
    work = F.first_value(time_column).over(by) * F.first_value("p").over(by)
    return runs.select("*", (work / F.col(time_column)).alias("speedup"), (work / F.col(time_column) / F.col("p")).alias("efficiency"))


_TASK = """struct<Event:string,`Stage ID`:int,`Task Info`:struct<`Launch Time`:bigint,`Finish Time`:bigint>,`Task Metrics`:struct<
`Executor CPU Time`:bigint,`Executor Run Time`:bigint,`Disk Bytes Spilled`:bigint,`Peak Execution Memory`:bigint,
`Shuffle Read Metrics`:struct<`Fetch Wait Time`:bigint,`Remote Bytes Read`:bigint,`Local Bytes Read`:bigint>,
`Shuffle Write Metrics`:struct<`Shuffle Bytes Written`:bigint>>>"""


def task_log(spark: SparkSession, path: str) -> DataFrame:
    """One row per finished task of an event log."""
    events = spark.read.text(path).where("value like '{\"Event\":\"SparkListenerTaskEnd\"%'")
    t = F.from_json("value", _TASK.replace("\n", " "))
    rows = events.select(t.alias("t"))
    m = "t.`Task Metrics`"
    return rows.select(
        F.col("t.`Stage ID`").alias("stage"),
        (F.col("t.`Task Info`.`Finish Time`") - F.col("t.`Task Info`.`Launch Time`")).alias("millis"),
        (F.col(f"{m}.`Executor CPU Time`") / 1e6).alias("cpu_millis"),
        F.col(f"{m}.`Shuffle Read Metrics`.`Fetch Wait Time`").alias("wait_millis"),
        (F.col(f"{m}.`Shuffle Read Metrics`.`Remote Bytes Read`") + F.col(f"{m}.`Shuffle Read Metrics`.`Local Bytes Read`")).alias("read_bytes"),
        F.col(f"{m}.`Shuffle Write Metrics`.`Shuffle Bytes Written`").alias("written_bytes"),
        F.col(f"{m}.`Disk Bytes Spilled`").alias("spilled_bytes"),
        F.col(f"{m}.`Peak Execution Memory`").alias("peak_bytes"),
    )


def shuffle_stats(tasks: DataFrame) -> DataFrame:
    """(stage, tasks, comp, comm, load_imb, shuffle_bytes, spilled_bytes, skew) of each stage, seconds."""
    return tasks.groupBy("stage").agg(
        F.count("*").alias("tasks"),
        (F.avg("cpu_millis") / 1000).alias("comp"),
        (F.avg("wait_millis") / 1000).alias("comm"),
        ((F.max("millis") - F.avg("millis")) / 1000).alias("load_imb"),
        F.sum("written_bytes").alias("shuffle_bytes"),
        F.sum("spilled_bytes").alias("spilled_bytes"),
        (F.max("millis") / F.avg("millis")).alias("skew"),
    )
