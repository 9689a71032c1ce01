"""Products over windows of an event stream.

ΔC = ΔA·B: each window's new entries of A meet a static B, and sums are kept per place and
window until the watermark passes it. The same function takes a stream or a table.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..matrix import Matrix
from ..operators.products import BROADCAST_ENTRIES
from ..session import scratch
from ..sources.tables import event_code


def source(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """The events of a folder of Parquet files, or of one file, as a stream of their own schema.

    ``ts`` becomes a timestamp of the session's zone, which watermarks ask for.
    """
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = where.getFileSystem(spark._jsc.hadoopConfiguration())
    if not files.getFileStatus(where).isDirectory():  # a stream reads folders
        reader = reader.option("pathGlobFilter", where.getName())
        path = where.getParent().toString()
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def _static(b: Matrix) -> DataFrame:
    """The static operand, broadcast where its number of places is bounded by its shape."""
    df = b.df.select(F.col("i").alias("k"), "j", F.col("v").alias("b"))
    return F.broadcast(df) if b.rows * b.cols <= BROADCAST_ENTRIES else df


def delta_product(events: DataFrame, b: Matrix, width: str = "1 day", slide: str | None = None, watermark: str = "1 day") -> DataFrame:
    """(start, i, j, v): the product of each window's user × event-type counts with B."""
    entries = events.withWatermark("ts", watermark).select("ts", F.col("user_id").alias("i"), event_code().cast("long").alias("k"))
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    met = entries.join(_static(b), "k")
    sums = met.groupBy(window.alias("w"), "i", "j").agg(F.sum("b").cast("long").alias("v"))
    return sums.select(F.col("w.start").alias("start"), "i", "j", "v")


def sessions(events: DataFrame, gap: str = "6 hours", watermark: str = "1 day") -> DataFrame:
    """(user_id, start, finish, n): runs of a user's events without a gap."""
    grouped = events.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("finish"), "n")


def running_product(events: DataFrame, b: Matrix) -> DataFrame:
    """(i, j, v): the product over all events so far; for complete mode."""
    entries = events.select(F.col("user_id").alias("i"), event_code().cast("long").alias("k"))
    met = entries.join(_static(b), "k")
    return met.groupBy("i", "j").agg(F.sum("b").cast("long").alias("v"))


def purchases_after_clicks(events: DataFrame, within: str = "1 hour", watermark: str = "1 day") -> DataFrame:
    """(user_id, click_id, purchase_id): a purchase within a time after a click of the same user."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("u1"), F.col("event_id").alias("click_id"), F.col("ts").alias("t1"))
    buys = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("t2"))
    met = clicks.withWatermark("t1", watermark).join(
        buys.withWatermark("t2", watermark), F.expr(f"u1 = u2 and t2 >= t1 and t2 <= t1 + interval {within}")
    )
    return met.select(F.col("u1").alias("user_id"), "click_id", "purchase_id")


def deduplicated(events: DataFrame, watermark: str = "1 day") -> DataFrame:
    """Events without repeats of an id inside the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def run(result: DataFrame, mode: str = "append", folder: str | None = None, keys: list[str] | None = None) -> DataFrame:
    """All that a stream has by now, through ``availableNow``, in files.

    Append leaves out windows that the watermark has not passed. Update writes every batch's changed
    rows to a folder of its own, which a retry overwrites, and reads the latest row of each of
    ``keys``; state of windows that the watermark has passed is dropped. Running again with the same
    ``folder``, which holds the state and the files, goes on where the last run ended. Complete
    keeps all state, and every batch writes the whole result to a folder of its own, of which the last is read.
    """
    spark = result.sparkSession
    folder = folder or f"{scratch(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    writer = result.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{folder}/out").start().awaitTermination()
        return spark.read.schema(result.schema).parquet(f"{folder}/out")
    if mode == "update":
        if not keys:
            raise ValueError("update needs the keys that rows are latest of")
        put = lambda batch, n: batch.write.mode("overwrite").parquet(f"{folder}/out/batch={n}")
        writer.foreachBatch(put).start().awaitTermination()
        # a schema of its own: ``add`` would change the one that ``result`` keeps
        stored = StructType([*result.schema.fields, StructField("batch", LongType())])
        rows = spark.read.option("basePath", f"{folder}/out").schema(stored).parquet(f"{folder}/out")
        rest = [c for c in result.columns if c not in keys]
        latest = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("latest"))
        return latest.select(*(F.col(c) if c in keys else F.col(f"latest.{c}").alias(c) for c in result.columns))
    # every batch is the whole result, written by the tasks; a retry overwrites it, and an empty stream has none
    whole = lambda batch, n: batch.write.mode("overwrite").parquet(f"{folder}/out/batch={n}")
    writer.foreachBatch(whole).start().awaitTermination()
    done = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/out")
    files = done.getFileSystem(spark._jsc.hadoopConfiguration())
    batches = [int(f.getPath().getName().split("=")[1]) for f in files.listStatus(done)] if files.exists(done) else []
    if not batches:
        return spark.createDataFrame([], result.schema)
    return spark.read.schema(result.schema).parquet(f"{folder}/out/batch={max(batches)}")
