"""Streaming twins: incremental de-duplication, windows and running scores over a bounded or unbounded stream."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from crossaudit.functions.storage import shared_folder


def read_stream(spark: SparkSession, path: str, schema: StructType, ts: str | None = None) -> DataFrame:
    """A file stream with a declared schema; a time column without zone is cast, as watermarks need one."""
    folder, _, name = path.rstrip("/").rpartition("/")
    out = spark.readStream.schema(schema).option("pathGlobFilter", name).parquet(folder) if name.endswith(".parquet") else spark.readStream.schema(schema).parquet(path)
    return out.withColumn(ts, F.col(ts).cast("timestamp")) if ts else out


def tumbling(stream: DataFrame, every: str = "1 day", late: str = "40 days") -> DataFrame:
    """``start, event_type, n, total`` of tumbling windows."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", every), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(stream: DataFrame, every: str = "2 days", step: str = "1 day", late: str = "40 days") -> DataFrame:
    """``start, n`` of sliding windows."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", every, step)).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "12 hours", late: str = "40 days") -> DataFrame:
    """``user_id, start, n`` of sessions that end after a gap."""
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def first_arrivals(stream: DataFrame, keys: list[str], late: str = "40 days") -> DataFrame:
    """The first row of each key within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def running_score(stream: DataFrame) -> DataFrame:
    """``key, n, correct`` by key over ``key, truth, pred`` rows: a running confusion's totals, kept by Spark's own aggregation."""
    return stream.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("truth") == F.col("pred")).cast("long")).alias("correct"))


def drain(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Run a bounded stream to its end into Parquet in the shared folder; what it holds then, with ``batch`` in update mode.

    A batch that is written again after a failure replaces itself.
    """
    spark = stream.sparkSession
    where = f"{shared_folder(spark)}/stream-{name}-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/rows/batch={number}")

    q = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = spark.read.schema(StructType([*stream.schema.fields]).add("batch", "long")).parquet(f"{where}/rows")
    if mode == "complete":
        last = rows.agg(F.max("batch").alias("last"))  # one row
        rows = rows.join(F.broadcast(last), F.col("batch") == F.col("last")).drop("last")
    return rows if mode == "update" else rows.drop("batch")
