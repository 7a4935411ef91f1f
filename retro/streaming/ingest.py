"""Streaming ingestion of statement logs: deduplicated micro-batches become read/write elements, effects, rates and last writers."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def log_stream(spark: SparkSession, path: str, schema: StructType | str, files_a_batch: int = 4) -> DataFrame:
    """A log of parquet files in a folder, or of the one file that `path` names."""
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_a_batch)
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(place).isFile():
        return reader.option("pathGlobFilter", place.getName()).parquet(place.getParent().toString())
    return reader.parquet(path)


def deduplicated(stream: DataFrame, key: str = "txn_id", late: str = "1 hour") -> DataFrame:
    """A record that is delivered again within the watermark counts once; later records belong to a repair batch."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def rates(stream: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, kind, n) for tumbling or sliding windows."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", late).groupBy(window.alias("w"), F.col("kind")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "kind", "n")


def sessions(stream: DataFrame, key: str, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), F.col(key)).agg(F.count("*").alias("n")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def last_writers(spark: SparkSession, stream: DataFrame, path: str, checkpoint: str) -> None:
    """Appends each micro-batch's effects and keeps the last writer of each cell, idempotently: a batch overwrites its own folder only."""

    def save(batch: DataFrame, number: int) -> None:
        batch.groupBy("tbl", "row_key", "col").agg(F.max_by("val", "idx").alias("val"), F.max("idx").alias("idx")).write.mode("overwrite").parquet(f"{path}/batch={number}")

    run_available(stream, save, checkpoint)


def run_available(stream: DataFrame, save: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    stream.writeStream.foreachBatch(save).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def to_parquet(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Writes a stream's results for what is available now."""
    if mode == "append":
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
    else:
        run = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
        run.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(path)).start().awaitTermination()
