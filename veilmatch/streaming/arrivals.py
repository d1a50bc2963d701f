"""Arriving query records linked to a registry snapshot."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veilmatch.operators import match
from veilmatch.sources.tables import shared_folder

PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ON_DISK = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def events(spark: SparkSession, folder: str) -> DataFrame:
    """The events table as a file stream, with the schema of its footer."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def collected(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything a bounded stream gives, through a memory table in the driver; for tests and small reports."""
    name = f"s_{uuid.uuid4().hex}"
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def written(stream: DataFrame) -> DataFrame:
    """Everything a bounded stream appends, as Parquet in the shared folder: its rows never come to the driver, and its state is kept on disks."""
    spark = stream.sparkSession
    path = f"{shared_folder(spark)}/arrivals-{uuid.uuid4().hex}"
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    before = spark.conf.get(PROVIDER)
    spark.conf.set(PROVIDER, ON_DISK)
    try:
        query = stream.writeStream.outputMode("append").format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
        query.awaitTermination()
    finally:
        spark.conf.set(PROVIDER, before)
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def first_arrivals(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each event once, by its id within the watermark."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def by_window(stream: DataFrame, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    """(start, event_type, n): arrivals by tumbling window."""
    counts = stream.withWatermark("ts", delay).groupBy(F.window("ts", width), "event_type").count()
    return counts.select(F.col("window.start").alias("start"), "event_type", F.col("count").alias("n"))


def link_stream(stream: DataFrame, arriving: DataFrame, registry: DataFrame, tau_bp: int, path: str, key: str = "user_id") -> None:
    """Links each batch's records with the snapshot and writes them under ``path`` by batch, so that a repeated batch overwrites itself."""

    def one(batch: DataFrame, number: int) -> None:
        wanted = batch.select(F.col(key).alias("_k")).distinct()
        records = arriving.join(wanted, arriving["arrival_key"] == wanted["_k"]).drop("_k", "arrival_key")
        match.link_all(records, registry, tau_bp).write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.foreachBatch(one).trigger(availableNow=True).start().awaitTermination()
