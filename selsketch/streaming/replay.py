"""Replay of the events table as a stream, and sketches kept up to date batch by batch."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.sketch import signed
from ..store import shared_dir


def replayed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream (files of one directory, one table by name)."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    # zone-free times as UTC instants, whatever the session's zone
    return rows.withColumn("ts", F.timestamp_micros(F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts)")))


def collected(stream: DataFrame, mode: str) -> DataFrame:
    """Runs the stream over what is there now; the final result as a table in memory."""
    name = f"t{uuid.uuid4().hex}"
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_dir(stream.sparkSession)}/{name}").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def sketch_deltas(spark: SparkSession, sf_dir: str, width: int, reps: int) -> DataFrame:
    """Signed sketch of the stream: each micro-batch writes its own sketch, a linear sum merges them; a batch that is
    repeated after a failure overwrites its own file, so it counts once."""
    at = f"{shared_dir(spark)}/deltas-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        signed(batch, {"user_id": "cust"}, {"user_id": ["cust#0"]}, width, reps).write.mode("overwrite").parquet(f"{at}/batch={number}")

    q = replayed(spark, sf_dir).writeStream.foreachBatch(put).option("checkpointLocation", f"{at}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(at).groupBy("rep", "bin").agg(F.sum("val").alias("val")).where("val <> 0")
