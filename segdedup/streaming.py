"""Releases from a stream: a micro-batch is a release, its tag follows from the batch id.

A batch that is repeated after a crash has the same id, hence the same tag: its segment is
replaced and not screened, so the state is the same.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup.index import Index


def ingest_stream(index: Index, source: DataFrame, checkpoint: str, prefix: str = "s"):
    """Starts a query that ingests each micro-batch; source: a stream of doc_id, text."""

    def batch(df: DataFrame, number: int) -> None:
        index.ingest(df, f"{prefix}{number}")

    return source.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events*")


def tumbling(stream: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width)).agg(F.count(F.lit(1)).alias("n"))


def sliding(stream: DataFrame, width: str = "1 day", step: str = "6 hours", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
