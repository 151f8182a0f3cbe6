"""How the given tables fall into releases."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch


def documents(spark: SparkSession, sf_dir: str, k: int = 40) -> DataFrame:
    """doc_id, text and release_no: 20 releases by source, or 40 with each halved by doc_id."""
    docs = scratch.spread(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    number = F.pmod("doc_id", F.lit(min(k, 20)))
    if k == 40:
        n = spark.read.parquet(f"{sf_dir}/documents.parquet").count()
        number = number + F.when(F.col("doc_id") >= n / 2, 20).otherwise(0)
    return docs.withColumn("release_no", number.cast("int"))


def key_stream(spark: SparkSession, sf_dir: str, k: int = 40, bands: int = 1, pool: int = 500) -> DataFrame:
    """Synthetic keys of lineitem rows: three in ten from a shared pool, the others novel."""
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    day = F.date_format("l_shipdate", "yyyy-MM-dd")
    whole = F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.col("l_quantity").cast("long"), F.round(F.col("l_extendedprice") * 100).cast("long"), day)
    hashed = lambda c: F.conv(F.substring(F.md5(c), 1, 15), 16, 10).cast("long")
    stream = rows.select(hashed(whole).alias("rid"), "l_partkey", F.pmod("l_orderkey", F.lit(k)).cast("int").alias("release_no"))
    banded = stream.withColumn("band", F.explode(F.sequence(F.lit(0), F.lit(bands - 1))))
    pooled = F.pmod("rid", F.lit(10)) < 3
    source = F.when(pooled, F.concat_ws("|", F.lit("p"), "band", F.pmod("l_partkey", F.lit(pool)))).otherwise(F.concat_ws("|", F.lit("n"), "band", "rid"))
    return banded.select("release_no", "rid", pooled.alias("pooled"), "band", hashed(source).alias("key"))
