"""Segments: sorted arrays of band keys, cut into shards that lie at the same place in every segment.

A segment is a Parquet table of one row for each (band, shard): the shard's keys, sorted, without
duplicates, eight bytes each in one binary value. A shard is a range of keys (their leading bits),
the same in all segments of a generation, and tables are bucketed by (band, shard). So a probe or
a merge joins rows that already lie together: no shuffle of history, and as many rows as there are
shards, whatever the number of keys. Work on keys is numpy on sorted arrays: binary search, merge.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup.config import DedupConfig

SCHEMA = "band int, shard int, n int, keys binary"
ON = ["band", "shard"]
#: Inputs up to which a merge is one chain of bucketed joins; more are dealt out by a shuffle.
JOINED = 16


def shard_of(config: DedupConfig):
    """The leading bits of a key (portable keys have 60 bits, others all 64)."""
    width = 60 if config.family == "portable31" else 64
    return F.shiftrightunsigned("key", width - config.shard_bits).cast("int")


def _packer(tagged: bool):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by (tag,) band, shard and key, each shard with a null key first."""
        names = [*(["tag_no"] if tagged else []), "band", "shard"]
        now, held, done = None, [], []

        def close() -> None:
            if now is not None:
                keys = np.unique(np.concatenate(held)) if held else np.zeros(0, dtype="<i8")
                done.append((*now, len(keys), keys.astype("<i8").tobytes()))

        def out() -> pa.RecordBatch:
            columns = list(zip(*done, strict=True)) if done else [()] * (len(names) + 2)
            kinds = [pa.int32()] * (len(names) + 1) + [pa.binary()]
            batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[*names, "n", "keys"])
            done.clear()
            return batch

        size = 0
        for batch in batches:
            where = [batch.column(n).to_numpy() for n in names]
            key = batch.column("key")
            cuts = np.flatnonzero(np.any([np.diff(w) != 0 for w in where], axis=0)) + 1
            edges = [0, *cuts.tolist(), len(batch)]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if a == b:
                    continue
                this = tuple(int(w[a]) for w in where)
                if this != now:
                    close()
                    now, held = this, []
                held.append(key.slice(a, b - a).drop_null().to_numpy(zero_copy_only=False))
                size += b - a
            if size > 1 << 20:
                size = 0
                yield out()
        close()
        yield out()

    return pack


def packed(keys: DataFrame, config: DedupConfig, tags: list[int] | None = None) -> DataFrame:
    """(tag_no,) band, shard, n, keys of the distinct keys; keys: (tag_no,) band, key. Empty shards have a row."""
    spark = keys.sparkSession
    named = [] if tags is None else ["tag_no"]
    cells = spark.range(config.bands << config.shard_bits).select((F.col("id") % config.bands).cast("int").alias("band"), F.floor(F.col("id") / config.bands).cast("int").alias("shard"), F.lit(None).cast("long").alias("key"))
    if tags is not None:
        cells = cells.withColumn("tag_no", F.explode(F.array(*[F.lit(t) for t in tags])))
    rows = keys.select(*named, F.col("band").cast("int"), shard_of(config).alias("shard"), "key").unionByName(cells)
    placed = rows.repartition(config.buckets, *ON).sortWithinPartitions(*named, *ON, "key")
    return placed.mapInArrow(_packer(tags is not None), ("tag_no int, " if named else "") + SCHEMA)


def save(rows: DataFrame, path: str, config: DedupConfig, by: str | None = None) -> None:
    """Writes packed rows as a bucketed table at path (in folders by a column, if given)."""
    name = f"seg_{uuid.uuid4().hex}"
    writer = rows.write.format("parquet").bucketBy(config.buckets, *ON).sortBy(*ON).option("path", path)
    (writer.partitionBy(by) if by else writer).saveAsTable(name)
    rows.sparkSession.sql(f"DROP TABLE {name}")  # an external table: the files stay


def load(spark: SparkSession, path: str, config: DedupConfig) -> DataFrame:
    """The bucketed table at path, known to the session's catalog by a name that follows from the path."""
    name = f"seg_{uuid.uuid5(uuid.NAMESPACE_URL, path).hex}"
    place = path.replace("'", "\\'")
    spark.sql(f"CREATE TABLE IF NOT EXISTS {name} ({SCHEMA}) USING parquet CLUSTERED BY (band, shard) SORTED BY (band, shard) INTO {config.buckets} BUCKETS LOCATION '{place}'")
    return spark.table(name)


def _search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Binary search of each shard's asked keys in its held ones: band, key of those found."""
    for batch in batches:
        bands, found = [], []
        for band, asked, held in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2), strict=True):
            x, y = np.frombuffer(asked.as_buffer(), dtype="<i8"), np.frombuffer(held.as_buffer(), dtype="<i8")
            if len(x) and len(y):
                x = x[np.searchsorted(x, y[0]) : np.searchsorted(x, y[-1], side="right")]
                hit = x[y[np.searchsorted(y, x)] == x] if len(x) else x
                bands.append(np.full(len(hit), band, dtype=np.int32))
                found.append(hit)
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(bands) if bands else [], pa.int32()), pa.array(np.concatenate(found) if found else [], pa.int64())], names=["band", "key"])


def probe(asked: DataFrame, held: DataFrame, hint: str | None = None) -> DataFrame:
    """band, key of the asked segment's keys that the held segment has. Both are bucketed alike: nothing is shuffled."""
    x = asked.where("n > 0").select(*ON, F.col("keys").alias("asked"))
    y = held.where("n > 0").select(*ON, F.col("keys").alias("held"))
    both = (x.hint(hint) if hint else x).join(y, ON)
    return both.select("band", "asked", "held").mapInArrow(_search, "band int, key long")


def _merger(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """band, shard and the sorted arrays of each input; their union, one shard in memory at a time."""
    for batch in batches:
        arrays = [batch.column(i) for i in range(2, batch.num_columns)]
        sizes, merged = [], []
        for row in range(len(batch)):
            parts = [np.frombuffer(c[row].as_buffer(), dtype="<i8") for c in arrays]
            keys = np.concatenate(parts)
            keys.sort(kind="stable")  # runs that are sorted already are merged
            keys = keys[np.concatenate([[True], keys[1:] != keys[:-1]])] if len(keys) else keys
            sizes.append(len(keys))
            merged.append(keys.tobytes())
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sizes, pa.int32()), pa.array(merged, pa.binary())], names=["band", "shard", "n", "keys"])


def _dealt_merger(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same for rows of many inputs that come sorted by band and shard; holds a union and one input."""
    now, keys = None, np.zeros(0, dtype="<i8")

    def row() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([now[0]], pa.int32()), pa.array([now[1]], pa.int32()), pa.array([len(keys)], pa.int32()), pa.array([keys.tobytes()], pa.binary())], names=["band", "shard", "n", "keys"])

    for batch in batches:
        for band, shard, part in zip(batch.column("band").to_pylist(), batch.column("shard").to_pylist(), batch.column("keys"), strict=True):
            if (band, shard) != now:
                if now is not None:
                    yield row()
                now, keys = (band, shard), np.zeros(0, dtype="<i8")
            keys = np.union1d(keys, np.frombuffer(part.as_buffer(), dtype="<i8"))
    if now is not None:
        yield row()


def merged(inputs: list[DataFrame], config: DedupConfig, path: str | None = None) -> DataFrame:
    """The union of segments, packed. path: joined (no shuffle) or dealt; by default joined up to JOINED inputs."""
    if path == "joined" or (path is None and len(inputs) <= JOINED):
        out = inputs[0].select(*ON, F.col("keys").alias("keys_0"))
        for i, s in enumerate(inputs[1:], 1):
            out = out.join(s.select(*ON, F.col("keys").alias(f"keys_{i}")).hint("merge"), ON)
        return out.mapInArrow(_merger, SCHEMA)
    every = inputs[0].select(*ON, "keys")
    for s in inputs[1:]:
        every = every.unionAll(s.select(*ON, "keys"))
    # dealt by a struct of the two: Spark 4.1 takes a union of tables bucketed by them for dealt already
    # and drops a repartition by band and shard, but then reads the tables unbucketed
    return every.repartition(config.buckets, F.struct(*ON)).sortWithinPartitions(*ON).mapInArrow(_dealt_merger, SCHEMA)


def _unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        parts = [np.frombuffer(k.as_buffer(), dtype="<i8") for k in batch.column(1)]
        band = np.repeat(batch.column(0).to_numpy(), [len(p) for p in parts])
        yield pa.RecordBatch.from_arrays([pa.array(band, pa.int32()), pa.array(np.concatenate(parts) if parts else [], pa.int64())], names=["band", "key"])


def unpacked(rows: DataFrame) -> DataFrame:
    """band, key, one row each."""
    return rows.select("band", "keys").mapInArrow(_unpack, "band int, key long")
