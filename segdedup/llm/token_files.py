"""Token ids in files of bit-plane shuffled, zstandard-compressed chunks.

A chunk holds the ids of whole consecutive documents (at least one, about CHUNK_IDS ids). Its
ids are cut into blocks of BLOCK_IDS; a block is transposed into byte planes (all low bytes,
then all next bytes ...) or bit planes, and each plane of a chunk is compressed by itself. High
planes are nearly constant and shrink to almost nothing. Per chunk the index has its file,
its place there, the first id, the number of ids, the sizes of the planes, a checksum, and of
each document the key and the number of ids, so any document can be read by decoding one chunk.

The container is Parquet with binary payloads (uncompressed: the planes already are), because
Spark's committers make its files whole or absent in any store, also when executors are lost.
encode_chunk and decode_chunk are independent of it.

Order: ascending doc_id, null doc_ids first, equal ones by text. A null or empty text is just
the end id, a very long one is a chunk of its own. Repeated rows are written as often as they
occur. An empty table gives no chunks. Columns other than doc_id and text are not looked at.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segdedup import scratch
from segdedup.llm import tokens

CHUNK_IDS, BLOCK_IDS, LEVEL, END_ID = 1 << 18, 1 << 16, 1, 2
VOCABULARY = "byte_bpe_50k.json"
CHUNK_SCHEMA = "file long, chunk long, n_ids long, width int, bits boolean, plane_bytes array<int>, payload binary, ids_crc32 long, doc_ids array<long>, doc_tokens array<int>"


def encode_chunk(ids: np.ndarray, bits: bool = False, block: int = BLOCK_IDS, level: int = LEVEL) -> tuple[int, list[int], bytes]:
    """width (planes), their compressed sizes, their bytes one after the other."""
    ids = np.ascontiguousarray(ids, dtype="<u4")
    top = int(ids.max()) if len(ids) else 0
    width = max(1, top.bit_length()) if bits else max(1, (top.bit_length() + 7) // 8)
    planes = [bytearray() for _ in range(width)]
    for at in range(0, len(ids), block):
        part = ids[at : at + block]
        if bits:
            for k in range(width):
                planes[k] += np.packbits((part >> k).astype(np.uint8) & 1).tobytes()
        else:
            low = part.view(np.uint8).reshape(-1, 4)
            for k in range(width):
                planes[k] += low[:, k].tobytes()
    compressor = zstandard.ZstdCompressor(level=level)
    packed = [compressor.compress(bytes(p)) for p in planes]
    return width, [len(p) for p in packed], b"".join(packed)


def decode_chunk(payload: bytes, n_ids: int, width: int, plane_bytes: list[int], bits: bool = False, block: int = BLOCK_IDS) -> np.ndarray:
    """The ids of a chunk, little-endian unsigned 32-bit."""
    ids = np.zeros(n_ids, dtype="<u4")
    view = ids.view(np.uint8).reshape(-1, 4)
    decompressor, at = zstandard.ZstdDecompressor(), 0
    for k, size in enumerate(plane_bytes[:width]):
        plane = np.frombuffer(decompressor.decompress(payload[at : at + size]), dtype=np.uint8)
        at += size
        if not bits:
            view[:, k] = plane
            continue
        start = 0
        for first in range(0, n_ids, block):
            n = min(block, n_ids - first)
            n_bytes = (n + 7) // 8
            ids[first : first + n] |= np.unpackbits(plane[start : start + n_bytes], count=n).astype("<u4") << k
            start += n_bytes
    return ids


def _chunk_writer(vocabulary: str, end_id: int, bits: bool):
    def write(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        encode, end = tokens.encoder(vocabulary), np.array([end_id], dtype="<u2")
        ids, keys, counts, held, number = [], [], [], 0, 0

        def chunk():
            nonlocal ids, keys, counts, held, number
            flat = np.concatenate(ids).astype("<u4")
            width, sizes, payload = encode_chunk(flat, bits)
            row = {"file": [part], "chunk": [number], "n_ids": [len(flat)], "width": [width], "bits": [bits], "plane_bytes": [sizes], "payload": [payload], "ids_crc32": [zlib.crc32(flat.tobytes())], "doc_ids": [keys], "doc_tokens": [counts]}
            ids, keys, counts, held, number = [], [], [], 0, number + 1
            return pa.RecordBatch.from_pydict(row, schema=ARROW)

        for batch in batches_:
            texts = batch.column("text").to_pylist()
            for key, got in zip(batch.column("doc_id").to_pylist(), tokens.batches(encode, texts), strict=True):
                ids += [got, end]
                keys.append(key)
                counts.append(len(got) + 1)
                held += len(got) + 1
                if held >= CHUNK_IDS:
                    yield chunk()
        if keys:
            yield chunk()

    return write


ARROW = pa.schema([("file", pa.int64()), ("chunk", pa.int64()), ("n_ids", pa.int64()), ("width", pa.int32()), ("bits", pa.bool_()), ("plane_bytes", pa.list_(pa.int32())), ("payload", pa.binary()), ("ids_crc32", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("doc_tokens", pa.list_(pa.int32()))])


def write(docs: DataFrame, path: str, vocabulary: str, end_id: int = END_ID, bits: bool = False) -> None:
    """Writes the ids of docs (doc_id, text) to path."""
    chunks = tokens.ordered(docs, tokens.partitions_for(docs.sparkSession)).mapInArrow(_chunk_writer(vocabulary, end_id, bits), CHUNK_SCHEMA)
    chunks.write.mode("overwrite").option("compression", "uncompressed").parquet(path)


def index(spark: SparkSession, path: str) -> DataFrame:
    """The chunk index without payloads, with each chunk's first id in the whole order."""
    chunks = spark.read.schema(CHUNK_SCHEMA).parquet(path)
    files = chunks.groupBy("file").agg(F.sum("n_ids").alias("file_ids"))
    before = files.select("file", (F.sum("file_ids").over(Window.orderBy("file")) - F.col("file_ids")).alias("file_start"))  # a row per file
    at = F.sum("n_ids").over(Window.partitionBy("file").orderBy("chunk")) - F.col("n_ids")
    starts = chunks.select("file", "chunk", "n_ids", at.alias("at")).join(F.broadcast(before), "file")  # of the number of shuffle partitions
    return starts.select("file", "chunk", "n_ids", (F.col("at") + F.col("file_start")).alias("start"))


def _doc_reader(batches_: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches_:
        for row in batch.to_pylist():
            ids = decode_chunk(row["payload"], row["n_ids"], row["width"], row["plane_bytes"], row["bits"])
            raw = ids.tobytes()
            if zlib.crc32(raw) != row["ids_crc32"]:
                raise ValueError(f"chunk {row['file']}/{row['chunk']}: its checksum differs")
            ends = np.cumsum(row["doc_tokens"])
            starts = ends - row["doc_tokens"]
            crcs = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
            n = len(crcs)
            yield pa.RecordBatch.from_arrays([pa.array([row["file"]] * n, pa.int64()), pa.array([row["chunk"]] * n, pa.int64()), pa.array(row["doc_ids"], pa.int64()), pa.array(starts, pa.int64()), pa.array(row["doc_tokens"], pa.int64()), pa.array(crcs, pa.int64())], names=["file", "chunk", "doc_id", "at", "n_tokens", "ids_crc32"])


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, decoded from the files."""
    docs = spark.read.schema(CHUNK_SCHEMA).parquet(path).mapInArrow(_doc_reader, "file long, chunk long, doc_id long, at long, n_tokens long, ids_crc32 long")
    places = index(spark, path).select("file", "chunk", F.col("start").alias("chunk_start"))
    return docs.join(places, ["file", "chunk"]).select("doc_id", (F.col("chunk_start") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def op4_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = scratch.new_path(spark, "token-files")
    write(scratch.table(spark, sf_dir, "documents"), path, public_tokenizers.path(VOCABULARY))
    return read(spark, path)


QUERIES = {"op4_token_files": op4_token_files}
ORACLE_SQL: dict[str, str] = {}
