"""From documents to band keys: normalise, shingle, MinHash, band.

The kernel runs in Arrow batches, one Python crossing a document; nothing is shuffled.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segdedup.config import PRIME, DedupConfig

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def normalise(text):
    """Column form: A-Z lowered, runs of ASCII white space one space, none at the ends."""
    return F.trim(F.regexp_replace(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), r"[\x20\x09-\x0D]+", " "))


def shingle_set(text: str | None, config: DedupConfig) -> set[bytes]:
    """Distinct k-word shingles; a shorter text is one shingle, a text without words has none."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = (raw.lower() if config.normalise == "ascii" else raw).split()
    if len(words) < config.k:
        return {b" ".join(words)} if words else set()
    return {b" ".join(words[i : i + config.k]) for i in range(len(words) - config.k + 1)}


def base_hashes(shingles: set[bytes], family: str) -> np.ndarray:
    if family == "portable31":
        return np.array([int(hashlib.md5(s).hexdigest()[:8], 16) % PRIME for s in shingles], dtype=np.uint64)
    import xxhash

    return np.array([xxhash.xxh64_intdigest(s) for s in shingles], dtype=np.uint64)


class Signer:
    """Signatures and band keys of one configuration."""

    def __init__(self, config: DedupConfig):
        self.config = config
        self.a, self.b = (np.array(c, dtype=np.uint64) for c in zip(*config.coefficients(), strict=True))
        if config.family == "xx64":
            self.a = (self.a << np.uint64(32) ^ self.b * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)

    def signature(self, text: str | None) -> np.ndarray | None:
        base = base_hashes(shingle_set(text, self.config), self.config.family)
        return self.sign(base) if len(base) else None

    def sign(self, base: np.ndarray) -> np.ndarray:
        """The least image of the shingles' hashes at each position."""
        least = None
        for at in range(0, len(base), 4096):
            part = base[at : at + 4096, None]
            value = (part * self.a + self.b) % np.uint64(PRIME) if self.config.family == "portable31" else (part ^ self.b) * self.a
            low = value.min(axis=0)
            least = low if least is None else np.minimum(least, low)
        return least

    def keys(self, signature: np.ndarray) -> list[int]:
        rows = signature.reshape(self.config.bands, self.config.rows)
        if self.config.family == "portable31":
            return [int(hashlib.md5(",".join(map(str, r.tolist())).encode()).hexdigest()[:15], 16) for r in rows]
        import xxhash

        return [int(np.uint64(xxhash.xxh64_intdigest(r.tobytes())).view(np.int64)) for r in rows]

    def wide_keys(self, signature: np.ndarray) -> list[bytes]:
        """128-bit keys."""
        return [hashlib.md5(",".join(map(str, r.tolist())).encode()).digest() for r in signature.reshape(self.config.bands, self.config.rows)]


def _kernel(config: DedupConfig, want: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(config)
        kind = {"keys": pa.int64(), "signature": pa.int64(), "wide": pa.binary()}[want]
        for batch in batches:
            at = batch.schema.get_field_index("text")
            out = []
            for text in batch.column(at):
                s = signer.signature(text.as_py())
                out.append([] if s is None else signer.keys(s) if want == "keys" else signer.wide_keys(s) if want == "wide" else s.view(np.int64).tolist())
            rest = [i for i in range(batch.num_columns) if i != at]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in rest), pa.array(out, pa.list_(kind))], names=[*(batch.schema.names[i] for i in rest), want])

    return run


def compute(docs: DataFrame, config: DedupConfig, want: str = "keys") -> DataFrame:
    """docs with text replaced by keys, signature (arrays of long) or wide (of binary)."""
    kept = [f for f in docs.schema.fields if f.name != "text"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept)
    kind = "array<binary>" if want == "wide" else "array<bigint>"
    return docs.mapInArrow(_kernel(config, want), f"{schema}, {want} {kind}")


def long_keys(docs: DataFrame, config: DedupConfig) -> DataFrame:
    """One row for each band of each document: the columns of docs, band, key."""
    keyed = compute(docs, config)
    return keyed.select(*[c for c in keyed.columns if c != "keys"], F.posexplode("keys").alias("band", "key"))


def keys_of_sets(sets: DataFrame, config: DedupConfig) -> DataFrame:
    """id, band, key of shingle sets given as such: id long, ids array of strings, none empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer = Signer(config)
        for batch in batches:
            found = [signer.keys(signer.sign(base_hashes({s.encode() for s in ids}, config.family))) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(found, pa.list_(pa.int64()))], names=["id", "keys"])

    return sets.select("id", "ids").mapInArrow(run, "id long, keys array<long>").select("id", F.posexplode("keys").alias("band", "key"))


def exact_dedup(docs: DataFrame) -> DataFrame:
    """The row of the smallest doc_id of each text."""
    least = docs.groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("doc_id"))
    return docs.join(least.select("doc_id"), "doc_id", "left_semi")


def similarity(a, b):
    """Share of agreeing positions of two signatures."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x) / F.size(a)


def register(spark, config: DedupConfig) -> None:
    """Makes segdedup_band_keys(text) callable from SQL: a row (band, key) for each band."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="band int, key bigint")
    class BandKeys:
        def __init__(self):
            self.signer = Signer(config)

        def eval(self, text: str):
            signed = self.signer.signature(text)
            if signed is not None:
                yield from enumerate(self.signer.keys(signed))

    spark.udtf.register("segdedup_band_keys", BandKeys)
