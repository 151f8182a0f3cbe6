"""Repeated byte strings through a logarithmic family of sparse suffix arrays.

Every byte that a LENGTH-byte string covers which also starts earlier (in a smaller doc_id, or
earlier in the same document) is removed; strings are judged on the input.

Which suffixes are indexed. Of the GRAM-byte strings in a LENGTH-byte window the one of least
hash, the leftmost on ties, is the window's anchor, so equal windows have equal anchors at
equal distances, and about one position in forty is an anchor. An anchor's context is all that
its windows cover. A suffix array holds, for each anchor, the fingerprint of its gram, the
fingerprint of its context, and its place, sorted in this order (fingerprint order takes the
part of alphabetic order: a merge scan needs equal strings together, not a to z).

The family. Entries are dealt to shards by gram. A shard takes its batches of documents in
order; a batch's array is merge-scanned against every level: an entry whose context is there
is a long match and all its windows go. Windows are also binned by their distance from the
anchor: those of a bin all hold the same core of 80 bytes, and where two different contexts
agree in a core (16 bits of its hash suffice to say no) the bin is undecided. What is new
becomes a level, and two levels of equal rank merge into one of the next rank, so an entry is
rewritten once per rank.

Undecided bins (the ends of repeated passages) are grouped by core and content: all but the
earliest of equal ones go, and where a core has different contents their windows' 128-bit
fingerprints are grouped, and all but the earliest go.

Skew. A group of equal entries within a buffer of text is one entry before any shuffle. A gram
with more than HOT contexts in a buffer sends its bins straight to the grouping by core and a
mark to its shard, so no shard collects a common line's occurrences.

There are so many shards that one takes the entries of about SHARD_BYTES of text, so a task's
levels are bounded however large the corpus is.

A null text is empty. doc_id names a document: rows that repeat one are the same place and do
not remove each other; a null doc_id comes before all. An empty table gives an empty result.
Columns other than doc_id and text are not looked at. Equal strings that start at one place in
two rows of one doc_id count as one; ties go to the earlier start.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch

LENGTH, GRAM = 100, 24
SPREAD = LENGTH - GRAM + 1
BATCHES, HOT = 8, 64
#: Bins of the distance between a window's start and its anchor.
BINS, BIN = 4, 20
#: Bytes hashed at a time, and bytes of text whose entries are sorted together.
BLOCK, BUFFER = 1 << 18, 32 << 20
#: Bytes of text whose entries (about 48 bytes each, one for forty bytes) a shard holds.
SHARD_BYTES = 256 << 20
FIRST = -(2**63)
ENTRY, COVERED, BINNED, UNDECIDED = 0, 1, 2, 3
#: Fixed odd multipliers (fractional parts of the golden ratio and of square roots).
M1, M2, M3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
BYTE = (np.arange(1, 257, dtype=np.uint64) * M2) ^ (np.arange(1, 257, dtype=np.uint64) * M3 >> np.uint64(17))


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = a * M1 + (b ^ (b >> np.uint64(29))) * M2
    x ^= x >> np.uint64(32)
    x *= M3
    return x


def _wider(h: np.ndarray, by: int) -> np.ndarray:
    """Hashes of strings made of two that start `by` apart."""
    return _mix(h[:-by], h[by:]) if len(h) > by else h[:0]


def grams_and_windows(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all GRAM-byte strings, two of all LENGTH-byte strings, one of all 64-byte strings."""
    h8 = BYTE[data]
    for by in (1, 2, 4):
        h8 = _wider(h8, by)
    h16 = _wider(h8, 8)
    gram = _mix(h16[: len(h16) - 8], h8[16:]) if len(h16) > 8 else h16[:0]
    h32 = _wider(h16, 16)
    h64 = _wider(h32, 32)
    high = _wider(h64, LENGTH - 64)
    low = _mix(h64[LENGTH - 64 :] ^ M2, h64[: len(h64) - (LENGTH - 64)]) if len(h64) > LENGTH - 64 else high
    return gram, high, low, h64


def anchors(gram: np.ndarray, n_windows: int) -> np.ndarray:
    """Of each window the place of its anchor."""
    keys = (gram >> np.uint64(28) << np.uint64(28)) | np.arange(len(gram), dtype=np.uint64)
    width = 1
    while 2 * width <= SPREAD:
        keys = np.minimum(keys[:-width], keys[width:])
        width *= 2
    if width < SPREAD:
        keys = np.minimum(keys[: -(SPREAD - width)], keys[SPREAD - width :])
    return (keys[:n_windows] & np.uint64((1 << 28) - 1)).astype(np.int64)


def blocks(docs: list[tuple[int, bytes]]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Runs of documents, joined: bytes; start of each part; its document; its place there.

    A document longer than a block comes in parts that overlap by LENGTH - 1 bytes.
    """
    parts: list[tuple[int, int, bytes]] = []
    size = 0
    for doc, data in docs:
        for at in range(0, max(1, len(data) - LENGTH + 1), BLOCK):
            part = data[at : at + BLOCK + LENGTH - 1]
            if len(part) >= LENGTH:
                parts.append((doc, at, part))
                size += len(part)
            if size >= BLOCK:
                yield _joined(parts)
                parts, size = [], 0
    if parts:
        yield _joined(parts)


def _joined(parts):
    lengths = np.array([len(p[2]) for p in parts])
    return np.frombuffer(b"".join(p[2] for p in parts), dtype=np.uint8), np.cumsum(lengths) - lengths, np.array([p[0] for p in parts], dtype=np.int64), np.array([p[1] for p in parts], dtype=np.int64)


def packed(a, b, p):
    """First and last window and anchor as one long."""
    return (a << 14) | (b - a) << 7 | (p - a)


def unpacked(place):
    a = place >> 14
    return a, a + ((place >> 7) & 127), a + (place & 127)


def _cores(data: np.ndarray, h64: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Sixteen bits of the hash of each bin's core, in one long; where data ends, of what exists."""
    out = np.zeros(len(p), dtype=np.uint64)
    last = len(h64) - 1
    for j in range(BINS):
        left = np.clip(p - j * BIN, 0, last)
        right = np.clip(p - (j + 1) * BIN + 1 + LENGTH - 64, 0, last)
        out |= (_mix(h64[left], h64[right]) >> np.uint64(48)) << np.uint64(16 * j)
    return out


def entries(docs: list[tuple[int, bytes]]) -> dict[str, np.ndarray]:
    """gram, context, core, doc and place of each anchor's run of windows."""
    found = []
    for data, starts, ids, places in blocks(docs):
        gram, high, low, h64 = grams_and_windows(data)
        n = len(high)
        anchor = anchors(gram, n)
        part = np.zeros(n, dtype=np.int64)
        part[starts[1:][starts[1:] < n]] = 1
        part = np.cumsum(part)
        ends = np.append(starts[1:], len(data))
        inside = np.arange(n) + LENGTH <= ends[part]
        cut = np.flatnonzero((np.diff(anchor) != 0) | (np.diff(part) != 0) | (np.diff(inside.astype(np.int8)) != 0)) + 1
        a = np.concatenate([[0], cut])
        b = np.append(cut, n) - 1
        ok = inside[a]
        a, b = a[ok], b[ok]
        p = anchor[a]
        context = _mix(_mix(high[a], low[b]), _mix(high[b], ((p - a) * 256 + (p - b)).astype(np.uint64)))
        shift = places[part[a]] - starts[part[a]]
        found.append((gram[p].view(np.int64), context.view(np.int64), _cores(data, h64, p).view(np.int64), ids[part[a]], packed(a + shift, b + shift, p + shift)))
    columns = [np.concatenate(c) if found else np.zeros(0, dtype=np.int64) for c in (zip(*found, strict=True) if found else [()] * 5)]
    return dict(zip(("gram", "context", "core", "doc", "place"), columns, strict=True))


def binned(docs: list[tuple[int, bytes]], wanted: dict[int, list[tuple[int, int, int]]]) -> dict[str, list]:
    """core, content, doc, first window and bytes of the bins wanted: (first, last, bin's least distance)."""
    out: dict[str, list] = {"core": [], "content": [], "doc": [], "a": [], "data": []}
    for doc, text in docs:
        for a, b, anchor, j in wanted[doc]:
            data = text[a : b + LENGTH]
            core = text[anchor - j * BIN : anchor - (j + 1) * BIN + 1 + LENGTH]
            out["core"].append(_digest(core, j))
            out["content"].append(_digest(data, anchor - a))
            out["doc"].append(doc)
            out["a"].append(a)
            out["data"].append(data)
    return out


def _digest(data: bytes, salt: int) -> int:
    return int.from_bytes(hashlib.blake2b(data, digest_size=8, salt=bytes([salt])).digest(), "little", signed=True)


def bins_of(place: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, int]]:
    """Of each bin j the rows that have windows in it, their first and last, their anchors, j."""
    a, b, p = unpacked(place)
    for j in range(BINS):
        first, last = np.maximum(a, p - (j + 1) * BIN + 1), np.minimum(b, p - j * BIN)
        has = np.flatnonzero((first <= last) & (place >= 0))
        if len(has):
            yield has, first[has], last[has], p[has], j


ROW = pa.schema([("kind", pa.int32()), ("route", pa.int64()), ("context", pa.int64()), ("core", pa.int64()), ("doc", pa.int64()), ("place", pa.int64()), ("data", pa.binary())])
ROW_SCHEMA = "kind int, route long, context long, core long, doc long, place long, data binary"


def _rows(kind: int, route, context, core, doc, place, data=None) -> pa.RecordBatch:
    """place: first and last window and anchor, packed; data: the bytes of a bin."""
    n = len(doc)
    fill = lambda x: pa.array(np.broadcast_to(np.asarray(x, dtype=np.int64), n).copy(), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind, dtype=np.int32)), fill(route), fill(context), fill(core), fill(doc), fill(place), pa.array(data, pa.binary()) if data is not None else pa.nulls(n, pa.binary())], schema=ROW)


def _again(gram, context, doc, place) -> tuple[np.ndarray, np.ndarray]:
    """In sorted entries: the first of each run of equal ones, and the others that lie elsewhere."""
    first = np.ones(len(gram), dtype=bool)
    first[1:] = (gram[1:] != gram[:-1]) | (context[1:] != context[:-1])
    lead = np.maximum.accumulate(np.where(first, np.arange(len(gram)), 0))
    return first, ~first & ((doc != doc[lead]) | (place != place[lead]))


def _buffered(batches: Iterator[pa.RecordBatch], least: int = BUFFER) -> Iterator[list[tuple[int, bytes]]]:
    held, size = [], 0
    for batch in batches:
        for doc, text in zip(batch.column("doc").to_pylist(), batch.column("text"), strict=True):
            data = text.as_py() or b""
            held.append((doc, data))
            size += len(data)
            if size >= least:
                yield held
                held, size = [], 0
    if held:
        yield held


def _entry_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for docs in _buffered(batches):
        e = entries(docs)
        if not len(e["gram"]):
            continue
        order = np.lexsort((e["place"], e["doc"], e["context"], e["gram"]))
        gram, context, core, doc, place = (e[k][order] for k in ("gram", "context", "core", "doc", "place"))
        first, again = _again(gram, context, doc, place)
        yield _rows(COVERED, doc[again], 0, 0, doc[again], place[again])
        gram, context, core, doc, place = (x[first] for x in (gram, context, core, doc, place))
        names, n = np.unique(gram, return_counts=True)
        hot = n > HOT
        is_hot = np.repeat(hot, n)
        if hot.any():
            wanted: dict[int, list[tuple[int, int, int, int]]] = {}
            hot_docs = doc[is_hot]
            for has, first_, last, anchor, j in bins_of(place[is_hot]):
                for d, x, y, z in zip(hot_docs[has].tolist(), first_.tolist(), last.tolist(), anchor.tolist(), strict=True):
                    wanted.setdefault(d, []).append((x, y, z, j))
            some = list({d: (d, data) for d, data in docs if d in wanted}.values())
            for i in range(0, len(some), 256):
                got = binned(some[i : i + 256], wanted)
                yield _rows(BINNED, got["core"], got["content"], 0, got["doc"], got["a"], got["data"])
            yield _rows(ENTRY, names[hot], 0, 0, np.full(hot.sum(), FIRST), -1)
        yield _rows(ENTRY, gram[~is_hot], context[~is_hot], core[~is_hot], doc[~is_hot], place[~is_hot])


class Level:
    """A sorted array of entries (gram, context, core, doc, place), and its cores' keys, sorted."""

    def __init__(self, columns: list[np.ndarray], rank: int):
        self.columns, self.rank = columns, rank
        self.keys, self.rows, self.bins = core_keys(columns)
        self.given = np.zeros(len(self.keys), dtype=bool)

    def merged(self, other: Level) -> Level:
        both = [np.concatenate([x, y]) for x, y in zip(self.columns, other.columns, strict=True)]
        order = np.lexsort((both[1], both[0]))
        new = Level([c[order] for c in both], self.rank + 1)
        old = np.concatenate([self.keys[self.given], other.keys[other.given]])
        new.given = np.isin(new.keys, old)
        return new

    def known(self, gram: np.ndarray, context: np.ndarray) -> np.ndarray:
        """Merge scan: whether each entry's context is here."""
        own, contexts = self.columns[0], self.columns[1]
        lo, hi = np.searchsorted(own, gram, "left"), np.searchsorted(own, gram, "right")
        known = np.zeros(len(gram), dtype=bool)
        one = hi - lo == 1
        known[one] = contexts[lo[one]] == context[one]
        for i in np.flatnonzero(hi - lo > 1).tolist():
            k = lo[i] + np.searchsorted(contexts[lo[i] : hi[i]], context[i])
            known[i] = k < hi[i] and contexts[k] == context[i]
        return known


def core_keys(columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted keys of (gram, bin, core) with the entry and the bin of each."""
    gram, _, core, _, place = columns
    a, b, p = unpacked(place)
    rows, keys, bins = [], [], []
    for j in range(BINS):
        low, high = j * BIN, (j + 1) * BIN - 1
        has = np.flatnonzero((place >= 0) & (p - a >= low) & (p - b <= high))
        part = (core[has].view(np.uint64) >> np.uint64(16 * j)) & np.uint64(0xFFFF)
        keys.append(_mix(gram[has].view(np.uint64), part + np.uint64(j << 16)))
        rows.append(has)
        bins.append(np.full(len(has), j))
    keys, rows, bins = np.concatenate(keys), np.concatenate(rows), np.concatenate(bins)
    order = np.argsort(keys, kind="stable")
    return keys[order], rows[order], bins[order]


class Family:
    """The levels of one shard."""

    def __init__(self):
        self.levels: list[Level] = []
        self.marks = np.zeros(0, dtype=np.int64)

    def _undecided(self, level: Level, which: np.ndarray) -> pa.RecordBatch:
        rows, bins = level.rows[which], level.bins[which]
        a, b, p = unpacked(level.columns[4][rows])
        first, last = np.maximum(a, p - (bins + 1) * BIN + 1), np.minimum(b, p - bins * BIN)
        return _rows(UNDECIDED, 0, 0, 0, level.columns[3][rows], packed(first, last, p))

    def add(self, gram: np.ndarray, context: np.ndarray, core: np.ndarray, doc: np.ndarray, place: np.ndarray) -> Iterator[pa.RecordBatch]:
        """Takes a batch, sorted by gram, context, doc and place; gives what it covers and what is undecided."""
        if not len(gram):
            return
        first, again = _again(gram, context, doc, place)
        yield _rows(COVERED, 0, 0, 0, doc[again], place[again])
        columns = [x[first] for x in (gram, context, core, doc, place)]
        known = np.zeros(len(columns[0]), dtype=bool)
        for level in self.levels:
            known |= level.known(columns[0], columns[1])
        lost = known & (columns[4] >= 0)
        yield _rows(COVERED, 0, 0, 0, columns[3][lost], columns[4][lost])
        new = Level([x[~known] for x in columns], 0)
        # grams that some buffer found hot: all of their windows are undecided
        self.marks = np.union1d(self.marks, new.columns[0][new.columns[4] < 0])
        met = np.isin(new.columns[0][new.rows], self.marks)
        same = np.zeros(len(new.keys), dtype=bool)
        same[1:] = new.keys[1:] == new.keys[:-1]
        met |= same
        met[:-1] |= same[1:]
        for level in self.levels:
            if len(level.keys):
                at = np.minimum(np.searchsorted(level.keys, new.keys), len(level.keys) - 1)
                met |= level.keys[at] == new.keys
                fresh = (np.isin(level.keys, new.keys) | np.isin(level.columns[0][level.rows], self.marks)) & ~level.given
                level.given |= fresh
                yield self._undecided(level, fresh)
        new.given |= met
        yield self._undecided(new, met)
        while self.levels and self.levels[-1].rank == new.rank:
            new = self.levels.pop().merged(new)
        self.levels.append(new)


def _shard_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by batch, gram, context, doc and place."""
    family, held, now = Family(), [], None

    def close() -> Iterator[pa.RecordBatch]:
        if held:
            yield from family.add(*(np.concatenate(c) for c in zip(*held, strict=True)))

    for rows in batches:
        kind, number, *rest = (rows.column(n).to_numpy(zero_copy_only=False) for n in ("kind", "batch", "route", "context", "core", "doc", "place"))
        through = kind != ENTRY
        if through.any():
            yield rows.filter(pa.array(through)).select(ROW.names)
        for x in np.unique(number[~through]).tolist():
            if x != now:
                yield from close()
                held, now = [], x
            pick = ~through & (number == x)
            held.append([c[pick] for c in rest])
    yield from close()


def _bin_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for doc, text, places in zip(batch.column("doc").to_pylist(), batch.column("text"), batch.column("places").to_pylist(), strict=True):
            wanted: list[tuple[int, int, int, int]] = []
            for _, first, last, anchor, j in bins_of(np.unique(np.array(places, dtype=np.int64))):
                wanted += [(x, y, z, j) for x, y, z in zip(first.tolist(), last.tolist(), anchor.tolist(), strict=True)]
            got = binned([(doc, text.as_py() or b"")], {doc: wanted})
            yield pa.RecordBatch.from_arrays([*(pa.array(got[n], pa.int64()) for n in ("core", "content", "doc", "a")), pa.array(got["data"], pa.binary())], names=list(got))


def _window_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        pieces = [x.as_py() for x in batch.column("data")]
        lengths = np.array([len(p) for p in pieces], dtype=np.int64)
        if not len(lengths):
            continue
        _, high, low, _ = grams_and_windows(np.frombuffer(b"".join(pieces), dtype=np.uint8))
        starts = np.cumsum(lengths) - lengths
        n = lengths - LENGTH + 1
        inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        at = np.repeat(starts, n) + inner
        doc, a = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("doc", "a"))
        yield pa.RecordBatch.from_arrays([pa.array(high[at].view(np.int64)), pa.array(low[at].view(np.int64)), pa.array(np.repeat(doc, n)), pa.array(np.repeat(a, n) + inner)], names=["high", "low", "doc", "a"])


def merged_runs(runs: list[tuple[int, int]], n: int) -> list[tuple[int, int]]:
    """Maximal runs of the union of half-open ranges within 0..n."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(runs):
        b = min(b, n)
        if a >= b:
            continue
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _removal_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: list[list] = [[], [], [], [], []]
        for text, runs in zip(batch.column("text"), batch.column("runs"), strict=True):
            data = text.as_py() or b""
            spans = merged_runs([(r["a"], r["b"]) for r in runs.as_py() or []], len(data))
            digest, last = hashlib.sha256(), 0
            for a, b in spans:
                digest.update(data[last:a])
                last = b
            digest.update(data[last:])
            for column, value in zip(out, (len(data), sum(b - a for a, b in spans), len(spans), digest.hexdigest(), [{"start": a, "end": b} for a, b in spans]), strict=True):
                column.append(value)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(out, kinds, strict=True))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "removed"])


def removals(docs: DataFrame, batches: int = BATCHES) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, removed (the runs) of each row of docs."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("doc_id").cast("long"), F.lit(FIRST)).alias("doc"), F.col("text").cast("binary").alias("text"))
    total = texts.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(scratch.shuffle_partitions(spark), spark.sparkContext.defaultParallelism, -(-total // SHARD_BYTES))
    fences = sorted(set(texts.approxQuantile("doc", [i / batches for i in range(1, batches)], 0.02)))
    number = sum((F.when(F.col("doc") >= int(x), 1).otherwise(0) for x in fences), F.lit(0)).cast("int")

    rows = texts.select("doc", "text").mapInArrow(_entry_kernel, ROW_SCHEMA).withColumn("batch", number)
    judged = rows.repartition(n, "route").sortWithinPartitions("batch", "route", "context", "doc", "place").mapInArrow(_shard_kernel, ROW_SCHEMA)
    judged = scratch.written(judged, "suffix-shards", ["kind"])
    scratch.release(spark)
    first = F.shiftright("place", 14)
    last = first + F.shiftright("place", 7).bitwiseAND(F.lit(127))

    undecided = judged.where(F.col("kind") == UNDECIDED).groupBy("doc").agg(F.collect_list("place").alias("places"))
    bins = texts.select("doc", "text").join(undecided, "doc").mapInArrow(_bin_kernel, "core long, content long, doc long, a long, data binary")
    hot = judged.where(F.col("kind") == BINNED).select(F.col("route").alias("core"), F.col("context").alias("content"), "doc", F.col("place").alias("a"), "data")
    bins = scratch.written(bins.union(hot).distinct(), "suffix-bins")
    for kind in (UNDECIDED, BINNED):
        scratch.remove(spark, f"{judged.shared_path}/kind={kind}")
    scratch.release(spark)
    contents = bins.groupBy("core", "content").agg(F.min(F.struct("doc", "a", "data")).alias("first"), F.count(F.lit(1)).alias("n"))
    contents = scratch.written(contents, "suffix-contents")
    repeated = contents.where("n > 1").select("core", "content", "first.doc", "first.a").withColumnsRenamed({"doc": "first_doc", "a": "first_a"})
    again = bins.join(repeated, ["core", "content"]).where((F.col("doc") != F.col("first_doc")) | (F.col("a") != F.col("first_a"))).select("doc", "a", (F.col("a") + F.length("data")).alias("b"))
    again = scratch.written(again, "suffix-again")
    scratch.drop(bins)
    scratch.release(spark)
    shared = contents.groupBy("core").agg(F.count(F.lit(1)).alias("contents")).where("contents > 1").select("core")
    windows = contents.join(shared, "core", "left_semi").select("first.*").mapInArrow(_window_kernel, "high long, low long, doc long, a long")
    windows = scratch.written(windows, "suffix-windows")
    scratch.drop(contents)
    scratch.release(spark)
    earliest = windows.groupBy("high", "low").agg(F.min(F.struct("doc", "a")).alias("first"), F.max(F.struct("doc", "a")).alias("last")).where("first <> last").select("high", "low", "first")
    late = windows.join(earliest, ["high", "low"]).where(F.struct("doc", "a") != F.col("first")).select("doc", "a", (F.col("a") + LENGTH).alias("b"))
    late = scratch.written(late, "suffix-late")
    scratch.drop(windows)
    scratch.release(spark)
    covered = judged.where(F.col("kind") == COVERED).select("doc", first.alias("a"), (last + LENGTH).alias("b")).union(again).union(late)
    runs = covered.groupBy("doc").agg(F.collect_list(F.struct("a", "b")).alias("runs"))
    return texts.join(runs, "doc", "left").select("doc_id", "text", "runs").mapInArrow(_removal_kernel, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, removed array<struct<start: long, end: long>>")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removals(scratch.table(spark, sf_dir, "documents")).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


QUERIES = {"op1_suffix_dedup": op1_suffix_dedup}
ORACLE_SQL: dict[str, str] = {}
