"""Candidate pairs of integer sets whose Jaccard may reach a threshold; none that reaches it is left out.

All sets are sorted by one order of their elements, rarest first. Two sets of sizes n and m at
Jaccard t or more share c = t / (1 + t) * (n + m) elements at least, so both hold a shared one
before their last c - 1 places: only prefixes are posted. A task takes a share of the elements
with all their postings, and of each set that posts there one parity sketch. It forms pairs
that sizes and places allow and gives those that sketches do not rule out: an element flips one
bit, so sketches differ in no more bits than the sets do in elements.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segdedup import scratch

#: Bits of the narrowest sketch; pairs, and bytes of sketches, that a task holds at once.
LEAST_BITS, PAIRS, HELD = 256, 1 << 18, 1 << 25
#: Far above the rounding of a bound, far below one element.
SLACK = 1e-6


def _distinct(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [b" ".join(sorted(set((t.as_py() or b"").lower().split()))) for t in batch.column(1)]
        found = pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], names=["doc_id", "w"])
        yield found.filter(pa.array([len(s) > 0 for s in sets], pa.bool_()))


def words(docs: DataFrame) -> DataFrame:
    """doc_id and w, the text's distinct words (as keys.normalise makes them) in order, a blank between; texts without words have no row."""
    found = docs.select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(_distinct, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, w binary")
    return found.select("doc_id", F.col("w").cast("string").alias("w"))


def _shared(total: np.ndarray, least: float) -> np.ndarray:
    """Elements that two sets of `total` elements share at `least` or more."""
    return np.maximum(np.ceil(least / (1 + least) * total - SLACK), 1).astype(np.int64)


def _width(n):
    """Bits of the sketch of n elements: a power of two, n or more."""
    return np.maximum(LEAST_BITS, np.int64(1) << np.frexp(np.asarray(n) - 1)[1].astype(np.int64))


def _sketch(ids: np.ndarray) -> np.ndarray:
    """Parities of the elements that fall on each bit."""
    width = int(_width(len(ids)))
    at = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)) & np.uint64(width - 1)
    return np.packbits((np.bincount(at.astype(np.int64), minlength=width) & 1).astype(np.uint8)).view("<u8")


def _fold(sketches: np.ndarray, words: int) -> np.ndarray:
    """Rows of sketches brought to `words` 64-bit words."""
    return np.bitwise_xor.reduce(sketches.reshape(len(sketches), -1, words), axis=1)


#: What a row holds for one part: of each set its doc_id, size, number of postings and sketch, of each posting the rest.
COLUMNS = {"doc": "<i8", "n": "<i4", "many": "<i4", "sketch": "<u8", "rank": "<i4", "place": "<i4", "before": "<i4"}


def _post(rank: np.ndarray, single: int, parts: int, least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, len(batch), 2000):
                cut = batch.slice(start, 2000)
                dealt: dict[int, list[tuple]] = {}
                for name, cell in zip(cut.column(0).to_pylist(), cut.column(1), strict=True):
                    ids = cell.values.to_numpy()
                    n = len(ids)
                    length = n - max(int(np.ceil(least * n - SLACK)), 1) + 1
                    ranks = np.sort(rank[ids])[:length]
                    rows = np.stack([ranks, np.arange(length), np.append(-1, ranks[:-1])], axis=1).astype(np.int32)
                    rows = rows[ranks >= single]  # an element of one set meets no other
                    if not len(rows):
                        continue
                    mark, to = _sketch(ids), rows[:, 0] % parts
                    order = np.argsort(to, kind="stable")
                    edges = np.append(0, np.flatnonzero(np.diff(to[order])) + 1)
                    for part, piece in zip(to[order][edges].tolist(), np.split(rows[order], edges[1:]), strict=True):
                        dealt.setdefault(part, []).append((name, n, len(piece), mark, piece))
                columns = [[] for _ in COLUMNS]
                for held in dealt.values():
                    doc, n, many, marks, pieces = zip(*held, strict=True)
                    flat = np.concatenate(pieces)
                    values = (doc, n, many, np.concatenate(marks), *flat.T)
                    for column, value, kind in zip(columns, values, COLUMNS.values(), strict=True):
                        column.append(np.ascontiguousarray(value, dtype=kind).tobytes())
                yield pa.RecordBatch.from_arrays([pa.array(list(dealt), pa.int32()), *(pa.array(c, pa.binary()) for c in columns)], names=["part", *COLUMNS])

    return run


def _spans(count: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose counts come to PAIRS, or of one row."""
    ends, at = np.cumsum(count), 0
    while at < len(count):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + PAIRS, side="right")))
        yield at, to
        at = to


def _pairs(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [b for b in batches if len(b)]
        if not rows:
            return
        doc, size, many, marks, rank, place, before = (np.frombuffer(b"".join(x.as_py() for b in rows for x in b.column(c)), dtype=kind) for c, kind in COLUMNS.items())
        del rows
        size = size.astype(np.int64)
        entry = np.repeat(np.arange(len(doc)), many)
        words, within = _width(size) // 64, np.zeros(len(doc), dtype=np.int64)
        begin, wide = np.cumsum(words) - words, {}
        for w in np.unique(words).tolist():
            own = np.flatnonzero(words == w)
            within[own] = np.arange(len(own))
            wide[w] = marks[begin[own][:, None] + np.arange(w)]
        folded: dict[tuple[int, int], np.ndarray] = {}

        def at_width(w: int, to: int) -> np.ndarray:
            if (w, to) not in folded:
                folded[w, to] = _fold(wide[w], to)
            return folded[w, to]

        # of one element by size: a set's possible larger partners follow it without a gap
        order = np.lexsort((entry, size[entry], rank))
        entry, left, before = entry[order], (size[entry] - place)[order], before[order]
        key = (rank[order].astype(np.int64) << 32) | size[entry]
        n = size[entry]
        most = n if least <= 0 else np.floor(n / least + SLACK).astype(np.int64)
        top = key | 0xFFFFFFFF if least <= 0 else (key >> 32 << 32) | np.minimum(most, 0xFFFFFFFF)
        count = np.searchsorted(key, top, side="right") - np.arange(len(key)) - 1
        count[left < _shared(2 * n, least)] = 0
        start = np.flatnonzero(count > 0)
        count = count[start]
        found: list[np.ndarray] = []

        def out() -> pa.RecordBatch:
            code = np.unique(np.concatenate(found)) if found else np.zeros(0, dtype=np.int64)
            x, y = doc[code // len(doc)], doc[code % len(doc)]
            a, b = np.minimum(x, y), np.maximum(x, y)
            order = np.lexsort((b, a))
            a, b = a[order], b[order]
            starts = np.flatnonzero(np.append(True, a[1:] != a[:-1])) if len(a) else np.zeros(0, dtype=np.int64)
            found.clear()
            others = pa.ListArray.from_arrays(pa.array(np.append(starts, len(b)), pa.int32()), pa.array(b))
            return pa.RecordBatch.from_arrays([pa.array(a[starts]), others], names=["a", "others"])

        held = 0
        for at, to in _spans(count):
            each = count[at:to]
            i = np.repeat(start[at:to], each)
            j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(each) - each, each)
            total = n[i] + n[j]
            shared = _shared(total, least)
            # where both have the same element just before, the pair is met there
            able = (np.minimum(left[i], left[j]) >= shared) & ((before[i] != before[j]) | (before[i] < 0))
            i, j, may = entry[i[able]], entry[j[able]], (total - 2 * shared)[able]
            kind = words[i] << 32 | words[j]
            for both_w in np.unique(kind).tolist():
                w, v = both_w >> 32, both_w & 0xFFFFFFFF
                both, narrow = np.flatnonzero(kind == both_w), min(w, v)
                step = max(1, HELD // (8 * narrow))
                for k in range(0, len(both), step):
                    some = both[k : k + step]
                    x, y = i[some], j[some]
                    far = np.bitwise_count(at_width(w, narrow)[within[x]] ^ at_width(v, narrow)[within[y]]).sum(axis=1, dtype=np.int64)
                    good = far <= may[some]
                    x, y = x[good], y[good]
                    found.append(np.unique(np.minimum(x, y) * len(doc) + np.maximum(x, y)))
                    held += len(found[-1])
            if held > PAIRS:
                held = 0
                yield out()
        yield out()

    return run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by a; each pair once."""
    a, b = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)

    def once(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
        order = np.lexsort((b, a))
        a, b = a[order], b[order]
        new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))[: len(a)]
        return pa.RecordBatch.from_arrays([pa.array(a[new]), pa.array(b[new])], names=["a", "b"])

    for batch in batches:
        if not len(batch):
            continue
        each = batch.column(1).value_lengths().to_numpy()
        a, b = np.append(a, np.repeat(batch.column(0).to_numpy(), each)), np.append(b, batch.column(1).flatten().to_numpy())
        whole = int(np.searchsorted(a, a[-1]))  # the last may go on
        yield once(a[:whole], b[:whole])
        a, b = a[whole:], b[whole:]
    yield once(a, b)


def candidates(sets: DataFrame, least: float) -> DataFrame:
    """a < b, once each, of all pairs whose Jaccard is `least` or more, and a few others.

    sets: doc_id, ids (distinct integers from 0 to below some fixed number, none empty); written before.
    """
    spark = sets.sparkSession
    often = sets.select(F.explode("ids").alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("df")).toArrow()
    ids, df = (often.column(c).to_numpy() for c in ("id", "df"))
    order = np.lexsort((ids, df))
    rank = np.zeros(int(ids.max()) + 1 if len(ids) else 1, dtype=np.int32)
    rank[ids[order]] = np.arange(len(ids))
    n = scratch.shuffle_partitions(spark)
    # sketches are copied to each share, so shares are as few as memory and cores allow
    parts = max(2 * spark.sparkContext.defaultParallelism, n // 4)
    single = int((df == 1).sum())
    posted = sets.select("doc_id", "ids").mapInArrow(_post(rank, single, parts, least), ", ".join(["part int", *(f"{c} binary" for c in COLUMNS)]))
    met = posted.repartitionById(parts, F.col("part")).mapInArrow(_pairs(least), "a long, others array<long>")
    # a doc_id that two sets bear makes no pair with itself
    return met.repartition(n, "a").sortWithinPartitions("a").mapInArrow(_merge, "a long, b long").where("a < b")



def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = np.zeros(0, dtype=bool)
    for batch in batches:
        if not len(batch):
            continue
        x, y = (batch.column(c) for c in ("x", "y"))
        own, other = x.flatten().to_numpy(), y.flatten().to_numpy()
        top = int(max(own.max(), other.max())) + 1
        held = held if top <= len(held) else np.zeros(top, dtype=bool)
        sizes = [c.value_lengths().to_numpy().astype(np.int64) for c in (x, y)]
        ends = [np.append(0, np.cumsum(c)).tolist() for c in sizes]
        inter, last = np.zeros(len(batch), dtype=np.int64), None
        for k in range(len(batch)):
            this = other[ends[1][k] : ends[1][k + 1]]
            if last is None or not np.array_equal(last, this):  # rows of one b come together
                if last is not None:
                    held[last] = False
                last = this
                held[last] = True
            inter[k] = np.count_nonzero(held[own[ends[0][k] : ends[0][k + 1]]])
        held[last] = False
        s, t = (batch.column(c).flatten().to_numpy().reshape(len(batch), -1) for c in ("s", "t"))
        columns = [batch.column("a"), batch.column("b"), pa.array(inter), pa.array(sizes[0] + sizes[1] - inter), pa.array((s == t).any(axis=1))]
        yield pa.RecordBatch.from_arrays(columns, names=["a", "b", "inter", "uni", "agree"])


def compared(pairs: DataFrame, signed: DataFrame) -> DataFrame:
    """pairs (a, b) with inter, uni: the elements that both have, that either has; agree: whether any of their marks is equal.

    signed: doc_id, ids, marks (as many for each).
    """
    left = signed.select(F.col("doc_id").alias("a"), F.col("ids").alias("x"), F.col("marks").alias("s"))
    right = signed.select(F.col("doc_id").alias("b"), F.col("ids").alias("y"), F.col("marks").alias("t"))
    return pairs.join(left, "a").join(right, "b").mapInArrow(_compare, "a long, b long, inter long, uni long, agree boolean")
