"""SimHash near-duplicates through an inverted index of byte positions with count filtering.

A fingerprint's bit is 1 if it is set in over half of the XXH64 hashes of the document's
3-word shingles. Two fingerprints within 2 bits share at least 6 of their 8 bytes in place.
The index posts each distinct fingerprint under positional bytes: the bytes are dealt into
four pairs, of which at least two agree in full, so the postings are the six combinations of
two pairs (32 bits). Within a posting the shared positional bytes of each pair of fingerprints
are tallied, pairs with at least 6 are retained and verified by their differing bits. A
posting longer than SPLIT is split by two further bytes before the shuffle (with 6 shared bytes
two of the other four agree), so no task holds more than 65,536 fingerprints of a posting; what
is then still longer than TALLY is looked up by the ball of 2 bits around each fingerprint. A
posting gives stars around the roots of its components, never all its pairs.

Equal fingerprints are one node whatever the number of copies. A null text has no words: its
fingerprint is zero and links like any other. Repeated rows stay; null doc_ids stay, and
count as a component's doc_id only where it has no other. An empty table gives none. Texts are
read whole, however long; columns other than doc_id and text are not looked at.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import components, scratch

SEED, WIDTH, MAX_BITS, MIN_BYTES = 42, 3, 2, 6
#: Fingerprints of a posting that are tallied at once, and up to which it is not split.
TALLY, SPLIT = 512, 4096


def fingerprint(text: str | None) -> int:
    """The 64-bit SimHash as a signed integer."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) <= WIDTH:
        hashes = [xxhash.xxh64_intdigest(b" ".join(words), SEED)]
    else:
        line = b" ".join(words)
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1)
        starts = np.concatenate([[0], ends[: -WIDTH]]).tolist()
        digest = xxhash.xxh64_intdigest
        hashes = [digest(line[a:b], SEED) for a, b in zip(starts, (ends[WIDTH - 1 :] - 1).tolist(), strict=True)]
    total = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = np.array(hashes[at : at + (1 << 16)], dtype="<u8")
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(2 * total > len(hashes), bitorder="little")
    return int(bits.view("<i8")[0])


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = batch.column(batch.schema.get_field_index("text"))
        marks = pa.array([fingerprint(t.as_py()) for t in texts], pa.int64())
        rest = [i for i, n in enumerate(batch.schema.names) if n != "text"]
        yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in rest), marks], names=[*(batch.schema.names[i] for i in rest), "mark"])


def with_fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id and mark, the fingerprint as a signed long."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_fingerprints, "doc_id long, mark long")


GROUPS = list(combinations(range(4), 2))


def _postings(marks: DataFrame) -> DataFrame:
    """posting, key, mark: each distinct fingerprint under its six 32-bit keys."""
    keys = []
    for n, (a, b) in enumerate(GROUPS):
        part = lambda k: F.shiftrightunsigned("mark", 16 * k).bitwiseAND(F.lit(0xFFFF))
        keys.append(F.struct(F.lit(n).alias("posting"), (F.shiftleft(part(a), 16).bitwiseOR(part(b))).alias("key")))
    return marks.select("mark", F.explode(F.array(*keys)).alias("p")).select("p.posting", "p.key", "mark")


def _popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


class _Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        a, b = self.root(i), self.root(j)
        self.up[max(a, b)] = min(a, b)
        return a != b


def _tally(marks: np.ndarray, start: int = 0, stop: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs i < j, i from start to stop, that share MIN_BYTES positional bytes and differ in at most MAX_BITS bits."""
    bytes_ = marks.view(np.uint8).reshape(-1, 8)
    own = bytes_[start:stop]
    shared = np.zeros((len(own), len(marks)), dtype=np.uint8)
    for k in range(8):
        shared += own[:, k][:, None] == bytes_[:, k][None, :]
    i, j = np.nonzero(np.triu(shared >= MIN_BYTES, start + 1))
    i = i + start
    near = _popcount(marks[i] ^ marks[j]) <= MAX_BITS
    return i[near], j[near]


def _ball(marks: np.ndarray, free: list[int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Links between sorted marks that agree outside the free bytes, by looking up neighbours."""
    bits = [np.uint64(1) << np.uint64(8 * k + b) for k in free for b in range(8)]
    for flip in [*bits, *(a | b for a, b in combinations(bits, 2))]:
        other = marks ^ flip
        at = np.minimum(np.searchsorted(marks, other), len(marks) - 1)
        i = np.flatnonzero((marks[at] == other) & (other > marks))
        if len(i):
            yield i, at[i]


def posting_links(marks: np.ndarray, fixed: tuple[int, ...]) -> list[tuple[int, int]]:
    """Links of one posting that keep its components; fixed: the bytes in which all marks agree.

    A posting that was not split has at most SPLIT marks, a split one two free bytes.
    """
    marks = np.unique(marks.view("<u8"))
    forest = _Forest(len(marks))

    def add(i: np.ndarray, j: np.ndarray) -> None:
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            forest.join(a, b)

    others = [k for k in range(8) if k not in fixed]
    if len(marks) <= TALLY or len(others) > 2:
        for at in range(0, len(marks), TALLY):  # a band of rows at a time
            add(*_tally(marks, at, at + TALLY))
    else:
        for i, j in _ball(marks, others):
            add(i, j)
    signed = marks.view("<i8")  # as stars around the roots, which settle in fewer rounds than chains
    return [(int(signed[i]), int(signed[r])) for i in range(len(marks)) if (r := forest.root(i)) != i]


def _fixed_bytes(posting: int, part: int) -> tuple[int, ...]:
    a, b = GROUPS[posting]
    held = (2 * a, 2 * a + 1, 2 * b, 2 * b + 1)
    free = [k for k in range(8) if k not in held]
    return held if part < 0 else held + tuple(free[k] for k in GROUPS[part])


def _posting_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by posting, part and key; links of each run of two marks or more."""
    u, v = [], []
    held: list[np.ndarray] = []
    now: tuple[int, int, int] | None = None

    def close() -> None:
        if now is not None and sum(map(len, held)) > 1:
            for x, y in posting_links(np.concatenate(held), _fixed_bytes(now[0], now[1])):
                u.append(x)
                v.append(y)

    def out() -> pa.RecordBatch:
        rows = pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], names=["u", "v"])
        u.clear()
        v.clear()
        return rows

    for batch in batches:
        names = [batch.column(n).to_numpy(zero_copy_only=False) for n in ("posting", "part", "key")]
        mark = batch.column("mark").to_numpy(zero_copy_only=False)
        cuts = np.flatnonzero(np.any([np.diff(x) != 0 for x in names], axis=0)) + 1
        edges = [0, *cuts.tolist(), len(mark)]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if a == b:
                continue
            this = tuple(int(x[a]) for x in names)
            if this != now:
                close()
                now, held = this, []
            held.append(np.ascontiguousarray(mark[a:b]))
        if len(u) > 50_000:
            yield out()
    close()
    yield out()


def _split(crowded: DataFrame) -> DataFrame:
    """posting, part, key, mark of postings longer than SPLIT, under two further bytes each.

    With MIN_BYTES shared bytes and four of them fixed, two of the other four agree.
    """
    byte = lambda k: F.shiftrightunsigned("mark", 8 * k).bitwiseAND(F.lit(0xFF))
    parts = []
    for posting in range(len(GROUPS)):
        keys = []
        for part in range(len(GROUPS)):
            x, y = _fixed_bytes(posting, part)[4:]
            more = F.shiftleft(F.col("key"), 16).bitwiseOR(F.shiftleft(byte(x), 8)).bitwiseOR(byte(y))
            keys.append(F.struct(F.lit(part).alias("part"), more.alias("key")))
        parts.append(F.when(F.col("posting") == posting, F.array(*keys)))
    return crowded.select("posting", F.explode(F.coalesce(*parts)).alias("p"), "mark").select("posting", "p.part", "p.key", "mark")


def links(marks: DataFrame) -> DataFrame:
    """u, v: links between distinct fingerprints that keep every component."""
    spark = marks.sparkSession
    posted = _postings(marks.select("mark").distinct())
    sizes = posted.groupBy("posting", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    several = scratch.written(posted.join(sizes, ["posting", "key"]), "simhash-postings")
    short = several.where(F.col("n") <= SPLIT).select("posting", F.lit(-1).alias("part"), "key", "mark")
    n = scratch.shuffle_partitions(spark)
    every = short.unionByName(_split(several.where(F.col("n") > SPLIT)))
    return every.repartition(n, "posting", "part", "key").sortWithinPartitions("posting", "part", "key").mapInArrow(_posting_kernel, "u long, v long")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, mark, component_id: the smallest doc_id that links reach."""
    marked = scratch.written(with_fingerprints(docs), "simhash")
    nodes = marked.groupBy("mark").agg(F.min("doc_id").alias("least"))
    joined = components.components(links(marked)).withColumnRenamed("component", "root")
    rooted = nodes.join(joined, nodes["mark"] == joined["node"], "left").select("mark", "least", F.coalesce("root", "mark").alias("root"))
    rooted = scratch.written(rooted, "simhash-roots")
    smallest = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = rooted.join(smallest, "root").select("mark", "component_id")
    return marked.join(named, "mark")


def hex_of(mark: str):
    return F.lpad(F.lower(F.hex(mark)), 16, "0")


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(scratch.table(spark, sf_dir, "documents"))
    return found.select("doc_id", hex_of("mark").alias("fingerprint"), "component_id")


QUERIES = {"op9_simhash": op9_simhash}
ORACLE_SQL: dict[str, str] = {}
