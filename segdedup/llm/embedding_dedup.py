"""Embedding near-duplicates by product quantisation.

Fit (on at most SAMPLE vectors, those under a hash threshold): coarse centroids by k-means on
unit vectors, one list for LIST_ROWS vectors up to a list for SAMPLE_ROWS of the sample, and for
each of SUBSPACES parts of the residuals a codebook of CODES entries.
Index (every vector): the nearest list, the residual's codes, and the length of what the codes
miss. Search (every vector): the lists whose centroid is within MARGIN of the nearest one, at
most PROBES; in a list, distances come from the query's lookup table, code by code. As the true
distance is at least the looked-up one less what the codes miss, dropping vectors beyond that
bound loses no link in the lists probed. What is left is ranked anew by the exact cosine in
double precision. A link may be missed if neither vector's search probes the other's list: recall
is measured against brute force on planted pairs just above the limit (README, tests).

Equal vectors are one node, whatever the number of copies. Lists are cut into blocks
of a bounded number of members, so a crowded list is many tasks. A block gives, for each query, its number of links
(a pair that both ways find counts once each way) and the links of a spanning forest: counts
are those of all links found, components lose none, and no group gives all its pairs.

Vectors that are null, empty or zero, or hold null or non-finite components, link with nothing;
vectors of each length link among themselves. Repeated rows (equal vec_id too) are copies like any
other. An empty table gives an empty result; other columns are not looked at.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import components, scratch
from segdedup.llm import sampling

LEAST = 0.95
SAMPLE, LIST_ROWS, SAMPLE_ROWS = 131_072, 400, 8
SUBSPACES, CODES = 8, 64
PROBES, MARGIN = 8, 0.12
#: Members of a block at least and at most (it grows with the table, so that queries are copied to few blocks).
LEAST_BLOCK, MOST_BLOCK, BLOCKS = 2048, 65_536, 4096
QUERIES_AT_A_TIME = 512


@dataclass
class Quantiser:
    coarse: np.ndarray  # lists x dimensions
    books: np.ndarray  # subspaces x codes x dimensions of a part
    dims: int

    def parts(self, x: np.ndarray) -> np.ndarray:
        pad = self.books.shape[0] * self.books.shape[2] - x.shape[1]
        return np.pad(x, ((0, 0), (0, pad))).reshape(len(x), self.books.shape[0], self.books.shape[2])

    def nearest(self, x: np.ndarray, probes: int, margin: float) -> list[np.ndarray]:
        """Of each unit vector its lists, nearest first."""
        d = np.sqrt(np.maximum(0, (x**2).sum(1)[:, None] + (self.coarse**2).sum(1)[None, :] - 2 * x @ self.coarse.T))
        k = min(probes, d.shape[1])
        some = np.argpartition(d, k - 1, axis=1)[:, :k]
        order = np.argsort(np.take_along_axis(d, some, 1), axis=1, kind="stable")
        some = np.take_along_axis(some, order, 1)
        near = np.take_along_axis(d, some, 1)
        return [s[n <= n[0] + margin] for s, n in zip(some, near, strict=True)]

    def encode(self, x: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes of the residuals and the length of what they miss."""
        r = self.parts(x - self.coarse[home])
        codes = np.empty(r.shape[:2], dtype=np.uint8)
        miss = np.zeros(len(x))
        for s, book in enumerate(self.books):
            d = (r[:, s] ** 2).sum(1)[:, None] + (book**2).sum(1)[None, :] - 2 * r[:, s] @ book.T
            codes[:, s] = d.argmin(1)
            miss += ((r[:, s] - book[codes[:, s]]) ** 2).sum(1)
        return codes, np.sqrt(miss)

    def distances(self, x: np.ndarray, place: int, codes: np.ndarray) -> np.ndarray:
        """Looked-up distances from queries x to the coded members of a list."""
        r = self.parts(x - self.coarse[place])
        out = np.zeros((len(x), len(codes)))
        for s, book in enumerate(self.books):
            table = (r[:, s] ** 2).sum(1)[:, None] + (book**2).sum(1)[None, :] - 2 * r[:, s] @ book.T
            out += table[:, codes[:, s]]
        return np.sqrt(np.maximum(out, 0))


def _kmeans(x: np.ndarray, k: int, rounds: int = 10) -> np.ndarray:
    rng = np.random.default_rng(0)
    centres = x[rng.choice(len(x), size=min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        length = (centres**2).sum(1)[None, :]
        near = np.concatenate([(length - 2 * x[at : at + 2048] @ centres.T).argmin(1) for at in range(0, len(x), 2048)])
        n = np.bincount(near, minlength=len(centres))
        total = np.stack([np.bincount(near, x[:, d], minlength=len(centres)) for d in range(x.shape[1])], axis=1)
        centres[n > 0] = total[n > 0] / n[n > 0][:, None]
    return centres


def fit(sample: np.ndarray, rows: int) -> Quantiser:
    """sample: unit vectors; rows: how many vectors there are, which sets the number of lists."""
    lists = int(min(max(1, len(sample) // SAMPLE_ROWS), max(1, rows // LIST_ROWS)))
    coarse = _kmeans(sample, lists)
    dims = sample.shape[1]
    width = -(-dims // SUBSPACES)
    q = Quantiser(coarse, np.zeros((SUBSPACES, 1, width)), dims)
    home = np.array([n[0] for at in range(0, len(sample), 512) for n in q.nearest(sample[at : at + 512], 1, 0)])
    r = q.parts(sample - coarse[home])
    books = [_kmeans(r[:, s], CODES) for s in range(SUBSPACES)]
    q.books = np.stack(books)
    return q


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x**2).sum(1))[:, None]


def _assign(q: Quantiser):
    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = len(batch)
            x = batch.column("vector").flatten().to_numpy(zero_copy_only=False).reshape(n, q.dims) if n else np.zeros((0, q.dims))
            near = []
            for at in range(0, n, 512):
                near += q.nearest(_unit(x[at : at + 512]), PROBES, MARGIN)
            yield pa.RecordBatch.from_arrays([batch.column("node"), batch.column("copies"), batch.column("vector"), pa.array([p.tolist() for p in near], pa.list_(pa.int32()))], names=["node", "copies", "vector", "probes"])

    return assign


RESULT = pa.schema([("kind", pa.int32()), ("u", pa.int64()), ("v", pa.int64())])
LINK, COUNT = 0, 1


def _block_kernel(q: Quantiser, least: float):
    radius = float(np.sqrt(2 - 2 * least)) + 1e-9

    def search(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of one block come members first; queries follow in groups."""
        place = key[0].as_py()
        members: list[tuple] = []
        codes = miss = mx = mnorm = mnode = mcopies = None
        reach: list[set[int]] = []
        up: dict[int, int] = {}

        def root(i: int) -> int:
            while up.setdefault(i, i) != i:
                up[i] = up[up[i]]
                i = up[i]
            return i

        for batch in batches:
            n = len(batch)
            role = batch.column("role").to_numpy(zero_copy_only=False)
            node = batch.column("node").to_numpy(zero_copy_only=False)
            copies = batch.column("copies").to_numpy(zero_copy_only=False)
            x = batch.column("vector").flatten().to_numpy(zero_copy_only=False).reshape(n, q.dims).astype(np.float64)
            probes = batch.column("probes").to_pylist()
            inside = role == 0
            if inside.any():
                members.append((node[inside], copies[inside], x[inside], [set(p) for p, m in zip(probes, inside, strict=True) if m]))
            if inside.all() or not members:
                continue
            if codes is None or len(mnode) != sum(len(m[0]) for m in members):
                mnode, mcopies, mx = (np.concatenate(c) for c in list(zip(*members, strict=True))[:3])
                reach = [p for m in members for p in m[3]]
                codes, miss = q.encode(_unit(mx), np.full(len(mx), place))
                mnorm = np.sqrt((mx**2).sum(1))
            pick = np.flatnonzero(~inside)
            step = max(16, QUERIES_AT_A_TIME * LEAST_BLOCK // max(LEAST_BLOCK, len(mnode)))
            for at in range(0, len(pick), step):
                rows = pick[at : at + step]
                qx = x[rows]
                maybe = q.distances(_unit(qx), place, codes) - miss[None, :] <= radius
                i, j = np.nonzero(maybe)
                apart = node[rows][i] != mnode[j]
                i, j = i[apart], j[apart]
                cosine = np.concatenate([(qx[i[k : k + 65536]] * mx[j[k : k + 65536]]).sum(1) for k in range(0, len(i), 65536)]) if len(i) else np.zeros(0)
                good = cosine >= least * np.sqrt((qx**2).sum(1))[i] * mnorm[j]
                i, j = i[good], j[good]
                if not len(i):
                    continue
                home = [p[0] for p in (probes[r] for r in rows)]
                both = np.array([home[a] in reach[b] for a, b in zip(i.tolist(), j.tolist(), strict=True)])
                links, found = [], {}
                for a, b, other in zip(i.tolist(), j.tolist(), both.tolist(), strict=True):
                    u, v = int(node[rows[a]]), int(mnode[b])
                    found[u] = found.get(u, 0) + int(mcopies[b])
                    if not other:  # v's own search does not look into u's list
                        found[v] = found.get(v, 0) + int(copies[rows[a]])
                    ru, rv = root(u), root(v)
                    if ru != rv:
                        up[max(ru, rv)] = min(ru, rv)
                        links.append((u, v))
                u = [a for a, _ in links] + list(found)
                v = [b for _, b in links] + list(found.values())
                yield pa.RecordBatch.from_arrays([pa.array([LINK] * len(links) + [COUNT] * len(found), pa.int32()), pa.array(u, pa.int64()), pa.array(v, pa.int64())], schema=RESULT)

    return search


def deduplicate(vectors: DataFrame, least: float = LEAST) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row of vectors (vec_id, embedding)."""
    as_double = F.col("embedding").cast("array<double>")
    finite = F.forall("vector", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    usable = F.coalesce(finite & F.exists("vector", lambda v: v != 0), F.lit(False))
    rows = scratch.written(vectors.select(F.col("vec_id").cast("long"), as_double.alias("vector")).withColumn("usable", usable), "vectors")
    found = rows.where(~F.col("usable")).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    lengths = rows.where("usable").select(F.size("vector").alias("dims")).distinct().collect()  # as many as there are lengths
    for (dims,) in sorted(map(tuple, lengths)):
        found = found.unionByName(_linked(rows.where(F.col("usable") & (F.size("vector") == dims)), least))
    return found.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def _linked(rows: DataFrame, least: float) -> DataFrame:
    """vec_id, n_links, component_id of usable vectors of one length."""
    # one node for each distinct vector; -0.0 is 0.0
    good = rows.select("vec_id", F.transform("vector", lambda v: v + F.lit(0.0)).alias("vector"))
    nodes = scratch.written(good.groupBy("vector").agg(F.min("vec_id").alias("node"), F.count(F.lit(1)).alias("copies")), "vector-nodes")
    n = nodes.count()
    sample = sampling.least_hashed(nodes, F.col("vector"), SAMPLE).select("vector").toArrow().column("vector").combine_chunks()  # at most SAMPLE
    drawn = sample.flatten().to_numpy(zero_copy_only=False).reshape(len(sample), -1)
    q = fit(_unit(drawn[np.lexsort(drawn.T[::-1])]), n)

    placed = scratch.written(nodes.mapInArrow(_assign(q), "node long, copies long, vector array<double>, probes array<int>"), "vector-lists")
    home = F.col("probes")[0]
    size = min(MOST_BLOCK, max(LEAST_BLOCK, n // BLOCKS))
    crowd = placed.groupBy(home.alias("list")).agg(F.ceil(F.count(F.lit(1)) / size).cast("int").alias("n_blocks"))
    crowd = F.broadcast(crowd)  # no more rows than lists: SAMPLE / SAMPLE_ROWS
    block = F.pmod(F.xxhash64("node"), F.col("n_blocks")).cast("int")
    members = placed.withColumn("list", home).join(crowd, "list").select("list", block.alias("block"), F.lit(0).alias("role"), "node", "copies", "vector", "probes")
    queries = placed.withColumn("list", F.explode("probes")).join(crowd, "list").withColumn("block", F.explode(F.sequence(F.lit(0), F.col("n_blocks") - 1)))
    both = members.unionByName(queries.select("list", "block", F.lit(1).alias("role"), "node", "copies", "vector", "probes"))
    found = scratch.written(_per_block(both, q, least), "vector-links")

    counts = found.where(F.col("kind") == COUNT).groupBy(F.col("u").alias("node")).agg(F.sum("v").alias("others"))
    joined = components.components(found.where(F.col("kind") == LINK).select("u", "v"))
    named = nodes.join(counts, "node", "left").join(joined, "node", "left").select("vector", (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    return good.join(named, "vector").select("vec_id", "n_links", "component_id")


def _per_block(both: DataFrame, q: Quantiser, least: float) -> DataFrame:
    """Streams each block's rows, members first, through the search."""
    search = _block_kernel(q, least)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from itertools import groupby

        def pieces():
            for batch in batches:
                place = batch.column("list").to_numpy(zero_copy_only=False).astype(np.int64) << 32 | batch.column("block").to_numpy(zero_copy_only=False)
                cuts = [0, *(np.flatnonzero(np.diff(place)) + 1).tolist(), len(place)]
                for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                    if b > a:
                        yield int(place[a]), batch.slice(a, b - a)

        for key, group in groupby(pieces(), key=lambda p: p[0]):
            yield from search((pa.scalar(key >> 32), pa.scalar(key & 0xFFFFFFFF)), (piece for _, piece in group))

    n = scratch.shuffle_partitions(both.sparkSession)
    return both.repartition(n, "list", "block").sortWithinPartitions("list", "block", "role").mapInArrow(run, "kind int, u long, v long")


def op10_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(scratch.table(spark, sf_dir, "embeddings"))


QUERIES = {"op10_embedding_dedup": op10_embedding_dedup}
ORACLE_SQL: dict[str, str] = {}
