"""Every pair of texts whose 5-word shingle sets have a Jaccard similarity of 0.8 or more, as links.

Equal sets are one node, named by a hash of the set. Two sets of sizes a and b at 0.8 or more
differ in at most (a + b) / 9 shingles. Sizes fall into levels that grow by a quarter, so such a
pair lies in one level or in two adjacent ones. Each set deals its shingles by hash into
the buckets of its own level and of the next; a level has more buckets than a pair can differ
in, so some are equal. As many as a set has empty are not counted on: where a set has so many
empty buckets that none might be left, it posts the empty ones too. Postings of equal buckets
are thus a complete list of candidates. A passage that many texts share makes few of them,
since a bucket of several shingles is equal as a whole or not at all.

Of each posting all sets are compared with the first one, so a group of near copies costs about
one comparison a member, and then each with its nearest of another component. What is then still in
different components of one posting is compared by parity sketches: an element flips one of SKETCH bits, so the sketches of two sets differ in no
more bits than the sets do in elements, and a pair whose sketches differ in more than (a + b) / 9
bits is no link. A task holds one block of a posting against another and gives only the pairs
that may be links, which are few; no pair between components is left out. Before whole sets are
fetched, wide sketches, of a bit or more for each element, rule out pairs of long sets. A link is
kept if the whole sets confirm it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segdedup import components, scratch
from segdedup.llm import simhash, tokens

WIDTH, NUM, DEN = 5, 4, 5
#: Bits of a parity sketch, and sets of a posting that a task holds against as many others.
SKETCH, BLOCK = 1024, 2048
#: Bits of a posting's key; keys that meet by chance cost a comparison of sketches, no more.
KEY = np.uint64((1 << 48) - 1)
_SPREAD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD], dtype=np.uint64)


def _levels(most: int = 1 << 40) -> list[int]:
    found = [1]
    while found[-1] < most:
        found.append(max(found[-1] + 1, -(-found[-1] * DEN // NUM)))
    return found


LEVELS = np.array(_levels())


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(32))


def shingles(text: str | None) -> np.ndarray:
    """Sorted distinct hashes of the shingles; a shorter text is one shingle, one without words has none."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    digest = xxhash.xxh64_intdigest
    if len(words) < WIDTH:
        return np.array([digest(b" ".join(words), 1)], dtype=np.uint64)
    own = np.fromiter(map(digest, words), dtype=np.uint64, count=len(words))
    n = len(own) - WIDTH + 1
    total = np.zeros(n, dtype=np.uint64)
    for k in range(WIDTH):
        total += _mix(own[k : k + n] + _SPREAD[k])
    return np.unique(_mix(total))


def postings(ids: np.ndarray) -> np.ndarray:
    """Keys of the buckets of a set, at its level and the next."""
    n = len(ids)
    own = int(np.searchsorted(LEVELS, n, side="right")) - 1
    keys = []
    for level in (own, own + 1):
        top = int(LEVELS[level + 1]) - 1
        differ = 2 * top // 9
        buckets = differ + differ // 12 + 2
        at = ids % np.uint64(buckets)
        order = np.argsort(at)
        at = at[order]
        starts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
        value, named = np.add.reduceat(_mix(ids[order]), starts), at[starts]
        # a partner differs in no more than this, and so many buckets are equal at least
        sure = buckets - (n + min(top, n * DEN // NUM)) // 9
        if buckets - len(named) >= sure:
            empty = np.setdiff1d(np.arange(buckets, dtype=np.uint64), named)
            value, named = np.concatenate([value, np.zeros(len(empty), dtype=np.uint64)]), np.concatenate([named, empty])
        keys.append(_mix(value + _mix(named + np.uint64(level << 40))) & KEY)
    return np.concatenate(keys)


def _node(ids: np.ndarray) -> int:
    import xxhash

    return int(np.uint64(xxhash.xxh64_intdigest(ids.tobytes())).view(np.int64)) if len(ids) else 0


def sketch(ids: np.ndarray, width: int = SKETCH) -> bytes:
    """Parity of the elements that fall on each of width bits, a power of two."""
    bits = np.bincount((_mix(ids ^ _SPREAD[0]) % np.uint64(width)).astype(np.int64), minlength=width) & 1
    return np.packbits(bits.astype(np.uint8)).tobytes()


def wide_sketch(ids: np.ndarray) -> bytes:
    """A sketch with a bit or more for each element: one of fixed width says nothing of long sets."""
    return sketch(ids, max(SKETCH, 1 << (len(ids) - 1).bit_length() if len(ids) else 0))


def least_difference(x: bytes, y: bytes) -> int:
    """Bits in which two wide sketches differ, the wider folded to the other: the sets differ in no fewer elements."""
    x, y = sorted((np.frombuffer(z, dtype="<u8") for z in (x, y)), key=len)
    return int(np.bitwise_count(x ^ np.bitwise_xor.reduce(y.reshape(-1, len(x)), axis=0)).sum())


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tokens.forget()
    for batch in batches:
        marks, nodes, sizes, sketches, wide = [], [], [], [], []
        for cell in batch.column(2):
            text = cell.as_py()
            ids = shingles(text)
            marks.append(simhash.fingerprint(text))
            nodes.append(_node(ids))
            sizes.append(len(ids))
            sketches.append(sketch(ids))
            wide.append(wide_sketch(ids))
        columns = [pa.array(c, pa.int64()) for c in (marks, nodes, sizes)] + [pa.array(c, pa.binary()) for c in (sketches, wide)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], names=["row_key", "doc_id", "mark", "node", "n", "sketch", "wide"])


def _post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tokens.forget()
    for batch in batches:
        for at in range(0, len(batch), 500):
            sets = [s for t in batch.column(0).slice(at, 500) if len(s := shingles(t.as_py()))]
            made = [postings(s) for s in sets]
            if made:
                own = np.repeat(np.array(list(map(_node, sets)), dtype=np.int64), list(map(len, made)))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(made).view(np.int64)), pa.array(own)], names=["key", "node"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [shingles(t.as_py()) for t in batch.column(0)]
        yield pa.RecordBatch.from_arrays([pa.array(list(map(_node, sets)), pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], names=["node", "ids"])


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by key; the distinct nodes of each key that has two or more."""
    key, node = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    pairs, others, seen = [], [], set()

    def close(key: np.ndarray, node: np.ndarray) -> None:
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, dtype=np.int64)
        size = np.diff(np.append(starts, len(key)))
        two = starts[size == 2]
        a, b = np.minimum(node[two], node[two + 1]), np.maximum(node[two], node[two + 1])
        pairs.append(np.stack([a, b], axis=1)[a != b])
        for s, n in zip(starts[size > 2].tolist(), size[size > 2].tolist(), strict=True):
            own = np.unique(node[s : s + n])
            if len(own) > 1 and (mark := hash(own.tobytes())) not in seen:
                seen.add(mark)
                others.append(own)

    def out() -> pa.RecordBatch:
        found = np.concatenate([np.zeros((0, 2), dtype=np.int64), *pairs])
        found = np.unique(np.ascontiguousarray(found).view([("a", "<i8"), ("b", "<i8")]))
        sizes = [2] * len(found) + list(map(len, others))
        flat = np.concatenate([found.view("<i8").reshape(-1), *others]) if sizes else np.zeros(0, dtype=np.int64)
        ends = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
        pairs.clear()
        others.clear()
        seen.clear()
        return pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=["nodes"])

    held = 0
    for batch in batches:
        if not len(batch):
            continue
        key, node = np.concatenate([key, batch.column(0).to_numpy()]), np.concatenate([node, batch.column(1).to_numpy()])
        whole = int(np.searchsorted(key, key[-1]))  # the last key may go on
        close(key[:whole], node[:whole])
        key, node = key[whole:], node[whole:]
        held += len(batch)
        if held > 4_000_000:
            held = 0
            yield out()
    close(key, node)
    yield out()


def _able(n: np.ndarray, marks: np.ndarray, label: np.ndarray, other: slice, own: slice, nearest: bool) -> tuple[np.ndarray, np.ndarray]:
    """Places of the pairs that sizes, labels and sketches allow to be links, own against other; of each own one only the nearest, if asked."""
    x, y = np.arange(len(n))[own], np.arange(len(n))[other]
    out = []
    for at in range(0, len(x), 128):
        i = x[at : at + 128]
        total = n[i][:, None] + n[y][None, :]
        far = np.zeros(total.shape, dtype=np.int64)
        for k in range(marks.shape[1]):
            far += np.bitwise_count(marks[i, k][:, None] ^ marks[y, k][None, :])
        sized = (n[i][:, None] * DEN >= n[y][None, :] * NUM) & (n[y][None, :] * DEN >= n[i][:, None] * NUM)
        good = (label[i][:, None] != label[y][None, :]) & (9 * far <= total) & sized
        if nearest and good.size:
            b = np.where(good, 9 * far - total, np.iinfo(np.int64).max).argmin(axis=1)
            a = np.flatnonzero(good[np.arange(len(i)), b])
            b = b[a]
        else:
            a, b = np.nonzero(good)
        out.append((i[a], y[b]))
    return tuple(np.concatenate(c) if out else np.zeros(0, dtype=np.int64) for c in (zip(*out, strict=True) if out else [(), ()]))


def _block_pairs(nearest: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by gid, a, b (a pair of blocks); candidates between the sets of blocks a and b."""
        found: set[tuple[int, int]] = set()
        held: list[pa.RecordBatch] = []
        now = None

        def close() -> None:
            if not held:
                return
            rows = pa.Table.from_batches(held).combine_chunks()
            node, label, n, block = (rows.column(c).to_numpy() for c in ("node", "label", "n", "block"))
            order = np.argsort(block, kind="stable")
            node, label, n = node[order], label[order], n[order]
            marks = np.frombuffer(b"".join(rows.column("sketch").take(pa.array(order)).to_pylist()), dtype="<u8").reshape(len(node), -1)
            _, a, b = now
            cut = int(np.searchsorted(block[order], a, side="right"))
            own, other = (slice(0, len(node)), slice(0, len(node))) if a == b else (slice(0, cut), slice(cut, len(node)))
            i, j = _able(n, marks, label, other, own, nearest)
            u, v = node[i], node[j]
            lower, upper = np.minimum(u, v), np.maximum(u, v)
            found.update(zip(lower[lower != upper].tolist(), upper[lower != upper].tolist(), strict=True))

        def out() -> pa.RecordBatch:
            pairs = np.array(sorted(found), dtype=np.int64).reshape(-1, 2)
            found.clear()
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["u", "v"])

        for batch in batches:
            keys = [batch.column(c).to_numpy() for c in ("gid", "a", "b")]
            cuts = np.flatnonzero(np.any([np.diff(k) != 0 for k in keys], axis=0)) + 1
            edges = [0, *cuts.tolist(), len(batch)]
            for x, y in zip(edges[:-1], edges[1:], strict=True):
                if x == y:
                    continue
                this = tuple(int(k[x]) for k in keys)
                if this != now:
                    close()
                    now, held = this, []
                held.append(batch.slice(x, y - x))
            if len(found) > 100_000:
                yield out()
        close()
        yield out()

    return run


def _plausible(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """u, v, their sizes and wide sketches come in; the pairs that may be links go out."""
    for batch in batches:
        both = zip(batch.column("u_wide"), batch.column("v_wide"), strict=True)
        far = np.array([least_difference(x.as_py(), y.as_py()) for x, y in both], dtype=np.int64)
        n, m = batch.column("u_n").to_numpy(), batch.column("v_n").to_numpy()
        good = (9 * far <= n + m) & (n * DEN >= m * NUM) & (m * DEN >= n * NUM)
        yield batch.select(["u", "v"]).filter(pa.array(good))


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        good = []
        for x, y in zip(batch.column(2), batch.column(3), strict=True):
            x, y = (np.frombuffer(z.as_py(), dtype=np.uint64) for z in (x, y))
            able = len(x) * DEN >= len(y) * NUM and len(y) * DEN >= len(x) * NUM
            both = len(np.intersect1d(x, y, assume_unique=True)) if able else 0
            good.append(both * DEN >= (len(x) + len(y) - both) * NUM)
        kept = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["u", "v"])
        yield kept.filter(pa.array(good, pa.bool_()))


def read(docs: DataFrame) -> DataFrame:
    """row_key, doc_id, mark (SimHash), node (hash of the shingle set, 0 if empty), n, sketch, wide; written."""
    rows = docs.select(row_key(), F.col("doc_id").cast("long").alias("doc_id"), "text")
    return scratch.written(rows.mapInArrow(_read, "row_key string, doc_id long, mark long, node long, n long, sketch binary, wide binary"), "near-rows")


def row_key():
    """Rows of one doc_id (or none) and text."""
    text = F.when(F.col("text").isNull(), "-").otherwise(F.concat(F.lit("="), "text"))
    return F.md5(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.lit(" "), text)).alias("row_key")


def _candidates(docs: DataFrame) -> DataFrame:
    """gid, nodes: the distinct postings of two nodes or more; written."""
    n = scratch.shuffle_partitions(docs.sparkSession)
    posted = docs.select("text").mapInArrow(_post, "key long, node long")
    found = posted.repartition(n, "key").sortWithinPartitions("key").mapInArrow(_groups, "nodes array<long>")
    return scratch.written(found.distinct().withColumn("gid", F.monotonically_increasing_id()), "near-groups")


def _wanted(docs: DataFrame, rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, ids: the shingle sets of the nodes, each once; written."""
    first = rows.where("node <> 0").groupBy("node").agg(F.min("row_key").alias("row_key"))
    one = first.join(nodes.distinct(), "node", "left_semi").select("row_key")
    texts = docs.select(row_key(), "text").join(one, "row_key", "left_semi").dropDuplicates(["row_key"])
    return scratch.written(texts.select("text").mapInArrow(_sets, "node long, ids binary"), "near-sets")


def _across(open_: DataFrame, sets: DataFrame, nearest: bool = False) -> DataFrame:
    """u, v: pairs of one posting and different labels that sketches do not rule out; open_: gid, node, label.

    nearest: of each node only the pair with the nearest sketch in each block.
    """
    n = scratch.shuffle_partitions(open_.sparkSession)
    many = open_.groupBy("gid").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    placed = open_.join(many, "gid").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    # block x meets every block: as a where x <= y, as b where not
    dealt = placed.withColumn("y", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("gid", F.least("block", "y").alias("a"), F.greatest("block", "y").alias("b"), "block", "node", "label")
    sized = dealt.join(sets.select("node", "n", "sketch"), "node").select("gid", "a", "b", "block", "node", "label", "n", "sketch")
    return sized.repartition(n, "gid", "a", "b").sortWithinPartitions("gid", "a", "b").mapInArrow(_block_pairs(nearest), "u long, v long").distinct()


def links(docs: DataFrame, rows: DataFrame) -> DataFrame:
    """u, v: links between nodes at 0.8 or more that keep every component of such pairs; rows: read(docs)."""
    spark = docs.sparkSession
    groups = _candidates(docs)
    scratch.release(spark)
    flat = groups.select("gid", F.explode("nodes").alias("node"))
    nodes = scratch.written(rows.where("node <> 0").select("node", "n", "sketch", "wide").dropDuplicates(["node"]), "near-nodes")

    def confirmed(pairs: DataFrame) -> DataFrame:
        """Of written pairs those that the whole sets confirm."""
        sets = _wanted(docs, rows, pairs.select(F.explode(F.array("u", "v")).alias("node")))
        left, right = (sets.select(F.col("node").alias(i), F.col("ids").alias(f"{i}_ids")) for i in "uv")
        both = pairs.join(left, "u").join(right, "v").select("u", "v", "u_ids", "v_ids")
        found = scratch.written(both.mapInArrow(_confirm, "u long, v long"), "near-links")
        del left, right, both
        scratch.drop(sets)
        scratch.release(spark)
        return found

    def plausible(pairs: DataFrame) -> DataFrame:
        left, right = (nodes.select(F.col("node").alias(i), F.col("n").alias(f"{i}_n"), F.col("wide").alias(f"{i}_wide")) for i in "uv")
        return pairs.join(left, "u").join(right, "v").mapInArrow(_plausible, "u long, v long")

    stars = groups.select(F.element_at("nodes", 1).alias("u"), F.explode("nodes").alias("v")).where("u <> v").distinct()
    stars = scratch.written(plausible(stars), "near-stars")
    scratch.release(spark)
    sure = confirmed(stars)
    # each node with its nearest, so that most components are whole before all is compared
    for nearest in (True, False):
        open_ = _open(flat, components.components(sure))
        rest = scratch.written(_across(open_, nodes, nearest).join(stars, ["u", "v"], "left_anti"), "near-rest")
        late = confirmed(scratch.written(plausible(rest), "near-able"))
        scratch.drop(open_)
        sure = scratch.written(sure.union(late), "near-sure")
        stars = scratch.written(stars.union(rest), "near-asked")
    scratch.drop(groups, nodes)
    return sure


def _open(flat: DataFrame, joined: DataFrame) -> DataFrame:
    """gid, node, label of the postings that hold different components; written."""
    named = flat.join(joined, "node", "left").select("gid", "node", F.coalesce("component", "node").alias("label"))
    named = scratch.written(named, "near-named")
    mixed = named.groupBy("gid").agg(F.min("label").alias("a"), F.max("label").alias("b")).where("a <> b").select("gid")
    found = scratch.written(named.join(mixed, "gid", "left_semi"), "near-open")
    scratch.drop(named)
    return found


def _by_mark(rows: DataFrame, close: DataFrame) -> DataFrame:
    """u, v: marks and their nodes, where a mark joins nodes: it has several, or a link of its own (close)."""
    pairs = rows.select("mark", "node").distinct()
    several = pairs.groupBy("mark").agg(F.min("node").alias("a"), F.max("node").alias("b")).where("a <> b").select("mark")
    linked = close.select(F.explode(F.array("u", "v")).alias("mark"))
    joins = several.union(linked).distinct()
    return pairs.join(joins, "mark", "left_semi").select(F.col("mark").alias("u"), F.col("node").alias("v"))


def one_of_each(docs: DataFrame) -> DataFrame:
    """Of each component of rows (same set, 0.8 or more, or SimHash within op9's bits) one row.

    It is the one of the smallest doc_id, a null one last; which of its texts, if that doc_id
    has several in the component, is settled by a hash. doc_id itself links nothing.
    """
    rows = read(docs)
    close = scratch.written(simhash.links(rows), "near-marks")
    joined = components.components(links(docs, rows).union(close).union(_by_mark(rows, close)))
    small = rows.select("row_key", "doc_id", "node")
    rooted = small.join(joined, "node", "left").withColumn("root", F.coalesce("component", "node"))
    best = rooted.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "row_key")).alias("best"))
    chosen = scratch.written(best.select("best.row_key"), "near-chosen")
    scratch.release(docs.sparkSession)
    fields = [F.col(f"`{c}`") for c in docs.columns]
    keyed = docs.select(row_key(), F.struct(*fields).alias("row")).join(chosen, "row_key", "left_semi")
    others = [F.col("row").getField(c) for c in docs.columns if c not in ("doc_id", "text")]
    first = Window.partitionBy("row_key").orderBy(*(others or [F.lit(0)]))  # of repeated rows one
    return keyed.withColumn("place", F.row_number().over(first)).where("place = 1").select("row.*")
