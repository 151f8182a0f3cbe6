"""Order-preserving packing: window cuts by dynamic programming with a monotone queue.

Documents in ascending doc_id are one stream of ids (each ends with END_ID); a sequence is a
window of at most `capacity` ids. Windows may end after a document (free), after a sentence
(SENTENCE_PENALTY) or, where a sentence runs on for long, every STRIDE ids (INNER_PENALTY).
With T the stream position of a cut and f the least cost up to it,

    f(j) = min over i, T(j) - T(i) <= capacity, of f(i) + capacity - (T(j) - T(i)) + penalty(j)

so f(i) + T(i) decides alone, and a queue kept increasing in it gives each minimum in amortised
constant time. Each range partition is a stream of its own and ends with one window that may
be short; the cost of padding nowhere else is more than the cuts allow.

Pieces of a document are the parts of it that windows hold. A null or empty text is just the
end id, a very long one has a piece in each of many windows. Repeated rows are packed as often
as they occur, null doc_ids come first, an empty table gives no pieces. Columns other than doc_id
and text are not looked at.
"""

from __future__ import annotations

import json
import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from segdedup import scratch
from segdedup.llm import tokens

CAPACITY, END_ID = 1024, 0
SENTENCE_PENALTY, INNER_PENALTY, STRIDE = 1.0, 4.0, 24
#: Ids of a stream that are held and decided at a time; the queue restarts at a chosen cut.
STREAM_IDS = 1 << 20
VOCABULARY = "byte_bpe_50k.json"
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def sentence_ends(vocabulary: str) -> np.ndarray:
    """Of each id, whether its string ends a sentence or a line."""
    with open(vocabulary, encoding="utf-8") as f:
        vocab = json.load(f)["model"]["vocab"]
    ends = np.zeros(max(vocab.values()) + 1, dtype=bool)
    for piece, i in vocab.items():
        ends[i] = piece.endswith((".", "!", "?", "Ċ"))
    return ends


def cut_points(ends: np.ndarray, doc_ends: np.ndarray, stride: int = STRIDE) -> tuple[np.ndarray, np.ndarray]:
    """Positions where a window may end, ascending, and their penalties; the last id is one."""
    docs = doc_ends
    sentences = np.setdiff1d(np.flatnonzero(ends) + 1, docs)
    at = np.concatenate([docs, sentences])
    cost = np.concatenate([np.zeros(len(docs)), np.full(len(sentences), SENTENCE_PENALTY)])
    order = np.argsort(at, kind="stable")
    at, cost = at[order], cost[order]
    before = np.concatenate([[0], at[:-1]])
    wide = np.flatnonzero(at - before > stride)
    if len(wide):
        inner = np.concatenate([np.arange(a + stride, b, stride) for a, b in zip(before[wide].tolist(), at[wide].tolist(), strict=True)])
        at, cost = np.concatenate([at, inner]), np.concatenate([cost, np.full(len(inner), INNER_PENALTY)])
        order = np.argsort(at, kind="stable")
        at, cost = at[order], cost[order]
    return at, cost


def choose(at: list[int], penalty: list[float], capacity: int = CAPACITY) -> list[int]:
    """Ends of the windows of least cost over the cut points `at`, the last of them included."""
    place, best, came = [0, *at], [0.0], [0]
    queue = deque([(0.0, 0)])  # (f + T, index), increasing in both
    for j in range(1, len(place)):
        t = place[j]
        while place[queue[0][1]] < t - capacity:
            queue.popleft()
        low, i = queue[0]
        f = low + capacity - t + penalty[j - 1]
        best.append(f)
        came.append(i)
        key = f + t
        while queue and queue[-1][0] >= key:
            queue.pop()
        queue.append((key, j))
    out, j = [], len(place) - 1
    while j:
        out.append(place[j])
        j = came[j]
    return out[::-1]


def _packer(vocabulary: str, capacity: int, end_id: int):
    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        first = TaskContext.get().partitionId() << 40
        encode, is_end, end = tokens.encoder(vocabulary), sentence_ends(vocabulary), np.array([end_id], dtype="<u2")
        held: list[tuple[int | None, np.ndarray, int, int]] = []  # doc_id, ids from `start` on, start, doc_tokens
        size = number = 0

        def windows(last: bool) -> pa.RecordBatch:
            """Pieces of the windows decided; what lies after the cut before last is held on."""
            nonlocal held, size, number
            ids = np.concatenate([h[1] for h in held])
            doc_ends = np.cumsum([len(h[1]) for h in held])
            at, cost = cut_points(is_end[np.minimum(ids, len(is_end) - 1)], doc_ends)
            chosen = np.array(choose(at.tolist(), cost.tolist(), capacity))
            if not last:
                chosen = chosen[: max(1, len(chosen) * 9 // 10)]
            stop = int(chosen[-1])
            edges = np.union1d(np.concatenate([[0], chosen]), doc_ends[doc_ends < stop])
            a, b = edges[:-1], edges[1:]
            doc, window = np.searchsorted(doc_ends, a, side="right"), np.searchsorted(chosen, a, side="right")
            doc_first = np.concatenate([[0], doc_ends[:-1]])
            window_first = np.concatenate([[0], chosen[:-1]])
            raw = memoryview(ids.astype("<u4").tobytes())
            crc = [zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(a.tolist(), b.tolist(), strict=True)]
            start = a - doc_first[doc] + np.array([h[2] for h in held])[doc]
            columns = [pa.array([held[d][0] for d in doc.tolist()], pa.int64()), pa.array(start, pa.int64()), pa.array(b - a, pa.int64()), pa.array(crc, pa.int64()), pa.array(np.array([h[3] for h in held])[doc], pa.int64()), pa.array(window + (first + number), pa.int64()), pa.array(a - window_first[window], pa.int64())]
            number += len(chosen)
            done = int(np.searchsorted(doc_ends, stop, side="right"))
            rest = held[done:]
            if rest and stop > doc_first[done]:
                key, left, began, whole = rest[0]
                cut = stop - int(doc_first[done])
                rest[0] = (key, left[cut:], began + cut, whole)
            held, size = rest, len(ids) - stop
            return pa.RecordBatch.from_arrays(columns, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for batch in batches:
            for key, got in zip(batch.column("doc_id").to_pylist(), tokens.batches(encode, (t.as_py() for t in batch.column("text"))), strict=True):
                ids = np.concatenate([got, end])
                held.append((key, ids, 0, len(ids)))
                size += len(ids)
                if size >= STREAM_IDS:
                    yield windows(False)
        if held:
            yield windows(True)

    return pack


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """The pieces of docs (doc_id, text) in their sequences."""
    return tokens.ordered(docs, tokens.partitions_for(docs.sparkSession)).mapInArrow(_packer(vocabulary, capacity, end_id), SCHEMA)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(scratch.table(spark, sf_dir, "documents"), public_tokenizers.path(VOCABULARY))


QUERIES = {"op7_packing": op7_packing}
ORACLE_SQL: dict[str, str] = {}
