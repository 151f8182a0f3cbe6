"""Quality classifier: a generalised additive model with pairwise interactions.

Features are ratios of the measures of quality_rules, taken over whole texts. Each feature is
cut into at most BINS quantile bins. Boosting goes round the features in a cycle: on the
gradient of the log loss it fits a tree of at most four leaves over the one feature's bins and
adds a small step of it to that feature's lookup table. Then the PAIRS pairs of features with
the largest gain left get tables over coarser bins in the same way. A score is the sum of the
looked-up values, by vectorised additions.

Labels come from at most MAX_ROWS labelled documents that are not held out, those under a hash
threshold of doc_id. labels, lang, source and doc_id are never inputs of a score. Null and empty
texts are scored like any other (all features at zero), very long ones whole. A doc_id counts once
for each label it has, whatever its repeated rows. Without labels of both kinds every score is 0.5.
Null doc_ids are scored and never held out, an empty table gives an empty result, columns other
than doc_id and text are not looked at.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch
from segdedup.llm import quality_rules, sampling

MAX_ROWS, BINS, PAIR_BINS, PAIRS = 20_000, 32, 8, 5
ROUNDS, PAIR_ROUNDS, RATE = 120, 60, 0.1
PREDICT_FROM = 0.7


def features() -> dict[str, Column]:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    lines = F.greatest(F.col("n_lines"), F.lit(1)).cast("double")
    return {
        "f_words": F.ln(n),
        "f_word_length": F.col("word_chars") / n,
        "f_symbols": F.col("n_symbols") / n,
        "f_dup_lines": F.col("n_dup_lines") / lines,
        "f_repeats": F.col("n_repeat_words") / n,
        "f_shouts": F.col("n_shouts") / n,
        "f_capitals": F.col("n_capitals") / n,
        "f_stops": F.col("n_stops") / n,
        "f_variety": F.col("n_distinct") / n,
        "f_line_words": F.ln(n / lines),
    }


@dataclass
class Model:
    base: float
    edges: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int]] = field(default_factory=list)
    pair_edges: list[np.ndarray] = field(default_factory=list)
    pair_tables: list[np.ndarray] = field(default_factory=list)

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of label 1 of each row of x."""
        z = np.full(len(x), self.base)
        for k, (edges, table) in enumerate(zip(self.edges, self.tables, strict=True)):
            z += table[np.searchsorted(edges, x[:, k], side="right")]
        coarse = [np.searchsorted(e, x[:, k], side="right") for k, e in enumerate(self.pair_edges)]
        for (i, j), table in zip(self.pairs, self.pair_tables, strict=True):
            z += table[coarse[i], coarse[j]]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _quantiles(x: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(x, np.linspace(0, 1, bins + 1)[1:-1]))


def _split(g: np.ndarray, h: np.ndarray) -> tuple[float, int]:
    """Gain and place of the best cut of a run of bins."""
    if len(g) < 2:
        return 0.0, 0
    a, b = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    gain = a**2 / (b + 1) + (g.sum() - a) ** 2 / (h.sum() - b + 1) - g.sum() ** 2 / (h.sum() + 1)
    k = int(np.argmax(gain))
    return float(gain[k]), k + 1


def _tree(g: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Leaf values over the bins, of a tree of depth two."""
    out, runs = np.zeros(len(g)), [(0, len(g))]
    for _ in range(2):
        deeper = []
        for a, b in runs:
            gain, cut = _split(g[a:b], h[a:b])
            deeper += [(a, a + cut), (a + cut, b)] if gain > 1e-9 else [(a, b)]
        runs = deeper
    for a, b in runs:
        out[a:b] = g[a:b].sum() / (h[a:b].sum() + 1)
    return out


def _corner(g: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray]:
    """Gain and leaf values of the best pair of cuts, one on each axis."""
    best, value = 0.0, np.zeros_like(g)
    base = g.sum() ** 2 / (h.sum() + 1)
    for i in range(1, g.shape[0]):
        for j in range(1, g.shape[1]):
            gain, leaves = -base, np.zeros_like(g)
            for rows in (slice(0, i), slice(i, None)):
                for cols in (slice(0, j), slice(j, None)):
                    a, b = g[rows, cols].sum(), h[rows, cols].sum()
                    gain += a**2 / (b + 1)
                    leaves[rows, cols] = a / (b + 1)
            if gain > best:
                best, value = gain, leaves
    return best, value


def train(x: np.ndarray, y: np.ndarray) -> Model:
    if len(y) == 0 or y.min() == y.max():
        return Model(0.0)
    rate = y.mean()
    model = Model(float(np.log(rate / (1 - rate))))
    model.edges = [_quantiles(c, BINS) for c in x.T]
    bins = [np.searchsorted(e, c, side="right") for e, c in zip(model.edges, x.T, strict=True)]
    model.tables = [np.zeros(len(e) + 1) for e in model.edges]
    z = np.full(len(y), model.base)
    for _ in range(ROUNDS):
        for k, b in enumerate(bins):
            p = 1 / (1 + np.exp(-z))
            n = len(model.tables[k])
            step = RATE * _tree(np.bincount(b, y - p, n), np.bincount(b, p * (1 - p), n))
            model.tables[k] += step
            z += step[b]
    model.pair_edges = [_quantiles(c, PAIR_BINS) for c in x.T]
    coarse = [np.searchsorted(e, c, side="right") for e, c in zip(model.pair_edges, x.T, strict=True)]
    size = [len(e) + 1 for e in model.pair_edges]

    def cells(i: int, j: int, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        flat = coarse[i] * size[j] + coarse[j]
        return tuple(np.bincount(flat, v, size[i] * size[j]).reshape(size[i], size[j]) for v in (y - p, p * (1 - p)))

    p = 1 / (1 + np.exp(-z))
    ranked = sorted(combinations(range(x.shape[1]), 2), key=lambda ij: -_corner(*cells(*ij, p))[0])
    model.pairs = ranked[:PAIRS]
    model.pair_tables = [np.zeros((size[i], size[j])) for i, j in model.pairs]
    for _ in range(PAIR_ROUNDS):
        for (i, j), table in zip(model.pairs, model.pair_tables, strict=True):
            p = 1 / (1 + np.exp(-z))
            step = RATE * _corner(*cells(i, j, p))[1]
            table += step
            z += step[coarse[i], coarse[j]]
    return model


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _scorer(model: Model, names: list[str]):
    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.column_stack([batch.column(n).to_numpy(zero_copy_only=False) for n in names]) if len(batch) else np.zeros((0, len(names)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(model.score(x), pa.float64())], names=["doc_id", "held_out", "score"])

    return score


def score(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted of every row of docs."""
    named = features()
    measured = quality_rules.measure(docs.select(F.col("doc_id").cast("long"), "text")).select("doc_id", held_out().alias("held_out"), *[c.alias(n) for n, c in named.items()])
    stored = scratch.written(measured, "quality-features")
    known = labels.where(F.col("quality").isin(0, 1)).select("doc_id", "quality")
    labelled = stored.where(~F.col("held_out")).join(known, "doc_id").groupBy("doc_id", "quality").agg(F.min(F.struct(*named)).alias("f"))
    labelled = scratch.written(labelled.select("doc_id", "quality", "f.*"), "quality-labelled")
    rows = sampling.least_hashed(labelled, F.col("doc_id"), max_rows).select("quality", *named).collect()  # at most max_rows
    data = np.array(sorted(map(tuple, rows)), dtype=float).reshape(-1, 1 + len(named))
    model = train(data[:, 1:], data[:, 0])
    scored = stored.mapInArrow(_scorer(model, list(named)), "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= PREDICT_FROM).cast("int"))


def op8_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(scratch.table(spark, sf_dir, "documents"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


QUERIES = {"op8_quality_model": op8_quality_model}
ORACLE_SQL: dict[str, str] = {}
