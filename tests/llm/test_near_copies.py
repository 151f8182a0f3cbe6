"""The pipeline's near-duplicate stage against brute-force Jaccard, and rows without an id of their own."""

import random
from itertools import combinations

import numpy as np
import pytest

import corpus_pipeline
from segdedup import keys
from segdedup.config import DedupConfig
from segdedup.llm import near_copies, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def _texts(seed: int) -> list[str]:
    """Texts of many lengths with copies edited more and less, chains of edits and a shared passage."""
    draw = random.Random(seed)
    passage = [f"common{i}" for i in range(40)]
    out = []
    for _ in range(40):
        words = [f"w{draw.randrange(500)}" for _ in range(draw.randrange(1, 300))]
        out.append(" ".join(words))
        for _ in range(draw.randrange(5)):
            words = list(words)
            for _ in range(draw.randrange(1, 2 + len(words) // 40)):
                words[draw.randrange(len(words))] = f"new{draw.randrange(10**6)}"
            out.append(" ".join(words))
        out.append(" ".join([*passage, *(f"x{draw.randrange(10**6)}" for _ in range(draw.randrange(5, 40)))]))
    return out


def _same(x: str, y: str, rule=DedupConfig()) -> bool:
    a, b = (keys.shingle_set(t, rule) for t in (x, y))
    near = (simhash.fingerprint(x) ^ simhash.fingerprint(y)) & (2**64 - 1)
    return near.bit_count() <= 2 or (bool(a | b) and 5 * len(a & b) >= 4 * len(a | b))


@pytest.mark.parametrize("seed", [1, 2])
def test_all_pairs_are_found(spark, seed):
    texts = _texts(seed)
    least = list(range(len(texts)))
    far = 0
    for i, j in combinations(range(len(texts)), 2):
        if _same(texts[i], texts[j]):
            far += ((simhash.fingerprint(texts[i]) ^ simhash.fingerprint(texts[j])) & (2**64 - 1)).bit_count() > 2
            a, b = sorted((least[i], least[j]))
            least = [a if x == b else x for x in least]
    assert far > 20
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], SCHEMA)
    assert sorted(r.doc_id for r in corpus_pipeline.one_of_each(spark, docs, "").collect()) == sorted(set(least))


def test_near_sets_share_a_posting():
    draw = np.random.default_rng(5)
    for n in [*range(1, 120), 400, 2000]:
        for gone in range(n // 5 + 1):
            new = max(0, (5 * (n - gone) - 4 * n) // 4)  # as many as 0.8 allows
            pool = draw.integers(0, 2**63, n + new, dtype=np.uint64)
            x, y = np.sort(pool[:n]), np.sort(pool[gone:])
            assert 5 * (n - gone) >= 4 * (n + new)
            assert np.intersect1d(near_copies.postings(x), near_copies.postings(y)).size


def test_wide_sketches_never_overstate_a_difference():
    draw = np.random.default_rng(6)
    for n in (1, 2, 1023, 1024, 1025, 3000, 9000):
        for gone in sorted({0, 1, n // 10, n // 2, n}):
            pool = draw.integers(0, 2**63, 2 * n + 5, dtype=np.uint64)
            x, y = pool[:n], pool[gone : gone + n + 5]
            far = near_copies.least_difference(near_copies.wide_sketch(x), near_copies.wide_sketch(y))
            assert far <= len(np.setxor1d(x, y))
    x, y = (draw.integers(0, 2**63, 9000, dtype=np.uint64) for _ in "xy")
    assert 9 * near_copies.least_difference(near_copies.wide_sketch(x), near_copies.wide_sketch(y)) > 18000  # ruled out
    empty = near_copies.wide_sketch(x[:0])
    assert near_copies.least_difference(empty, near_copies.wide_sketch(x[:1])) == 1


def test_rows_without_own_id_stay(spark):
    draw = random.Random(4)
    a, b, c, d = (" ".join(f"w{draw.randrange(900)}" for _ in range(80)) for _ in range(4))
    rows = [(None, a), (None, b), (None, b), (7, c), (7, d), (7, d), (None, c + " x"), (9, a + " y"), (3, None), (None, None)]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], SCHEMA)
    got = corpus_pipeline.one_of_each(spark, docs, "").select("doc_id", "text").collect()
    assert sorted(map(tuple, got), key=str) == sorted([(9, a + " y"), (None, b), (7, c), (7, d), (3, None)], key=str)
