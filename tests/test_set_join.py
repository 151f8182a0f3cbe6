"""The ML baseline's own candidates against the library's join and against brute force."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from segdedup import baselines, scratch, set_join


def _texts():
    """One language: all share common words; some are near copies, some long, some of other cases."""
    draw = random.Random(11)
    common = [f"c{i}" for i in range(40)]
    out = [None, "", "one", "One", "a b", "a,b", "a b,", "B A"]
    for i in range(60):
        own = draw.sample(common, 25) + [f"w{draw.randrange(4000)}" for _ in range(draw.choice([3, 40, 700]))]
        out.append(" ".join(own))
        for share in (0.05, 0.16, 0.3):
            near = [w if draw.random() > share else f"x{draw.randrange(4000)}" for w in own]
            out.append(" ".join(near))
    return list(enumerate(out))


def test_rows_of_the_library(spark, monkeypatch):
    from pyspark.ml.feature import HashingTF, MinHashLSH, MinHashLSHModel

    docs = spark.createDataFrame(_texts(), "doc_id long, text string")
    sets = {}
    for i, t in _texts():
        if (t or "").split():
            sets.setdefault(frozenset(t.lower().split()), []).append(i)
    want = {(own[0], other, 0.0) for own in sets.values() for other in own[1:]}
    words = spark.createDataFrame([(own[0], sorted(s)) for s, own in sets.items()], "doc_id long, w array<string>")
    vectors = HashingTF(inputCol="w", outputCol="v", numFeatures=1 << 18, binary=True).transform(words)
    joined = MinHashLSH(inputCol="v", outputCol="h", numHashTables=8, seed=7).fit(vectors).approxSimilarityJoin(vectors, vectors, 0.3, "d")
    rows = joined.where("datasetA.doc_id < datasetB.doc_id").select("datasetA.doc_id", "datasetB.doc_id", F.round("d", 6)).collect()
    want |= {tuple(r) for r in rows}

    def pairs_of_a_language(*_, **__):
        raise AssertionError("makes most pairs of one language")

    monkeypatch.setattr(MinHashLSHModel, "approxSimilarityJoin", pairs_of_a_language)
    got = [tuple(r) for r in baselines.ml_minhash(docs).collect()]
    assert len(rows) > 60 and len(got) == len(set(got)) and set(got) == want


def test_words_with_commas_stay_apart(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, "a,b")], "doc_id long, text string")
    assert baselines.ml_minhash(docs).count() == 0


def test_doc_ids_that_repeat(spark):
    base = [f"w{i}" for i in range(20)]
    rows = [(1, base), (2, base[:19]), (2, base[:16] + ["x"]), (2, base[:10]), (None, base[1:])]
    docs = spark.createDataFrame([(i, " ".join(w)) for i, w in rows], "doc_id long, text string")
    assert sorted(tuple(r) for r in baselines.ml_minhash(docs).collect()) == [(1, 2, 0.05), (1, 2, 0.238095)]


@pytest.mark.parametrize("least", [0.3, 0.5, 0.7, 0.95])
def test_no_pair_is_left_out(spark, least):
    draw = random.Random(5)
    sets = []
    for _ in range(120):
        own = {min(draw.randrange(900), draw.randrange(900)) for _ in range(draw.choice([1, 2, 9, 60, 400]))}
        sets += [own, own ^ {draw.randrange(900)} or {1}, {x for x in own if draw.random() < 0.75} or {2}]
    table = spark.createDataFrame([(i, sorted(s)) for i, s in enumerate(sets)], "doc_id long, ids array<int>")
    got = [tuple(r) for r in set_join.candidates(scratch.written(table, "sets"), least).collect()]
    want = {(a, b) for a, b in combinations(range(len(sets)), 2) if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b])}
    assert want and len(got) == len(set(got)) and want <= set(got)


def test_no_sets(spark):
    table = spark.createDataFrame([], "doc_id long, ids array<int>")
    assert set_join.candidates(scratch.written(table, "sets"), 0.7).count() == 0
    assert baselines.ml_minhash(spark.createDataFrame([], "doc_id long, text string")).count() == 0
