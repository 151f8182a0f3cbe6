"""Pairs above a Jaccard threshold and the served baseline, against brute force."""

import random
from itertools import combinations

import pytest

from segdedup import baselines, keys, similarity
from segdedup.config import DedupConfig

SMALL = DedupConfig(p=32, bands=8, family="portable31")


@pytest.fixture(scope="module")
def texts():
    """Copies, near copies, a passage that half the texts share, null, empty, short and long texts."""
    draw = random.Random(3)
    passage = " ".join(f"common{i}" for i in range(12))
    out = [None, "", "  \t", "one", "one", "a b c", "One", " ".join(["same"] * 40), " ".join(["same"] * 9), " ".join(f"w{i}" for i in range(6000))]
    for i in range(30):
        own = [f"w{draw.randrange(60)}" for _ in range(draw.randrange(4, 40))]
        out.append(" ".join(own) + (" " + passage if i % 2 else ""))
        near = list(own)
        near[draw.randrange(len(near))] = "changed"
        out += [" ".join(own), " ".join(near), " ".join(near)]
    return list(enumerate(out))


def _brute(texts):
    sets = {i: keys.shingle_set(t, SMALL) for i, t in texts}
    sets = {i: s for i, s in sets.items() if s}
    rep = {i: min(j for j, r in sets.items() if r == s) for i, s in sets.items()}
    return sets, rep


@pytest.mark.parametrize(("num", "den"), [(1, 10), (1, 2), (4, 5)])
def test_pairs_above(spark, texts, num, den):
    sets, rep = _brute(texts)
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = similarity.shingle_sets(docs, SMALL.k)
    found = similarity.classes(got, "ids")
    assert {r.doc_id: r.rep for r in found.collect()} == rep
    pairs = similarity.pairs_above(similarity.representatives(got, found), num, den)
    want = set()
    for a, b in combinations(sorted(set(rep.values())), 2):
        inter, uni = len(sets[a] & sets[b]), len(sets[a] | sets[b])
        if inter * den >= uni * num:
            want.add((a, b, inter, uni))
    assert want and {tuple(r) for r in pairs.select("a", "b", "inter", "uni").collect()} == want


def test_empty(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    got = similarity.shingle_sets(docs, SMALL.k)
    assert similarity.pairs_above(similarity.representatives(got, similarity.classes(got, "ids")), 1, 2).count() == 0


@pytest.mark.parametrize("top_k", [1, 3])
def test_served(spark, texts, top_k):
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    signer = keys.Signer(SMALL)
    signed = {i: s for i, t in texts if (s := signer.signature(t)) is not None}
    own = {i: set(enumerate(signer.keys(s))) for i, s in signed.items()}
    want = set()
    for i in signed:
        near = [(-round(float((signed[i] == signed[j]).mean()), 6), j) for j in signed if j < i and own[i] & own[j]]
        want |= {(i, j, -e) for e, j in sorted(n for n in near if -n[0] >= 0.5)[:top_k]}
    assert {tuple(r) for r in baselines.served_topk(docs, SMALL, top_k).select("doc_id", "match_id", "est").collect()} == want
