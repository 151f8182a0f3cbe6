"""The methods themselves: brute-force dynamic programming, held-out accuracy, recall, base patterns, filters that err."""

import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from segdedup.llm import embedding_dedup, near_copies, packing, pii, quality_model, quality_rules, sampling, simhash, url_filter


def test_cuts_are_the_cheapest():
    """choose() against all sequences of cuts."""
    draw = random.Random(2)
    for _ in range(60):
        capacity = draw.randrange(4, 12)
        at, here = [], 0
        for _ in range(draw.randrange(1, 14)):
            here += draw.randrange(1, capacity + 1)
            at.append(here)
        penalty = [draw.choice([0.0, 1.0, 4.0]) for _ in at]
        best = {0: 0.0}
        for j, t in enumerate(at):
            best[t] = min(best[s] + capacity - (t - s) + penalty[j] for s in best if t - s <= capacity)
        got = packing.choose(at, penalty, capacity)
        cost = dict(zip(at, penalty, strict=True))
        assert got[-1] == at[-1]
        assert abs(sum(capacity - (b - a) + cost[b] for a, b in zip([0, *got[:-1]], got, strict=True)) - best[at[-1]]) < 1e-9


def test_padding_is_small(spark):
    import public_tokenizers

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").repartition(4)
    used = packing.pack(docs, public_tokenizers.path(packing.VOCABULARY)).groupBy("sequence_id").agg(F.sum("length").alias("n")).agg(F.sum("n"), F.count(F.lit(1))).first()
    assert used[0] / (1024 * used[1]) > 0.97


def test_held_out_accuracy(spark):
    """Trained without the held-out fold, the scores rank it."""
    d = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{d}/documents.parquet").repartition(8)
    labels = spark.read.parquet(f"{d}/labels.parquet")
    scored = quality_model.score(docs, labels).where("held_out").join(labels, "doc_id").select("score", "quality").collect()
    y, s = np.array([r.quality for r in scored]), np.array([r.score for r in scored])
    good, bad = s[y == 1], s[y == 0]
    auc = ((good[:, None] > bad[None, :]).mean() + 0.5 * (good[:, None] == bad[None, :]).mean()) if len(good) and len(bad) else 0
    assert len(good) > 50 and len(bad) > 50 and auc > 0.9, auc


def test_labels_of_the_held_out_fold_are_not_used(spark):
    docs = spark.createDataFrame([(i, ("good words here and there. " if i % 2 else "BUY !!! # $ ") * (10 + i % 5)) for i in range(80)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(80)], "doc_id long, quality int")
    held = labels.withColumn("held", F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2)
    turned = held.withColumn("quality", F.when(F.col("held"), 1 - F.col("quality")).otherwise(F.col("quality"))).drop("held")
    one, two = (sorted(map(tuple, quality_model.score(docs, x).collect())) for x in (labels, turned))
    assert one == two and any(r[1] for r in one)


def test_bounded_sample(spark):
    rows = spark.range(20_000).withColumn("id", F.when(F.col("id") < 3000, 7).otherwise(F.col("id")))
    for bound in (0, 1, 500, 5000, 19_999, 30_000):
        got = sampling.least_hashed(rows, F.col("id"), bound).collect()
        assert len(got) <= bound and (bound < 3500 or len(got) >= min(20_000, bound) - 3001)
        assert sum(r.id == 7 for r in got) in (0, 3001 - 1)


def test_planted_vectors_are_recalled(spark):
    """60,000 vectors, 6000 planted pairs of cosine 0.95 to 0.96, more than a hundred lists."""
    rng = np.random.default_rng(4)
    n, planted, dims = 60_000, 6_000, 64
    x = rng.normal(size=(n, dims))
    x /= np.linalg.norm(x, axis=1)[:, None]
    side = rng.normal(size=(planted, dims))
    side -= (side * x[:planted]).sum(1)[:, None] * x[:planted]
    side /= np.linalg.norm(side, axis=1)[:, None]
    cosine = rng.uniform(0.9505, 0.96, planted)[:, None]
    x[n - planted :] = cosine * x[:planted] + np.sqrt(1 - cosine**2) * side
    import pandas as pd

    vectors = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(n), "embedding": x.tolist()}), "vec_id long, embedding array<double>").repartition(8)
    got = {r.vec_id: r for r in embedding_dedup.deduplicate(vectors).where("n_links > 0").collect()}
    true = {}
    for at in range(0, n, 4000):  # brute force
        i, j = np.nonzero(x[at : at + 4000] @ x.T >= 0.95)
        for a, b in zip((i + at).tolist(), j.tolist(), strict=True):
            if a != b:
                true.setdefault(a, set()).add(b)
    links, found = sum(map(len, true.values())), sum(r.n_links for r in got.values())
    assert links >= 2 * planted and all(r.n_links <= len(true[i]) for i, r in got.items())
    assert found >= 0.99 * links, found / links
    assert all(r.component_id == min(i, *true[i]) for i, r in got.items() if len(true[i]) == 1)


def _matches(text: str) -> list[tuple[int, int, int]]:
    """The base patterns as they are worded."""
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        digits = [int(c) for c in m[0] if c.isdigit()]
        if 14 <= len(digits) <= 19 and sum(d if k % 2 == 0 else 2 * d - 9 * (d > 4) for k, d in enumerate(reversed(digits))) % 10 == 0:
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 10 <= sum(c.isdigit() for c in m[0]) <= 15]
    return sorted(out)


def test_base_spans(spark):
    draw = random.Random(6)
    bits = ["a.b@c.de", "x@y", "1.2.3.4", "256.1.1.1", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (555) 555-0100", "+12", "99", ".", "@", " ", "word", "é中", "-", "5500000000000004", "+49 30 1234567.", "1.2.3.4.5.6.7.8"]
    texts = [None, ""] + ["".join(draw.choice(bits) + draw.choice(["", " ", "\n"]) for _ in range(draw.randrange(1, 30))) for _ in range(300)]
    texts += [r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text").collect()]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in pii.detect(docs).collect()}
    for i, t in enumerate(texts):
        want = _matches(t or "")
        line = ",".join(f"{pii.KINDS[k]}:{a}:{b}" for a, k, b in want)
        assert got[i].base_sha256 == hashlib.sha256(line.encode()).hexdigest(), (t, line)
        assert [got[i][f"n_{k}"] for k in pii.KINDS] == [sum(w[1] == k for w in want) for k in range(4)]
        assert set(line.split(",")) - {""} <= set(got[i].spans.split(","))


def test_redaction_covers_overlaps(spark):
    docs = spark.createDataFrame([(1, "call +1 555 010 0199.bob@corp.com now"), (2, None), (3, "plain")], "doc_id long, text string")
    got = {r.doc_id: r.text for r in pii.redact(docs).collect()}
    assert "corp" not in got[1] and "010" not in got[1] and got[1].startswith("call <") and got[1].endswith("> now")
    assert got[2] is None and got[3] == "plain"


def test_measures(spark):
    """word_chars, n_symbols and n_dup_lines as they are worded."""
    draw = random.Random(9)
    lines = ["", " ", "a b", "a b ", "# $ x|y<z>", "é中 word", "\t", "a\x0bb", "x\r"]
    texts = [None, ""] + ["\n".join(draw.choice(lines) for _ in range(draw.randrange(12))) for _ in range(80)]
    got = {r.doc_id: r for r in quality_rules.judge(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        seen, again = set(), 0
        for line in t.split("\n"):
            if re.search(r"[^\x20\x09-\x0D]", line):
                again += line in seen
                seen.add(line)
        assert (got[i].n_words, got[i].word_chars, got[i].n_symbols, got[i].n_dup_lines) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), again)


def test_bloom_errs_and_the_join_mends_it(spark):
    """A filter of one block is full, so every candidate passes it; verdicts stay exact."""
    draw = random.Random(3)
    hosts = [f"h{i}.org" for i in range(900)]
    rules = [(h, "/a/" if i % 2 else "/", "block") for i, h in enumerate(hosts[:600])]
    urls = [f"http://{draw.choice(['', 'www.'])}{draw.choice(hosts)}/{draw.choice(['a/x', 'b', ''])}" for _ in range(400)]
    listed = spark.createDataFrame([(h + p,) for h, p, _ in rules], "key string")
    bloom = url_filter.build_bloom(listed, max_words=url_filter.BLOCK)
    missed = spark.createDataFrame([(h + "/",) for h in hosts[600:]], "key string")
    assert len(bloom) == url_filter.BLOCK and missed.where(url_filter.maybe_listed(F.col("key"), bloom)).count() > 250
    assert listed.where(~url_filter.maybe_listed(F.col("key"), bloom)).count() == 0
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    given = spark.createDataFrame(rules, "host string, path string, verdict string")
    for words in (url_filter.BLOCK, url_filter.MAX_WORDS):
        for r in url_filter.judge(pages, given, max_words=words).collect():
            fits = [h + p for h, p, _ in rules if (r.host == h or r.host.endswith("." + h)) and r.path.startswith(p)]
            assert r.rule == (fits[0] if fits else None) and r.verdict == ("block" if fits else "allow")


@pytest.mark.parametrize("split", [4, 4096])
def test_long_postings(spark, monkeypatch, split):
    """Fingerprints that crowd under one key, split by further bytes or not."""
    monkeypatch.setattr(simhash, "SPLIT", split)
    monkeypatch.setattr(simhash, "TALLY", 8 if split == 4 else 512)
    draw = random.Random(1)
    base = draw.getrandbits(64)
    marks = {base ^ (1 << draw.randrange(24)) ^ (1 << draw.randrange(64)) ^ (draw.getrandbits(24) if k % 3 else 0) for k in range(150)}
    marks = [m - (1 << 64) if m >> 63 else m for m in sorted(marks)]
    got = simhash.links(spark.createDataFrame([(m,) for m in marks], "mark long")).collect()

    def components(links):
        up = {m: m for m in marks}
        for a, b in links:
            x, y = up[a], up[b]
            if x != y:
                up = {m: min(x, y) if r in (x, y) else r for m, r in up.items()}
        return up

    pairs = [(a, b) for a in marks for b in marks if a < b and ((a ^ b) & (2**64 - 1)).bit_count() <= 2]
    assert components(pairs) == components([(r.u, r.v) for r in got]) and len(pairs) > 50


def test_sketch_never_rules_out_a_link():
    rng = np.random.default_rng(3)
    for n in (5, 40, 300, 3000):
        for _ in range(20):
            pool = rng.integers(0, 2**63, 2 * n, dtype=np.uint64)
            a, b = np.sort(pool[:n]), np.sort(pool[n // 10 : n + n // 10])
            far = np.bitwise_count(np.frombuffer(near_copies.sketch(a), dtype="<u8") ^ np.frombuffer(near_copies.sketch(b), dtype="<u8")).sum()
            assert far <= 2 * (n // 10)


@pytest.mark.parametrize("block", [3, 2048])
def test_blocks_of_a_posting_meet(spark, monkeypatch, block):
    monkeypatch.setattr(near_copies, "BLOCK", block)
    rng = np.random.default_rng(5)
    sets = [np.sort(rng.integers(0, 2**63, 50, dtype=np.uint64)) for _ in range(10)]
    sets += [np.sort(np.append(s[1:], np.uint64(9))) for s in sets[:6]]
    rows = [(i, len(s), bytearray(near_copies.sketch(s))) for i, s in enumerate(sets)]
    stored = spark.createDataFrame(rows, "node long, n long, sketch binary")
    open_ = spark.createDataFrame([(0, i, i) for i in range(16)] + [(1, 0, 5), (1, 10, 5)], "gid long, node long, label long")
    assert sorted(map(tuple, near_copies._across(open_, stored).collect())) == [(i, 10 + i) for i in range(6)]
