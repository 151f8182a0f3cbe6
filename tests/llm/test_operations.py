"""Each operation against a brute-force version on small rows with nulls, empties, ties and repeats."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from segdedup.llm import embedding_dedup, mixing, packing, pii, quality_model, quality_rules, simhash, suffix_dedup, token_files, tokens, url_filter

VOCAB = public_tokenizers.path("byte_bpe_50k.json")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, runs string, mark int"


@pytest.fixture(scope="module")
def rows():
    rnd = random.Random(5)
    phrases = ["".join(rnd.choice("abc d.\n") for _ in range(rnd.randint(20, 260))) for _ in range(9)] + ["x" * 230, "ab" * 120]
    texts = [None, "", " ", "word", "Ünï ½ 中文 <|endoftext|>\t x", "+1 (555) 555-0100 a@b.co 1.2.3.4 x 4111111111111111"] + ["".join(rnd.choice(phrases) for _ in range(rnd.randint(0, 6))) for _ in range(60)] + ["long " * 30000]
    return [(i, t, "en", f"s{i % 3}" if i % 7 else None, len(t or ""), "clash", i) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_suffix_dedup(docs, rows, empty):
    seen, want = set(), {}
    for i, text, *_ in rows:
        data = (text or "").encode()
        mask = bytearray(len(data))
        for s in range(len(data) - 99):
            w = data[s : s + 100]
            if w in seen:
                mask[s : s + 100] = b"\x01" * 100
            seen.add(w)
        kept = bytes(c for c, m in zip(data, mask) if not m)
        spans = sum(1 for k in range(len(mask)) if mask[k] and not (k and mask[k - 1]))
        want[i] = (len(data), sum(mask), spans, hashlib.sha256(kept).hexdigest())
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix_dedup.removals(docs).collect()}
    assert got == want
    assert suffix_dedup.removals(empty).count() == 0


def test_mixing(docs, rows, empty):
    got = {r.doc_id: r for r in mixing.mix(docs, [3, 1, 2], 1.5).collect()}
    assert len(got) == len(rows)
    for source in {r[3] for r in rows}:
        own = [got[r[0]] for r in rows if r[3] == source]
        assert all(r.source_size == sum(x.size for x in own) for r in own)
        assert abs(sum(r.taken for r in own) - own[0].target) <= max(r.size for r in own)
        assert all(r.taken <= 2 * r.size for r in own)
    assert mixing.mix(empty, [1], 1.5).count() == 0


def test_tokens_round_trip(docs, rows, empty, spark, tmp_path):
    tokenizer = Tokenizer.from_file(VOCAB)
    ids = {r[0]: tokenizer.encode(r[1] or "", add_special_tokens=False).ids for r in rows}
    assert all(list(g) == ids[r[0]] for g, r in zip(tokens.batches(tokens.Encoder(VOCAB), [r[1] for r in rows]), rows))
    token_files.write(docs, str(tmp_path / "t"), VOCAB)
    start = 0
    for r in token_files.read(spark, str(tmp_path / "t")).orderBy("doc_id").collect():
        own = np.array([*ids[r.doc_id], 2], dtype="<u4")
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(own), zlib.crc32(own.tobytes()))
        start += len(own)
    token_files.write(empty, str(tmp_path / "e"), VOCAB)
    assert token_files.read(spark, str(tmp_path / "e")).count() == 0
    a = np.random.default_rng(0).integers(0, 50257, 70_001)
    for bits in (False, True):
        width, sizes, payload = token_files.encode_chunk(a, bits)
        assert (token_files.decode_chunk(payload, len(a), width, sizes, bits) == a).all()


def test_packing(docs, rows, empty):
    got = packing.pack(docs, VOCAB).collect()
    by_doc, by_sequence = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_sequence.setdefault(r.sequence_id, []).append(r)
    assert set(by_doc) == {r[0] for r in rows}
    for pieces in by_doc.values():
        at = 0
        for p in sorted(pieces, key=lambda p: p.start):
            assert p.start == at
            at += p.length
        assert at == pieces[0].doc_tokens
    for pieces in by_sequence.values():
        at = 0
        for p in sorted(pieces, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 1024
    assert packing.pack(empty, VOCAB).count() == 0


def test_url_filter(spark):
    rules = spark.createDataFrame(url_filter.RULES, "host string, path string, verdict string")
    urls = [None, "", "no scheme", "http://WWW.Example.COM/en/x?y", "https://a.example.com/en/#z", "ftp://x.net/es/1", "http://x.net/de/", "http://com", "http://notexample.com/en/"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls + urls[3:5])], "page_id long, url string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge(pages, rules).collect()}
    assert got[3] == got[9] == ("www.example.com", "/en/x", "www.example.com/en/", "allow")
    assert got[4] == ("a.example.com", "/en/", "example.com/en/", "block") and got[5] == ("x.net", "/es/1", "net/es/", "block")
    assert got[0] == got[1] == got[2] == ("", "", None, "allow") and got[6][2] is None and got[7] == ("com", "", None, "allow")
    assert got[8] == ("notexample.com", "/en/", "com/", "allow") and url_filter.judge(pages.limit(0), rules).count() == 0


def test_quality(docs, rows, empty, spark):
    got = {r.doc_id: r for r in quality_rules.judge(docs).collect()}
    for i, text, *_ in rows:
        words = (text or "").encode().split()
        windows = list(zip(words, words[1:], words[2:]))
        counts = {}
        for w in windows:
            counts[w] = counts.get(w, 0) + 1
        covered = {k + d for k, w in enumerate(windows) if counts[w] > 1 for d in range(3)}
        assert (got[i].n_words, got[i].n_repeat_words) == (len(words), len(covered))
        assert got[i].base_failed == (len(words) < 50 or 100 * len(covered) > 50 * len(words))
    assert quality_rules.judge(empty).count() == 0
    labels = spark.createDataFrame([(i, int(i % 2)) for i in range(40)], "doc_id long, quality int")
    scored = quality_model.score(docs, labels).collect()
    assert len(scored) == len(rows) and all(0 <= r.score <= 1 for r in scored)
    assert quality_model.score(empty, labels).count() == 0


def test_pii(docs, empty):
    assert pii.joined(pii.spans("+1 (555) 555-0100 a@b.co 1.2.3.4 x 4111111111111111")) == "phone:0:17,email:18:24,ip:25:32,card:35:51"
    got = {r.doc_id: r for r in pii.detect(docs).collect()}
    assert got[5].n_email == got[5].n_ip == got[5].n_card == got[5].n_phone == 1 and got[0].spans == ""
    assert {r.doc_id: r.text for r in pii.redact(docs).collect()}[5] == "<PHONE> <EMAIL> <IP> x <CARD>"
    assert pii.detect(empty).count() == 0


def test_simhash(docs, rows, empty):
    got = {r.doc_id: r for r in simhash.near_duplicates(docs).collect()}
    marks = {i: simhash.fingerprint(t) for i, t, *_ in rows}
    assert all(got[i].mark == m for i, m in marks.items())
    up = {i: i for i in marks}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in marks:
        for j in marks:
            if i < j and ((marks[i] ^ marks[j]) & (2**64 - 1)).bit_count() <= 2:
                a, b = sorted((root(i), root(j)))
                up[b] = a
    assert all(got[i].component_id == root(i) for i in marks)
    assert simhash.near_duplicates(empty).count() == 0


def test_embeddings(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(12, 16))
    x = [(base[i % 12] + 0.05 * rng.normal(size=16)).astype("float32").tolist() for i in range(120)]
    rows = [(i, v) for i, v in enumerate(x + x[:3])] + [(200, None), (201, [0.0] * 16), (202, [float("nan")] * 16), (203, [1.0])]
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {r.vec_id: r for r in embedding_dedup.deduplicate(vectors).collect()}
    m = np.array([v for _, v in rows[:123]])
    m /= np.linalg.norm(m, axis=1)[:, None]
    links = ((m @ m.T) >= 0.95).sum(1) - 1
    assert sum(got[i].n_links for i in range(123)) >= 0.9 * links.sum() and all(got[i].n_links <= links[i] for i in range(123))
    assert all(got[i].n_links == 0 and got[i].kept for i in range(200, 204))
    assert embedding_dedup.deduplicate(vectors.limit(0)).count() == 0
