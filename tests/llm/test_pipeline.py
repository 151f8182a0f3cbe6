"""Each stage of the pipeline against a brute-force version on its own input."""

import hashlib
import random
import zlib
from collections import Counter

import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from segdedup import keys
from segdedup.config import DedupConfig
from segdedup.llm import pii, quality_rules, simhash

VOCAB = public_tokenizers.path("byte_bpe_50k.json")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = "the river of stone and a green house that we saw in winter was old but its garden had many trees with birds to watch for hours".split()


def _texts() -> list[str | None]:
    rnd = random.Random(11)
    fresh = [" ".join(f"{rnd.choice(WORDS)}{rnd.choice(['', '', '.', f' {rnd.randint(0, 999)}'])}" for _ in range(rnd.randint(60, 400))) for _ in range(40)]
    private = [f"{t} write to ann.lee@mail.example.org or +1 (555) 555-0100 from 10.1.2.3" for t in fresh[:5]]
    near = [fresh[6] + " x", fresh[7].upper(), fresh[8] + "\n"]
    junk = [None, "", " ", "short text", "buy now " * 80, "# $ % & | < > * " * 30, "A" * 5000]
    return fresh + private + near + fresh[10:14] + [fresh[20]] * 6 + junk + [" ".join(fresh) + " end"]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rows = [(3 * i + 1, t, "en", [None, "hot", "b", "c"][0 if i % 9 == 0 else 1 + (i % 5 > 2) + (i % 5 > 3)], len(t or "")) for i, t in enumerate(_texts())]
    found = str(tmp_path_factory.mktemp("pipeline"))
    spark.createDataFrame([*rows, rows[1]], SCHEMA).repartition(3).write.parquet(f"{found}/documents.parquet")
    return found


@pytest.fixture(scope="module")
def steps(spark, folder, tmp_path_factory):
    """The input of each stage and what it gave, each written and read again."""
    made = [spark.read.parquet(f"{folder}/documents.parquet")]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        path = str(tmp_path_factory.mktemp("stage") / str(k))
        stage(spark, made[-1], folder).write.parquet(path)
        made.append(spark.read.parquet(path))
    assert all(df.columns == made[0].columns for df in made[:-1])
    return made


def _rows(df) -> Counter:
    return Counter(map(tuple, df.collect()))


def test_quality_rules_reject(steps):
    names = [f"v_{r}" for r in quality_rules.RULES]
    judged = quality_rules.votes(quality_rules.measure(steps[0])).collect()

    def passes(text: str | None) -> bool:
        words = (text or "").encode().split()
        windows = list(zip(words, words[1:], words[2:]))
        counts = Counter(windows)
        covered = {k + d for k, w in enumerate(windows) if counts[w] > 1 for d in range(3)}
        return len(words) >= 50 and 100 * len(covered) <= 50 * len(words)

    sound = [r for r in judged if passes(r.text)]
    counts = Counter(tuple(int(r[n]) for n in names) for r in sound)
    model = quality_rules.fit(sorted(counts.items()))
    want = Counter((r.doc_id, r.text, r.lang, r.source, r.n_chars) for r in sound if quality_rules.log_odds(tuple(int(r[n]) for n in names), model["rates"], model["prior"]) >= 0)
    assert _rows(steps[1]) == want and 40 < sum(want.values()) < len(judged)


def test_one_of_each_group_stays(steps):
    """The stage's rule: 5-word Jaccard of 0.8 or more, or op9's two bits."""
    texts = {r.doc_id: r.text for r in steps[1].collect()}
    marks = {i: simhash.fingerprint(t) & (2**64 - 1) for i, t in texts.items()}
    sets = {i: keys.shingle_set(t, DedupConfig()) for i, t in texts.items()}

    def linked(i: int, j: int) -> bool:
        near = 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])
        return near or (marks[i] ^ marks[j]).bit_count() <= 2

    groups = []
    for i in sorted(marks):
        near = [g for g in groups if any(linked(i, j) for j in g)]
        groups = [g for g in groups if g not in near] + [[i, *(j for g in near for j in g)]]
    kept = {min(g) for g in groups}
    assert _rows(steps[2]) == Counter({r: 1 for r in _rows(steps[1]) if r[0] in kept})
    assert len(kept) < len(texts)


def test_personal_data_goes(steps):
    found = {r.doc_id: pii.spans(r.text or "") for r in steps[2].collect()}
    accepted = pii.fit(dict(sorted(Counter(s[4] for spans in found.values() for s in spans).items())))
    want = Counter()
    for r in steps[2].collect():
        out, last = "", 0
        for start, kind, end, base, votes in found[r.doc_id]:
            if not (base or votes in accepted):
                continue
            if start >= last:
                out += r.text[last:start] + f"<{pii.KINDS[kind].upper()}>"
            last = max(last, end)  # what sticks out of an earlier span goes with it
        out += r.text[last:]
        want[r.doc_id, out, r.lang, r.source, len(out)] += 1
    assert _rows(steps[3]) == want
    after = " ".join(r.text for r in steps[3].collect())
    assert "ann.lee@mail.example.org" not in after and "555-0100" not in after and "10.1.2.3" not in after


def test_mix_meets_targets(steps):
    rows = steps[3].collect()
    size = {r.doc_id: len(r.text.encode().split()) for r in rows}
    order = sorted({r.source for r in rows}, key=lambda s: (s is None, s or ""))
    own = {s: sum(size[r.doc_id] for r in rows if r.source == s) for s in order}
    weight = {s: corpus_pipeline.WEIGHTS[k % len(corpus_pipeline.WEIGHTS)] for k, s in enumerate(order)}
    target, budget, free = {}, corpus_pipeline.SHARE * sum(own.values()), list(order)
    while free:
        share = {s: budget * weight[s] / sum(weight[x] for x in free) for s in free}
        full = [s for s in free if share[s] >= 2 * own[s]]
        for s in full or free:
            target[s] = 2 * own[s] if full else share[s]
            budget -= target[s] if full else 0
        free = [s for s in free if full and s not in full]
    want = Counter()
    for s in order:
        base, held = int(target[s] // own[s]), 0.0
        for r in sorted((r for r in rows if r.source == s), key=lambda r: hashlib.md5(str(r.doc_id).encode()).hexdigest()[:15]):
            held += size[r.doc_id]
            copies = base + (base < 2 and held <= target[s] - base * own[s])
            if copies:
                want[tuple(r)] = copies
    assert _rows(steps[4]) == want


def test_packing_keeps_every_id(steps):
    tokenizer = Tokenizer.from_file(VOCAB)
    copies = Counter(r.doc_id for r in steps[4].collect())
    ids = {r.doc_id: [*tokenizer.encode(r.text, add_special_tokens=False).ids, 0] for r in steps[4].collect()}
    covered, sequences = Counter(), {}
    for p in steps[5].collect():
        own = ids[p.doc_id]
        assert p.doc_tokens == len(own) and p.length > 0
        assert p.ids_crc32 == zlib.crc32(b"".join(x.to_bytes(4, "little") for x in own[p.start : p.start + p.length]))
        covered.update((p.doc_id, k) for k in range(p.start, p.start + p.length))
        sequences.setdefault(p.sequence_id, []).append((p.offset, p.length))
    assert covered == Counter({(i, k): copies[i] for i in ids for k in range(len(ids[i]))})
    for pieces in sequences.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 1024


def test_run_gives_the_last_stage(spark, folder, steps):
    total = lambda df: Counter((r.doc_id, r.ids_crc32, r.length) for r in df.collect())
    assert total(corpus_pipeline.run(spark, folder)) == total(steps[5])
