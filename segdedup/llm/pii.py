"""Personal data by weak supervision: labelers vote on candidate spans, a classifier decides.

Candidates are the matches of the base patterns (they always stay) and looser ones: spelled-out
e-mail addresses, phone numbers without a country code, digit chains that fail their checksum.
Five labelers vote personal (1), not (0) or abstain (-1) on each: the strict pattern (0 where
its check fails), the checksum or range, a gazetteer (top-level domains, service numbers), the cue words before
the span, and counter-cues (version, order, build ...). Expectation-maximisation over the
counts of vote patterns (at most 4 kinds x 3^5) estimates each labeler's reliability, and a
logistic span classifier is trained on the posteriors with the pattern counts as weights.
A loose candidate becomes a span if the classifier gives it `least` or more.

Offsets are code points, ends exclusive. A null or empty text has no spans. Repeated rows
give equal rows, null doc_ids stay, an empty table gives an empty result; in redact() extra
columns pass through, whatever their names.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch
from segdedup.llm import tokens

KINDS = ("email", "ip", "card", "phone")
LABELERS = 5
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
DIGIT = re.compile("[0-9]")
LOOSE_PHONE = re.compile(r"(?<![\w+.-])(?:\([0-9]{3}\)|[0-9]{3})[ .-][0-9]{3}[ .-][0-9]{4}(?![\w-])")
SPELLED_DOT = re.compile(r" ?(?:\[dot\]|\(dot\)| dot )", re.I)
SPELLED = re.compile(r"(?<![\w.%+-])[\w.%+-]{1,64} ?(?:\[at\]|\(at\)| at ) ?[A-Za-z0-9-]{1,63} ?(?:\[dot\]|\(dot\)| dot ) ?[A-Za-z]{2,24}(?!\w)", re.I)
#: Gazetteers and cue words.
DOMAINS = frozenset("com org net edu gov io co info biz de fr es uk us eu example".split())
SERVICE_NUMBERS = frozenset(("800", "888", "877", "900"))
CUES = {
    "email": re.compile(r"\b(?:e-?mail|mail|contact|write|reach)\b", re.I),
    "ip": re.compile(r"\b(?:ip|host|server|address|login|client)\b", re.I),
    "card": re.compile(r"\b(?:card|visa|credit|debit|payment|iban|account)\b", re.I),
    "phone": re.compile(r"\b(?:phone|tel|call|mobile|fax|cell|number)\b", re.I),
}
COUNTER = re.compile(r"\b(?:version|release|build|order|isbn|section|serial|ticket|sku)\b", re.I)
BEFORE = 48


def luhn(digits: str) -> bool:
    twice = [2 * int(d) for d in digits[-2::-2]]
    return (sum(int(d) for d in digits[::-2]) + sum(d - 9 if d > 9 else d for d in twice)) % 10 == 0


def digits_of(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def emails(text: str) -> list[tuple[int, int]]:
    """Matches of the base pattern, found from each @ outwards, so long runs cost no more than their length."""
    out, last, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            last = m.end()
            out.append((start, last))
        at = text.find("@", max(at + 1, last))
    return out


def spans(text: str) -> list[tuple[int, int, int, bool, str]]:
    """start, kind's number, end, whether it is a base span, votes; ordered."""
    found: list[tuple[int, int, int, bool, str]] = []

    def add(kind: int, a: int, b: int, base: bool, check: int, known: int) -> None:
        before = text[max(0, a - BEFORE) : a]
        cue = 1 if CUES[KINDS[kind]].search(before) else -1
        against = 0 if COUNTER.search(before) else -1
        strict = 1 if base else 0 if check == 0 else -1
        votes = (strict, check, known, cue, against)
        found.append((a, kind, b, base, f"{kind}:" + ",".join(map(str, votes))))

    mails = emails(text)
    for a, b in mails:
        top = text[a:b].rsplit(".", 1)[-1].lower()
        add(0, a, b, True, -1, 1 if top in DOMAINS else -1)
    if SPELLED_DOT.search(text):
        for m in SPELLED.finditer(text):
            if not any(a < m.end() and m.start() < b for a, b in mails):
                add(0, m.start(), m.end(), False, -1, 1 if m[0].rsplit(None, 1)[-1].rstrip(")]").lower() in DOMAINS or m[0].split("]")[-1].lower() in DOMAINS else 0)
    if not DIGIT.search(text):
        return found
    for m in IP.finditer(text):
        if all(int(p) <= 255 for p in m[0].split(".") if len(p) < 19) and all(len(p.lstrip("0")) <= 3 for p in m[0].split(".")):
            add(1, m.start(), m.end(), True, 1, -1)
    for m in CARD.finditer(text):
        digits = digits_of(m[0])
        if 14 <= len(digits) <= 19:
            good = luhn(digits)
            add(2, m.start(), m.end(), good, 1 if good else 0, 1 if digits[0] in "3456" else -1)
    phones = []
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= len(digits_of(m[0])) <= 15:
                phones.append(m.span())
                add(3, m.start(), m.end(), True, 1, -1)
    for m in LOOSE_PHONE.finditer(text):
        if not any(a < m.end() and m.start() < b for a, b in phones):
            area = digits_of(m[0])[:3]
            add(3, m.start(), m.end(), False, 1 if area[0] not in "01" else 0, 0 if area in SERVICE_NUMBERS else 1)
    found.sort(key=lambda s: s[:3])
    return found


def joined(rows) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b, *_ in rows)


FOUND = pa.list_(pa.struct([("start", pa.int64()), ("kind", pa.int32()), ("end", pa.int64()), ("base", pa.bool_()), ("votes", pa.string())]))


def _find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        every, counts, digests = [], [[], [], [], []], []
        for text in batch.column("text"):
            got = spans(text.as_py() or "")
            base = [s for s in got if s[3]]
            for k in range(4):
                counts[k].append(sum(s[1] == k for s in base))
            digests.append(hashlib.sha256(joined(base).encode()).hexdigest())
            every.append([dict(zip(("start", "kind", "end", "base", "votes"), s, strict=True)) for s in got])
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), *(pa.array(c, pa.int64()) for c in counts), pa.array(digests, pa.string()), pa.array(every, FOUND)], names=["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "found"])


FOUND_SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, found array<struct<start: long, kind: int, end: long, base: boolean, votes: string>>"


def find(docs: DataFrame) -> DataFrame:
    """A row per document: counts and digest of the base spans, and all candidates with their votes."""
    return docs.select("doc_id", F.col("text")).mapInArrow(_find, FOUND_SCHEMA)


def fit(patterns: dict[str, int], least: float = 0.5, rounds: int = 40) -> set[str]:
    """Vote patterns whose loose candidates count as personal data."""
    if not patterns:
        return set()
    rows = [(int(p.split(":")[0]), np.array([int(v) for v in p.split(":")[1].split(",")])) for p in patterns]
    votes = np.array([v for _, v in rows])
    kinds = np.eye(len(KINDS))[[k for k, _ in rows]]
    weight = np.array([float(n) for n in patterns.values()])
    yes, no = (votes == 1).astype(float), (votes == 0).astype(float)
    right = np.full((LABELERS, 2), 0.8)  # P(vote 1 | personal), P(vote 0 | not)
    prior = 0.6
    for _ in range(rounds):
        odds = math.log(prior / (1 - prior)) + yes @ np.log(right[:, 0] / (1 - right[:, 1])) + no @ np.log((1 - right[:, 0]) / right[:, 1])
        p = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
        one, zero = weight * p, weight * (1 - p)
        # Beta(8, 2) beliefs in the labelers, in units of a tenth of the spans
        belief = 0.1 * weight.sum()
        right[:, 0] = (one @ yes + 0.8 * belief) / (one @ (yes + no) + belief)
        right[:, 1] = (zero @ no + 0.8 * belief) / (zero @ (yes + no) + belief)
        right = np.clip(right, 0.55, 0.98)
        prior = float(np.clip(one.sum() / weight.sum(), 0.05, 0.95))
    features = np.hstack([yes, no, kinds])
    beta, w = np.zeros(features.shape[1]), weight / weight.sum()
    for _ in range(500):  # the span classifier, on the posteriors
        q = 1 / (1 + np.exp(-np.clip(features @ beta, -30, 30)))
        beta -= 2.0 * (features.T @ (w * (q - p)) + 1e-4 * beta)
    q = 1 / (1 + np.exp(-np.clip(features @ beta, -30, 30)))
    return {name for name, x in zip(patterns, q, strict=True) if x >= least}


def learn(found: DataFrame) -> set[str]:
    counts = found.select(F.explode("found.votes").alias("votes")).groupBy("votes").count().collect()  # at most 4 x 3^5 rows
    return fit({r["votes"]: r["count"] for r in sorted(counts)})


def detect(docs: DataFrame) -> DataFrame:
    """doc_id, n_<kind> of the base, base_sha256 and all spans as a string."""
    found = scratch.written(find(docs), "pii")
    accepted = sorted(learn(found))
    kept = F.filter("found", lambda s: s["base"] | s["votes"].isin(accepted))
    names = F.array(*[F.lit(k) for k in KINDS])
    text = F.transform(kept, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"], s["end"]))
    return found.withColumn("spans", F.array_join(text, ",")).drop("found")


def covering(found: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """start, end, kind of the maximal runs that (start, end, kind) cover together; the first one names a run."""
    out: list[tuple[int, int, int]] = []
    for a, b, kind in sorted(found):
        if out and a < out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]), out[-1][2])
        else:
            out.append((a, b, kind))
    return out


CANDIDATES = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.int32()), ("base", pa.bool_()), ("votes", pa.string())]))


def _propose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """row and text come in; row and the candidates go out."""
    tokens.forget()
    for batch in batches:
        every = [[{"start": a, "end": b, "kind": k, "base": base, "votes": v} for a, k, b, base, v in spans(text.as_py() or "")] for text in batch.column("text")]
        yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(every, CANDIDATES)], names=["row", "found"])


def _redactor(accepted: set[str]):
    def redact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for cell, found in zip(batch.column("text"), batch.column("found").to_pylist(), strict=True):
                text = cell.as_py()
                parts, last = [], 0
                for a, b, kind in covering([(s["start"], s["end"], s["kind"]) for s in found if s["base"] or s["votes"] in accepted]):
                    parts += [text[last:a], f"<{KINDS[kind].upper()}>"]
                    last = b
                out.append("".join([*parts, text[last:]]) if parts else text)
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(out, pa.string())], names=["row", "clean"])

    return redact


def redact(docs: DataFrame) -> DataFrame:
    """docs with each run of overlapping spans replaced by the kind of its first in angle brackets.

    Texts are parsed once: the candidates are written beside the rows, the votes are counted
    there, and the second pass only cuts.
    """
    fields = [F.col(f"`{c}`") for c in docs.columns]
    rows = docs.select(F.struct(*fields).alias("row"), F.col("text"))
    kind = rows.schema["row"].dataType.simpleString()
    found = scratch.written(rows.mapInArrow(_propose, f"row {kind}, found array<struct<start: long, end: long, kind: int, base: boolean, votes: string>>"), "pii")
    accepted = learn(found)
    cut = found.select("row", F.col("row.text").alias("text"), "found").mapInArrow(_redactor(accepted), f"row {kind}, clean string")
    return cut.select(*[F.col("clean").alias(c) if c == "text" else F.col("row").getField(c).alias(c) for c in docs.columns])


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(scratch.table(spark, sf_dir, "documents"))


QUERIES = {"op6_pii": op6_pii}
ORACLE_SQL: dict[str, str] = {}
