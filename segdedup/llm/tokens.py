"""Fast, exact encoding with the public byte-level BPE vocabulary.

The pattern that splits text before the merges never lets a piece run across a single space
or line feed between two other characters, so the ids of a clean text are those of its words,
each with the space or line feed before it. A worker keeps the ids of words it has met, as
little-endian 16-bit bytes, and hands only new words to the tokenizers library, many in one
text: their ids are told apart by the tokens that begin with a space or line feed, which occur
only at the start of a word. Texts with other white space, runs of it, or a special token's
string go to the library whole.

A worker outlives the stage it works for, and its memory counts as its executor's: texts are
encoded in small groups, and a worker that turns to other work forgets what it has learnt.
"""

from __future__ import annotations

import ctypes
import gc
import os
import re
from collections.abc import Iterable

import numpy as np

TAILS = ",."
#: Words a worker remembers at most, and characters of such a word; others are encoded each time they are met.
CACHE_WORDS, LONGEST = 1_000_000, 64
#: Characters of texts that are encoded at once.
GROUP = 400_000
#: New words in one text for the library.
JOINED = 64
OTHER_SPACE = re.compile("[\t\r\x0b\x0c\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")


class Encoder:
    """Ids of texts as arrays of unsigned 16-bit integers (the vocabulary has 50,257)."""

    def __init__(self, vocabulary: str, cache_words: int = CACHE_WORDS):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.cache_words = cache_words
        self.known: dict[str, bytes] = {}
        self.tails: dict[str, bytes] = {}
        vocab = self.tokenizer.get_vocab()
        self.begins = np.zeros(max(vocab.values()) + 1, dtype=bool)
        for piece, i in vocab.items():
            self.begins[i] = piece.startswith(("Ġ", "Ċ"))

    def _whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, dtype="<u2") for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _words(self, words: list[str]) -> dict[str, bytes]:
        """Keys are a word after a space; a line feed and a word; a space and a text's first word."""
        found = {}
        groups = [words[i : i + JOINED] for i in range(0, len(words), JOINED)]
        texts = ["".join([w if w[0] == "\n" else f"\n{w[1:]}" if w[0] == " " else f" {w}" for w in group]) for group in groups]
        for group, ids in zip(groups, self._whole(texts), strict=True):
            starts = np.flatnonzero(self.begins[ids])
            ends = np.append(starts[1:], len(ids)).tolist()
            raw = ids.tobytes()
            for w, a, b in zip(group, starts.tolist(), ends, strict=True):
                found[w] = raw[2 * a + 2 * (w[0] == " ") : 2 * b]
        return found

    def _learn(self, missing: set[str]) -> dict[str, bytes]:
        """Ids of new keys. A comma or full stop after a letter is a piece of its own, so such a
        word is its stem and the mark."""
        stems = {w: s for w in missing if (s := w.rstrip(TAILS)) != w and s[-1:].isalpha()}
        plain = [w for w in {*missing.difference(stems), *stems.values()} if w not in self.known]
        found = self._words(plain)
        for word, stem in stems.items():
            tail = word[len(stem) :]
            if tail not in self.tails:
                self.tails[tail] = self._whole([tail])[0].tobytes()
            found[word] = (self.known.get(stem) or found[stem]) + self.tails[tail]
        return found

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        get = self.known.get
        got: list[list | None] = []
        gaps: list[list[tuple[int, str]]] = []
        odd, missing = [], set()
        for text in texts:
            parts = text.replace("\n", " \n").split(" ") if text else []
            if parts and ("" in parts or "\n" in parts or parts[0][0] == "\n" or "<|" in text or OTHER_SPACE.search(text)):
                got.append(None)
                gaps.append([])
                odd.append(text)
                continue
            if parts:
                parts[0] = f" {parts[0]}"
            ids = list(map(get, parts))
            gap = [(i, parts[i]) for i, x in enumerate(ids) if x is None] if None in ids else []
            missing.update([w for _, w in gap])
            got.append(ids)
            gaps.append(gap)
        if missing:
            found = self._learn(missing)
            for ids, gap in zip(got, gaps, strict=True):
                for i, word in gap:
                    ids[i] = found[word]
            if len(self.known) + len(found) <= self.cache_words:
                self.known.update((w, ids) for w, ids in found.items() if len(w) <= LONGEST)
        whole = iter(self._whole(odd) if odd else ())
        return [next(whole) if ids is None else np.frombuffer(b"".join(ids), dtype="<u2") for ids in got]


_encoders: dict[str, Encoder] = {}


def encoder(vocabulary: str) -> Encoder:
    """This worker's encoder for a vocabulary file, with what it has learnt."""
    if vocabulary not in _encoders:
        _encoders[vocabulary] = Encoder(vocabulary)
    return _encoders[vocabulary]


def forget() -> None:
    """Gives back what this worker's encoders hold; kernels of other work call it."""
    if _encoders:
        _encoders.clear()
        gc.collect()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
            trim(0)


def batches(encode: Encoder, texts: Iterable[str | None], chars: int = GROUP):
    """Ids of each text, null as empty, encoded in groups of about `chars` characters."""
    group, size = [], 0
    for text in texts:
        group.append(text or "")
        size += len(group[-1])
        if size >= chars:
            yield from encode.encode(group)
            group, size = [], 0
    if group:
        yield from encode.encode(group)


def ordered(docs, partitions: int):
    """doc_id and text in ascending doc_id over range partitions, sorted within each; nulls first.

    Small Arrow batches keep long texts from filling a worker's memory.
    """
    from pyspark.sql import functions as F

    return docs.select(F.col("doc_id").cast("long"), "text").repartitionByRange(partitions, "doc_id").sortWithinPartitions("doc_id", "text")


def partitions_for(spark) -> int:
    """Range partitions: as many as shuffles have, or twice the cores if that is more."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
