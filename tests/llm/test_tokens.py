"""What a worker holds: it outlives the stage it works for, and its memory counts as its executor's."""

import numpy as np
import pyarrow as pa
import pytest
import public_tokenizers

from segdedup.llm import near_copies, packing, pii, tokens

VOCAB = public_tokenizers.path(packing.VOCABULARY)


def _text(names: list[str]) -> pa.RecordBatch:
    columns = {"row_key": ["a"], "doc_id": [1], "text": ["one two three four five six"], "row": [1]}
    return pa.RecordBatch.from_pydict({n: columns[n] for n in names})


@pytest.mark.parametrize("kernel, names", [(near_copies._read, ["row_key", "doc_id", "text"]), (near_copies._post, ["text"]), (pii._propose, ["row", "text"])])
def test_other_work_forgets_the_words(kernel, names):
    tokens.encoder(VOCAB).encode(["one two three"])
    assert sum(b.num_rows for b in kernel(iter([_text(names)])))
    assert not tokens._encoders


def test_texts_are_encoded_in_small_groups():
    class Counting(tokens.Encoder):
        most = 0

        def encode(self, texts):
            self.most = max(self.most, sum(map(len, texts)))
            return super().encode(texts)

    texts = [None, "", *(f"word{i % 7} and {'more ' * 2000}end" for i in range(200)), "x" * 5000 + " z"]
    encode = Counting(VOCAB)
    got = list(tokens.batches(encode, iter(texts)))
    assert encode.most < 500_000
    for ids, text in zip(got, texts, strict=True):
        assert np.array_equal(ids, encode.tokenizer.encode(text or "", add_special_tokens=False).ids)


def test_long_words_are_not_remembered():
    encode = tokens.Encoder(VOCAB)
    text = f"a short word and {'long' * 3000}, then {'long' * 3000}"
    for _ in range(2):
        assert np.array_equal(encode.encode([text])[0], encode.tokenizer.encode(text, add_special_tokens=False).ids)
    assert "short" in encode.known and max(map(len, encode.known)) <= tokens.LONGEST
