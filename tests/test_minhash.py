"""The ML baseline keeps short texts."""

from segdedup import baselines


def test_short_texts_form_classes(spark):
    texts = [None, "", "  ", "one", "One", "a b c", "c b a b", "p q r s t", "p q r s t"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {tuple(r) for r in baselines.ml_minhash(docs).collect()} == {(3, 4, 0.0), (5, 6, 0.0), (7, 8, 0.0)}
