"""Clashing columns, empty tables, ties and repeated rows through every operation and stage."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from segdedup.llm import embedding_dedup, mixing, packing, pii, quality_model, quality_rules, simhash, suffix_dedup, token_files, url_filter

#: Names that the operations use inside or give out.
CLASH = ["size", "h", "target", "taken", "copies", "copy_", "source_size", "n_words", "kept", "posterior", "words_", "row_key", "row", "found", "votes", "doc", "runs", "mark", "node", "best", "hit_url", "place", "score", "start", "length", "v_lines", "base_failed", "clean", "key", "batch"]
VOCAB = None


def _vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(packing.VOCABULARY)


@pytest.fixture(scope="module")
def docs(spark):
    draw = random.Random(8)
    words = "the river of stone and a green house that we saw in winter was old but its garden had many trees with birds to watch for hours".split()
    texts = [" ".join(draw.choice(words) + draw.choice(["", "", "."]) + str(draw.randrange(40)) for _ in range(draw.randrange(70, 200))) for _ in range(12)]
    texts += [texts[0], texts[0], None, "", "mail a.b@c.org or 10.0.0.1 now. " + texts[1], "far " * 9000]
    rows = [(i if i != 4 else None, t, "en", f"s{i % 3}" if i % 5 else None, len(t or "")) for i, t in enumerate(texts)]
    made = spark.createDataFrame([*rows, rows[2]], "doc_id long, text string, lang string, source string, n_chars long")
    return made.select("*", *[F.lit(f"mine {c}").alias(c) for c in CLASH])


def _own(rows, column="text"):
    """The user's columns hold what they held."""
    for r in rows:
        assert all(r[c] == f"mine {c}" for c in CLASH), r
    return sorted((str(r["doc_id"]), str(r[column])) for r in rows)


def test_stages_keep_user_columns(spark, docs):
    now, bare = docs, docs.drop(*CLASH)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now, bare = (stage(spark, x, "").transform(lambda d: spark.createDataFrame(d.collect(), d.schema)) for x in (now, bare))
        rows = now.collect()
        assert rows and now.columns == docs.columns, name
        assert _own(rows) == sorted((str(r.doc_id), str(r.text)) for r in bare.collect()), name
        assert all(r.n_chars == len(r.text) for r in rows)
    last = corpus_pipeline.STAGES[-1][1]
    assert sorted(map(tuple, last(spark, now, "").collect())) == sorted(map(tuple, last(spark, bare, "").collect()))


def test_operations_do_not_look_at_other_columns(spark, docs, tmp_path):
    bare = docs.drop(*CLASH)
    labels = spark.createDataFrame([(i, i % 2) for i in range(12)], "doc_id long, quality int")
    token_files.write(docs, str(tmp_path / "a"), _vocabulary())
    token_files.write(bare, str(tmp_path / "b"), _vocabulary())
    both = [
        [suffix_dedup.removals(d).drop("removed") for d in (docs, bare)],
        [mixing.mix(d, [3, 1, 2], 1.5) for d in (docs, bare)],
        [quality_rules.judge(d) for d in (docs, bare)],
        [token_files.read(spark, str(tmp_path / n)) for n in "ab"],
        [pii.detect(d) for d in (docs, bare)],
        [quality_model.score(d, labels) for d in (docs, bare)],
        [simhash.near_duplicates(d) for d in (docs, bare)],
    ]
    for x, y in both:
        assert x.columns == y.columns and sorted(map(str, x.collect())) == sorted(map(str, y.collect()))


def test_pages_and_vectors_with_other_columns(spark):
    rules = spark.createDataFrame(url_filter.RULES, "host string, path string, verdict string")
    pages = spark.createDataFrame([(1, "http://a.net/es/x"), (2, None), (2, None), (None, "x://com/")], "page_id long, url string").select("*", *[F.lit(f"mine {c}").alias(c) for c in CLASH])
    got = url_filter.judge(pages, rules, whole=True).collect()
    assert sorted((str(r.page_id), r.verdict) for r in got) == [("1", "block"), ("2", "allow"), ("2", "allow"), ("None", "allow")]
    assert all(r["row"][c] == f"mine {c}" for r in got for c in CLASH)
    vectors = spark.createDataFrame([(1, [1.0, 0.0]), (2, [1.0, 0.01]), (3, [1.0]), (4, [2.0]), (5, None), (6, [])], "vec_id long, embedding array<float>").select("*", *[F.lit(0).alias(c) for c in CLASH])
    got = {r.vec_id: (r.n_links, r.component_id) for r in embedding_dedup.deduplicate(vectors).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (1, 3), 4: (1, 3), 5: (0, 5), 6: (0, 6)}  # lengths link among themselves


def test_empty_table_through_the_pipeline(spark, tmp_path):
    spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
