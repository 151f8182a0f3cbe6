"""Quality rules as weak supervision, in DataFrame functions only.

Nine rules look at whole texts and vote good (1), bad (0) or abstain (-1). Expectation-
maximisation over the counts of the vote patterns (at most 3^9 rows, whatever the corpus)
estimates how often each rule votes good or bad on good and on bad documents, and the share
of good documents. A document is kept if its posterior probability of being good reaches
`least` and no hard limit fails, so one borderline rule does not reject a document.

Words are runs without ASCII white space; lines are split at \\n. A null or empty text has
no words and fails the hard limit. Very long texts are measured whole. Repeated rows get equal
rows, null doc_ids stay, an empty table gives an empty result. Extra columns may have any name:
accepted() carries them in one struct, judge() gives doc_id and its own columns only.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import scratch

MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50
ROUNDS, SMOOTH = 40, 1.0

RULES = ("word_length", "symbols", "many_symbols", "shouting", "capitals", "lines", "windows", "variety", "stops")
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_shouts", "n_capitals", "n_stops", "n_distinct")
HELPERS = ("words_", "lines_", "hashes_", "ordered_", "places_")


def _band(value: Column, bad_under: float | None = None, good_from: float | None = None, good_to: float | None = None, bad_over: float | None = None) -> Column:
    """1 within the good range, 0 outside the bad limits, -1 between."""
    good, bad = F.lit(True), F.lit(False)
    if good_from is not None:
        good, bad = good & (value >= good_from), bad | (value < bad_under)
    if good_to is not None:
        good, bad = good & (value <= good_to), bad | (value > bad_over)
    return F.when(bad, 0).when(good, 1).otherwise(-1).cast("tinyint")


def with_repeated_words(split: DataFrame) -> DataFrame:
    """Adds n_repeat_words: how many words of words_ lie in a 3-word window found twice or more.

    Windows are sorted as (hash, place); neighbours of equal hash are repeated, and each such
    place covers itself and the next two words. Each step is a column of its own that the
    next one reads more than once, so Spark evaluates it once for a row, not once for an
    element of the array.
    """
    words, n = F.col("words_"), F.size("words_")
    hashed = split.withColumn("hashes_", F.when(n > 3, F.slice(F.transform(F.arrays_zip(words, F.slice(words, 2, n), F.slice(words, 3, n)), lambda w: F.xxhash64(w)), 1, n - 2)))
    repeats = F.size(F.array_distinct("hashes_")) < F.size("hashes_")
    ordered = hashed.withColumn("ordered_", F.when(repeats, F.sort_array(F.transform("hashes_", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    same = lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False))
    twice = F.filter("ordered_", lambda x, i: same(x, F.get(F.col("ordered_"), i + 1)) | same(x, F.get(F.col("ordered_"), i - 1)))
    places = ordered.withColumn("places_", F.transform(twice, lambda x: x["i"]))
    covered = F.array_union(F.array_union("places_", F.transform("places_", lambda p: p + 1)), F.transform("places_", lambda p: p + 2))
    return places.withColumn("n_repeat_words", F.coalesce(F.size(covered), F.lit(0)).cast("long")).drop("hashes_", "ordered_", "places_")


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with the measures of MEASURES, all long; text: the column (or field) that holds the texts."""
    text = F.coalesce(F.col(text), F.lit(""))
    rare = F.contains(text, F.lit("\t")) | F.contains(text, F.lit("\r")) | F.contains(text, F.lit("\x0b")) | F.contains(text, F.lit("\x0c"))
    spaced = F.replace(F.when(rare, F.translate(text, "\t\r\x0b\x0c", "    ")).otherwise(text), F.lit("\n"), F.lit(" "))
    lines = F.filter(F.split(text, "\n"), lambda s: F.length(F.trim(F.when(rare, F.translate(s, "\t\r\x0b\x0c", "    ")).otherwise(s))) > 0)
    base = docs.drop(*MEASURES, *HELPERS)
    split = base.withColumn("words_", F.array_remove(F.split(spaced, " "), "")).withColumn("lines_", lines)
    without = lambda c: (F.length(text) - F.length(F.replace(text, F.lit(c), F.lit("")))).cast("long")
    return with_repeated_words(split).select(
        *base.columns,
        F.size("words_").cast("long").alias("n_words"),
        F.length(F.array_join("words_", "")).cast("long").alias("word_chars"),
        F.regexp_count(text, F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"),
        (F.size("lines_") - F.size(F.array_distinct("lines_"))).cast("long").alias("n_dup_lines"),
        "n_repeat_words",
        F.size("lines_").cast("long").alias("n_lines"),
        without("!").alias("n_shouts"),
        F.regexp_count(text, F.lit("[A-Z]{3,}")).cast("long").alias("n_capitals"),
        without(".").alias("n_stops"),
        F.size(F.array_distinct("words_")).cast("long").alias("n_distinct"),
    )


def votes(measured: DataFrame) -> DataFrame:
    """measured with a column v_<rule> for each rule."""
    n = F.greatest(F.col("n_words"), F.lit(1))
    lines = F.greatest(F.col("n_lines"), F.lit(1))
    return measured.withColumns(
        {
            "v_word_length": _band(F.col("word_chars") / n, 2.5, 3.5, 9.0, 12.0),
            "v_symbols": _band(F.col("n_symbols") / n, good_to=0.05, bad_over=0.12),
            "v_many_symbols": _band(F.col("n_symbols") / n, good_to=0.1, bad_over=0.25),
            "v_shouting": _band(F.col("n_shouts") / n, good_to=0.05, bad_over=0.15),
            "v_capitals": _band(F.col("n_capitals") / n, good_to=0.05, bad_over=0.15),
            "v_lines": _band(F.col("n_dup_lines") / lines, good_to=0.1, bad_over=0.3),
            "v_windows": _band(F.col("n_repeat_words") / n, good_to=0.1, bad_over=0.25),
            "v_variety": F.when(n < 2000, _band(F.col("n_distinct") / n, 0.15, 0.3)).otherwise(F.lit(-1).cast("tinyint")),
            "v_stops": _band(F.col("n_stops") / n, 0.001, 0.01, 0.5, 0.8),
        }
    )


def fit(patterns: list[tuple[tuple[int, ...], int]]) -> dict:
    """Expectation-maximisation on (votes, count); rates[rule][vote] = (if bad, if good).

    It starts from the belief that rules are right more often than wrong, which fixes the
    meaning of the two classes. Abstentions carry no evidence. No patterns: the start.
    """
    width = len(patterns[0][0]) if patterns else len(RULES)
    rates = [{0: (0.6, 0.03), 1: (0.4, 0.97)} for _ in range(width)]
    prior = 0.85
    for _ in range(ROUNDS if patterns else 0):
        total = good = 0.0
        seen = [{0: [SMOOTH, SMOOTH * 0.1], 1: [SMOOTH, SMOOTH]} for _ in range(width)]
        for vote, count in patterns:
            p = 1 / (1 + math.exp(-max(-500.0, min(500.0, log_odds(vote, rates, prior)))))
            total, good = total + count, good + p * count
            for j, v in enumerate(vote):
                if v >= 0:
                    seen[j][v][0] += (1 - p) * count
                    seen[j][v][1] += p * count
        prior = min(0.999, max(0.5, good / total))
        rates = [{v: tuple(s[v][c] / (s[0][c] + s[1][c]) for c in (0, 1)) for v in (0, 1)} for s in seen]
    return {"rates": rates, "prior": prior}


def log_odds(vote: tuple[int, ...], rates: list[dict], prior: float) -> float:
    return math.log(prior / (1 - prior)) + sum(math.log(r[v][1] / r[v][0]) for v, r in zip(vote, rates, strict=True) if v >= 0)


def posterior(model: dict) -> Column:
    """Probability of a good document, from its v_ columns."""
    odds = F.lit(math.log(model["prior"] / (1 - model["prior"])))
    for rule, r in zip(RULES, model["rates"], strict=True):
        v = F.col(f"v_{rule}")
        odds = odds + F.when(v == 1, math.log(r[1][1] / r[1][0])).when(v == 0, math.log(r[0][1] / r[0][0])).otherwise(0.0)
    return 1 / (1 + F.exp(-odds))


def judge(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """doc_id, text, the measures, base_failed, posterior and kept of each row of docs."""
    return _judged(votes(measure(docs.select("doc_id", "text"))), least)


def accepted(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """The rows of docs that are kept, all of their columns with them."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return _judged(votes(measure(rows, "row.text")), least).where("kept").select("row.*")


def _judged(voted: DataFrame, least: float) -> DataFrame:
    """voted with base_failed, posterior and kept.

    The model is fitted on the documents that no hard limit rejects: they are the ones it judges.
    """
    voted = scratch.written(voted, "quality")
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    counts = voted.where(~failed).groupBy(*[f"v_{r}" for r in RULES]).count().collect()  # at most 3^9 rows
    model = fit([(tuple(int(x) for x in row[:-1]), row[-1]) for row in counts])
    return voted.withColumn("base_failed", failed).withColumn("posterior", posterior(model)).withColumn("kept", ~failed & (F.col("posterior") >= least))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = scratch.spread(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "posterior")


QUERIES = {"op3_quality_rules": op3_quality_rules}
ORACLE_SQL: dict[str, str] = {}
