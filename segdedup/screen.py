"""Decisions: within a release, against history, and for all releases in one pass."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def within_release(keys: DataFrame) -> DataFrame:
    """release_no, doc_id, band, winner: the documents that some band's group gives to a smaller one.

    keys: release_no, doc_id, band, key. Groups are reduced by map-side minima and only groups
    of several documents are joined back, so a boilerplate key costs no more than its rows.
    """
    groups = keys.groupBy("release_no", "band", "key").agg(F.min("doc_id").alias("winner"), F.max("doc_id").alias("last")).where("winner < last")
    lost = keys.join(groups.select("release_no", "band", "key", "winner"), ["release_no", "band", "key"]).where("winner < doc_id")
    return lost.groupBy("release_no", "doc_id").agg(F.min(F.struct("band", "winner")).alias("m")).select("release_no", "doc_id", "m.band", "m.winner")


def internal_keys(keys: DataFrame) -> DataFrame:
    """Keys of the documents that survive within their release: what the index commits."""
    return keys.join(within_release(keys).select("release_no", "doc_id"), ["release_no", "doc_id"], "left_anti")


def first_seen(internal: DataFrame) -> DataFrame:
    """Of each (band, key) the first release that commits it."""
    return internal.groupBy("band", "key").agg(F.min("release_no").alias("first_release"))


def bulk(docs: DataFrame, keys: DataFrame) -> DataFrame:
    """Decisions on all releases at once: release_no, doc_id, status, band, matched_release.

    Committing the survivors of a release, not of its history, makes a release's keys
    independent of history, so the first release of each key decides them all.
    """
    within = within_release(keys).select("doc_id", "release_no", F.col("band").alias("within_band"))
    internal = internal_keys(keys)
    history = (
        internal.join(first_seen(internal), ["band", "key"])
        .where("first_release < release_no")
        .groupBy("doc_id", "release_no")
        .agg(F.min(F.struct("first_release", "band")).alias("m"))
        .select("doc_id", "release_no", "m.first_release", F.col("m.band").alias("history_band"))
    )
    ids = docs.select("release_no", "doc_id")
    joined = ids.join(within, ["release_no", "doc_id"], "left").join(history, ["release_no", "doc_id"], "left")
    status = F.when(F.col("within_band").isNotNull(), "removed_within").when(F.col("first_release").isNotNull(), "removed_history").otherwise("kept")
    return joined.select("release_no", "doc_id", status.alias("status"), F.coalesce("within_band", "history_band").alias("band"), F.col("first_release").alias("matched_release"))
