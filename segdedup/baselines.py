"""The systems that the segmented index is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segdedup import components, costmodel, keys, scratch, screen, set_join, similarity


#: Bytes of a (band, key) entry of a hash table in memory: two words, a pointer, the table's slack.
ENTRY_BYTES = 100


def snapshot_rebuild(docs: DataFrame, band_keys: DataFrame, releases: int) -> DataFrame:
    """Rebuilds all state at each release: release_no, touches (keys read), n_final."""
    decided = screen.bulk(docs, band_keys)
    per = band_keys.groupBy("release_no").agg(F.count(F.lit(1)).alias("n"))
    kept = decided.groupBy("release_no").agg(F.count(F.when(F.col("status") == "kept", 1)).alias("n_final"))
    upto = Window.orderBy("release_no").rowsBetween(Window.unboundedPreceding, Window.currentRow)  # a row per release
    return kept.join(per, "release_no", "left").select("release_no", F.sum("n").over(upto).alias("touches"), "n_final")


def bloom_positions(items: DataFrame, n0: int, fp: float) -> DataFrame:
    """items (id, key, ...) with the filter's bit positions, by double hashing of md5 halves."""
    bits, k = costmodel.bloom_bits(n0, fp)
    part = lambda at: F.conv(F.substring(F.md5(F.col("key").cast("string")), at, 8), 16, 10).cast("long")
    return items.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).withColumn("bit", F.pmod(part(1) + F.col("i") * (part(9) + 1), F.lit(bits)))


def bloom_fpr(stream: DataFrame, n0: int, fp: float, steps: list[int], holdout: DataFrame) -> DataFrame:
    """False positives of a holdout after each number of releases: step, n_inserted, fp, holdout.

    Each bit's first release is kept, so one pass answers every step.
    """
    first_bit = bloom_positions(stream, n0, fp).groupBy("bit").agg(F.min("release_no").alias("set_at"))
    asked = bloom_positions(holdout.select("rid", "key"), n0, fp).join(first_bit, "bit", "left")
    hit_at = asked.groupBy("rid").agg(F.max(F.coalesce("set_at", F.lit(1 << 30))).alias("hit_at"))
    step = F.explode(F.array(*[F.lit(s) for s in steps])).alias("step")
    hits = hit_at.select("hit_at", step).groupBy("step").agg(F.count(F.when(F.col("hit_at") <= F.col("step"), 1)).alias("fp"), F.count(F.lit(1)).alias("holdout"))
    grown = stream.groupBy("key").agg(F.min("release_no").alias("r")).select("r", step).groupBy("step").agg(F.count(F.when(F.col("r") <= F.col("step"), 1)).alias("n_inserted"))
    return hits.join(grown, "step").select("step", "n_inserted", "fp", "holdout")


def bloom_decisions(internal: DataFrame, fp: float, share: int = 4) -> DataFrame:
    """doc_id of the documents that a Bloom filter per band would call known: all bits of one of its keys
    were set by earlier releases. Each filter is made for a `share`th of its band's keys.

    A bit counts from the first release that sets it, so one pass answers for all releases.
    """
    n = internal.select("band", "key").distinct().count()
    bands = internal.select("band").distinct().count() or 1
    positions = bloom_positions(internal, max(1, n // (share * bands)), fp)
    first = positions.groupBy("band", "bit").agg(F.min("release_no").alias("set_at"))
    held = positions.join(first, ["band", "bit"]).groupBy("release_no", "doc_id", "band").agg(F.max("set_at").alias("all_set"))
    return held.where("all_set < release_no").select("doc_id").distinct()


def resident_decisions(docs: DataFrame, band_keys: DataFrame, cap_bytes: int) -> DataFrame:
    """doc_id, kept, bytes, stopped: one process takes the documents in order and keeps every band key of
    those it keeps in memory. It is the baseline's nature to be one task; it ends at the cap, and the
    documents from there on have no decision (kept is null)."""
    each = band_keys.groupBy("release_no", "doc_id").agg(F.sort_array(F.collect_list(F.struct("band", "key"))).alias("own"))
    rows = docs.select("release_no", "doc_id").join(each, ["release_no", "doc_id"], "left").select("release_no", "doc_id", F.coalesce("own", F.array().cast("array<struct<band: int, key: bigint>>")).alias("own"))

    def run(batches):
        import pyarrow as pa

        seen, used, stopped = set(), 0, False
        for batch in batches:
            kept, size, over = [], [], []
            for own in batch.column("own").to_pylist():
                mine = {(k["band"], k["key"]) for k in own}
                known = bool(mine & seen)
                if not known and not stopped:
                    used += ENTRY_BYTES * len(mine)
                    seen |= mine
                stopped = stopped or used > cap_bytes
                kept.append(None if stopped else not known)
                size.append(used)
                over.append(stopped)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(kept, pa.bool_()), pa.array(size, pa.int64()), pa.array(over, pa.bool_())], names=["doc_id", "kept", "bytes", "stopped"])

    return rows.repartition(1).sortWithinPartitions("release_no", "doc_id").mapInArrow(run, "doc_id long, kept boolean, bytes long, stopped boolean")


def served_topk(docs: DataFrame, config, top_k: int = 1, least: float = 0.5) -> DataFrame:
    """Each document's best earlier candidates by the signatures' agreement: doc_id, match_id, est.

    Of documents with equal signatures only the top_k first are compared with others: a later one
    has those at agreement 1, and no document needs more of a class than its top_k first.
    """
    signed = scratch.written(keys.compute(docs.select("doc_id", "text"), config, "signature").where(F.size("signature") > 0), "signatures")
    chosen = scratch.written(similarity.first_of_class(signed, "signature", top_k), "chosen")
    band = keys.long_keys(docs.select("doc_id", "text").join(chosen.select("doc_id"), "doc_id", "left_semi"), config)
    pairs = band.alias("x").join(band.alias("y"), ["band", "key"]).where("y.doc_id < x.doc_id").select(F.col("x.doc_id").alias("doc_id"), F.col("y.doc_id").alias("match_id")).distinct()
    both = pairs.join(chosen.select("doc_id", F.col("signature").alias("s")), "doc_id").join(chosen.select(F.col("doc_id").alias("match_id"), F.col("signature").alias("t")), "match_id")
    scored = both.select("doc_id", "match_id", F.round(keys.similarity("s", "t"), 6).alias("est")).where(F.col("est") >= least)
    best = Window.partitionBy("doc_id").orderBy(F.desc("est"), "match_id")
    found = scored.withColumn("place", F.row_number().over(best)).where(F.col("place") <= top_k).drop("place")
    later = signed.join(chosen.select("doc_id"), "doc_id", "left_anti").select("doc_id", F.sha2(F.array_join("signature", ","), 256).alias("class_"))
    copies = later.join(chosen.select("class_", F.col("doc_id").alias("match_id")), "class_")
    return found.union(copies.select("doc_id", "match_id", F.lit(1.0)))


def transitive(band_keys: DataFrame) -> DataFrame:
    """doc_id, label: components over all band collisions (each group linked to its least document)."""
    least = band_keys.groupBy("band", "key").agg(F.min("doc_id").alias("v"))
    edges = band_keys.join(least, ["band", "key"]).where("doc_id > v").select(F.col("doc_id").alias("u"), "v").distinct()
    joined = components.components(edges)
    return band_keys.select("doc_id").distinct().join(joined, F.col("doc_id") == F.col("node"), "left").select("doc_id", F.coalesce("component", "doc_id").alias("label"))


def ml_minhash(docs: DataFrame, tables: int = 8, distance: float = 0.3) -> DataFrame:
    """Spark ML's MinHash join of the documents' word sets: a, b, distance.

    Texts without words have no row. Equal word sets are joined once; their further documents stand beside the smallest at distance 0.
    The library's own join first makes every pair that agrees in one of `tables` values, which are most pairs of one language;
    here the candidates are the pairs near enough, and of them those that agree are kept: the same rows.
    """
    from pyspark.ml.feature import HashingTF, MinHashLSH

    spark = docs.sparkSession
    words = set_join.words(docs).select("doc_id", F.sha2("w", 256).alias("class_"), F.split("w", " ").alias("w"))
    vectors = HashingTF(inputCol="w", outputCol="v", numFeatures=1 << 18, binary=True).transform(words)
    hashed = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=7).fit(vectors).transform(vectors)
    # a value of the library's is a vector of one whole number below 2^31
    marks = F.transform("h", lambda h: F.unwrap_udt(h)["values"][0].cast("int"))
    every = scratch.written(hashed.select("doc_id", "class_", F.unwrap_udt("v")["indices"].alias("ids"), marks.alias("marks")), "word-sets")
    groups = scratch.written(similarity.classes(every.select("doc_id", F.array("class_").alias("w")), "w"), "classes")
    sets = scratch.written(similarity.representatives(every.drop("class_"), groups), "sets")
    scratch.drop(every)
    scratch.release(spark)
    pairs = scratch.written(set_join.candidates(sets, 1 - distance), "candidates")
    scratch.release(spark)
    asked = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()
    signed = scratch.written(sets.join(asked, "doc_id", "left_semi"), "signed")
    scratch.release(spark)
    apart = F.lit(1.0) - F.col("inter") / F.col("uni")
    between = set_join.compared(pairs, signed).where(F.col("agree") & (apart < distance)).select("a", "b", F.round(apart, 6).alias("distance"))
    return between.union(similarity.star(groups).select("a", "b", F.lit(0.0)))


def graph_bytes(n: int, m: int = 128, bits: int = 4096) -> int:
    """Signature and two-way links of each vector."""
    return n * (bits // 8 + 2 * m * 4)


def capabilities(spark: SparkSession) -> DataFrame:
    rows = [
        ("segmented_index", True, True, True, False, True, True),
        ("snapshot_rebuild", False, True, None, False, True, None),
        ("resident_table", True, True, False, False, None, None),
        ("bloom_bands", True, False, True, True, None, False),
        ("served_index", True, None, True, False, None, None),
        ("graph_substrate", True, False, False, False, None, None),
    ]
    return spark.createDataFrame(rows, "system string, incremental boolean, exact boolean, ram_free boolean, capacity_fixed boolean, retry boolean, withdrawal boolean")
