"""Exact set similarity between documents, over classes of equal shingle sets.

Documents of equal sets form a class, held by its smallest doc_id; only such representatives
are compared, so a group of copies costs one comparison and its members are listed once. Between
representatives a prefix filter finds every pair of the wanted similarity: sets are ordered
rarest shingle first, and two sets of Jaccard num/den or more share a shingle within their first
n - ceil(n * num / den) + 1. No shingle is left out however common it is; a common one stands
late in its sets and seldom falls in a prefix. Candidates are counted whole before a pair is kept.

Shingles travel as 64-bit hashes. Two that collide in different documents only share a place in
the order; a count is wrong only if they meet within one compared pair.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segdedup import keys, scratch


def shingle_sets(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, ids (sorted distinct shingle hashes), n; texts without words (or null) have no row."""
    words = F.filter(F.split(keys.normalise(F.col("text")), " "), lambda w: w != "")
    n = F.size("w")
    at = F.sequence(F.lit(1), F.greatest(n - (k - 1), F.lit(1)))
    made = F.when(n < k, F.array(F.xxhash64(F.array_join("w", " ")))).otherwise(F.transform(at, lambda i: F.xxhash64(F.array_join(F.slice("w", i, k), " "))))
    found = docs.select("doc_id", words.alias("w")).where(F.size("w") > 0).select("doc_id", F.array_sort(F.array_distinct(made)).alias("ids"))
    return found.withColumn("n", F.size("ids").cast("long"))


def classes(rows: DataFrame, content: str) -> DataFrame:
    """doc_id and rep, the smallest doc_id whose array `content` is equal."""
    digest = F.sha2(F.array_join(content, ","), 256)
    marked = rows.select("doc_id", digest.alias("class_"))
    return marked.join(marked.groupBy("class_").agg(F.min("doc_id").alias("rep")), "class_").select("doc_id", "rep").distinct()


def members(found: DataFrame) -> DataFrame:
    """rep and the number of its class's documents."""
    return found.groupBy("rep").agg(F.count(F.lit(1)).alias("members"))


def representatives(rows: DataFrame, found: DataFrame) -> DataFrame:
    """The rows of the representatives alone."""
    return rows.join(found.where("doc_id = rep").select("doc_id"), "doc_id", "left_semi")


def _prefixes(sets: DataFrame, num: int, den: int) -> DataFrame:
    """doc_id, n, id, pos of each prefix shingle that another set has too."""
    flat = sets.select("doc_id", "n", F.explode("ids").alias("id"))
    often = flat.groupBy("id").agg(F.count(F.lit(1)).alias("df"))
    ranked = flat.join(often, "id").groupBy("doc_id", "n").agg(F.sort_array(F.collect_list(F.struct("df", "id"))).alias("ranked"))
    length = F.expr(f"cast(n - ceil(n * {num} / {den}d - 1e-9) + 1 as int)")
    cut = ranked.select("doc_id", "n", F.posexplode(F.slice("ranked", 1, length)).alias("pos", "t"))
    return cut.where("t.df > 1").select("doc_id", "n", F.col("t.id").alias("id"), (F.col("pos") + 1).alias("pos"))


def counted(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """pairs (a, b, ...) with inter, uni: the shingles that both have, that either has."""
    left = sets.select(F.col("doc_id").alias("a"), F.col("ids").alias("x_"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("ids").alias("y_"))
    both = pairs.join(left, "a").join(right, "b")
    inter = F.size(F.array_intersect("x_", "y_")).cast("long")
    return both.select(*pairs.columns, inter.alias("inter"), (F.size("x_") + F.size("y_")).alias("sum_")).withColumn("uni", F.col("sum_") - F.col("inter")).drop("sum_")


def pairs_above(sets: DataFrame, num: int, den: int) -> DataFrame:
    """a < b, inter, uni of all pairs of sets whose Jaccard is num/den or more (num > 0)."""
    cut = scratch.written(_prefixes(sets, num, den), "prefixes")
    x, y = (cut.select(F.col("doc_id").alias(i), F.col("n").alias(f"n{i}"), "id", F.col("pos").alias(f"p{i}")) for i in "ab")
    sized = (F.col("na") * den >= F.col("nb") * num) & (F.col("nb") * den >= F.col("na") * num)
    met = x.join(y, "id").where((F.col("a") < F.col("b")) & sized)
    first = met.groupBy("a", "b", "na", "nb").agg(F.min("pa").alias("pa"), F.min("pb").alias("pb"))
    # nothing before the first common shingle is shared
    most = 1 + F.least(F.col("na") - F.col("pa"), F.col("nb") - F.col("pb"))
    able = first.where(most * (num + den) >= (F.col("na") + F.col("nb")) * num).select("a", "b")
    return counted(able, sets).where(F.col("inter") * den >= F.col("uni") * num)


def star(found: DataFrame) -> DataFrame:
    """a (representative), b (another member of its class)."""
    return found.where("doc_id <> rep").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"))


def first_of_class(rows: DataFrame, content: str, k: int) -> DataFrame:
    """rows with class_ and place for the k smallest doc_ids of each class (place 1 to k)."""
    order = Window.partitionBy("class_").orderBy("doc_id")
    marked = rows.withColumn("class_", F.sha2(F.array_join(content, ","), 256))
    return marked.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)
