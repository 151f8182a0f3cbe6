"""Mixing sources to target weights with hash-threshold histograms.

Each row gets a 60-bit hash of its doc_id. A source's target is met by taking every row
`base` times and one more copy of the rows whose hash lies under the source's threshold.
The threshold comes from nested histograms: words are summed by source and by the leading
12 bits of the hash, the running sums show in which bucket the budget ends, and only that
bucket is cut into 4096 finer ones, until the last bits of the hash. Nothing is sorted by
hash; a larger budget takes a superset of a smaller one.

Rows of equal hash (repeated doc_id) are taken together or not at all. A null text has
size 0, a null doc_id hashes like an empty string, null sources are one source, the last
in order. An empty table gives an empty mix. Very long texts count whole. Extra columns do not
matter, whatever their names: rows() carries them in one struct.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segdedup import scratch

#: Sources up to which the table of targets is broadcast.
BROADCAST_SOURCES = 50_000
HASH_BITS, STEP_BITS = 60, 12
WORD = r"[^\x20\x09-\x0D]+"


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def hash60(key: Column) -> Column:
    """The leading 15 hex digits of the key's md5."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long")


def targets(sized: DataFrame, weights: list[float], share: float, max_repeat: float) -> DataFrame:
    """source, source_size, target: water-filling in closed form.

    Sources in order of cap/weight; a source is at its cap if the level that the others
    would share (budget less the caps so far, by the weights left) is not under its ratio.
    """
    by_source = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    in_order = Window.orderBy(F.col("source").isNull(), "source")
    everything = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    filled = Window.orderBy("ratio", "place")
    return (
        by_source.withColumn("place", F.row_number().over(in_order))
        .withColumn("weight", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), ((F.col("place") - 1) % len(weights) + 1).cast("int")))
        .withColumn("cap", F.col("source_size") * F.lit(float(max_repeat)))
        .withColumn("ratio", F.col("cap") / F.col("weight"))
        .withColumn("budget", F.sum("source_size").over(everything) * F.lit(float(share)))
        .withColumn("spent", F.coalesce(F.sum("cap").over(filled.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("open_weight", F.sum("weight").over(filled.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("capped", F.col("ratio") <= (F.col("budget") - F.col("spent")) / F.col("open_weight"))
        .withColumn("first_open", F.min(F.when(~F.col("capped"), F.struct("ratio", "place", "spent", "open_weight"))).over(everything))
        .withColumn("target", F.when(F.col("capped"), F.col("cap")).otherwise((F.col("budget") - F.col("first_open.spent")) * F.col("weight") / F.col("first_open.open_weight")))
        .select("source", "source_size", "target")
    )


def _boundary(rows: DataFrame, low: int) -> DataFrame:
    """Of each open source the bucket in which its budget ends; rows: source, prefix, left, size, h."""
    cells = rows.groupBy("source", "left", F.shiftright("h", low).alias("bucket")).agg(F.sum("size").alias("n"))
    upto = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return (
        cells.withColumn("upto", F.sum("n").over(upto))
        .where(F.col("upto") > F.col("left"))
        .groupBy("source")
        .agg(F.min_by(F.struct("bucket", (F.col("left") - (F.col("upto") - F.col("n"))).alias("left")), "bucket").alias("b"))
        .select("source", F.col("b.bucket").alias("prefix"), F.col("b.left").alias("left"))
    )


def rows(docs: DataFrame, weights: list[float], share: float, max_repeat: int = 2) -> DataFrame:
    """The rows of docs as often as the mix takes them, all of their columns kept."""
    taken = mix(docs, weights, share, max_repeat, whole=True).where("copies > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")


def mix(docs: DataFrame, weights: list[float], share: float, max_repeat: int = 2, whole: bool = False) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, copies (how often the mix has it) of every row.

    weights repeat over the sources in order; share is the mix's size by the corpus's.
    whole: carry the row of docs along, as the struct `row`.
    """
    carried = [F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")] if whole else []
    narrow = docs.select("doc_id", "source", *carried, size_of(F.col("text")).alias("size"), hash60(F.col("doc_id")).alias("h"))
    stored = scratch.written(narrow, "mix")
    sized = stored.select("source", "size", "h")
    goal = scratch.written(targets(sized, weights, share, max_repeat), "mix-targets")
    small = goal.count() <= BROADCAST_SOURCES
    side = F.broadcast if small else lambda df: df

    goal = goal.withColumn("base", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0))
    budget = goal.select("source", (F.col("target") - F.col("base") * F.col("source_size")).alias("left"))
    edge = _boundary(_on_source(sized, side(budget)), HASH_BITS - STEP_BITS)
    for low in range(HASH_BITS - 2 * STEP_BITS, -1, -STEP_BITS):
        open_rows = _on_source(sized, side(edge)).where(F.shiftright("h", low + STEP_BITS) == F.col("prefix"))
        edge = _boundary(open_rows, low)
    plan = _on_source(goal, side(edge.select("source", F.col("prefix").alias("threshold"))), "left")
    whole = F.col("threshold").isNull() & (F.col("base") < max_repeat)
    return (
        _on_source(stored, side(plan), "left")
        .withColumn("copies", (F.col("base") + F.when(F.coalesce(F.col("h") < F.col("threshold"), whole), 1).otherwise(0)).cast("int"))
        .withColumn("taken", F.col("size") * F.col("copies"))
        .drop("h", "base", "threshold")
    )


def _on_source(left: DataFrame, right: DataFrame, how: str = "inner") -> DataFrame:
    """Joins on source, where null is a source as any other."""
    other = right.withColumnRenamed("source", "source_")
    return left.join(other, left["source"].eqNullSafe(other["source_"]), how).drop("source_")


def op2_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix(scratch.table(spark, sf_dir, "documents"), [3, 1, 2], 1.5)
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


QUERIES = {"op2_source_mix": op2_source_mix}

ORACLE_SQL = {
    "op2_source_mix": r"""
with sized as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size,
         ('0x' || substr(md5(coalesce(doc_id::varchar, '')), 1, 15))::bigint as h
  from documents),
per as (
  select source, sum(size)::bigint as source_size, row_number() over (order by source is null, source) as place
  from sized group by source),
w as (
  select *, [3.0, 1.0, 2.0][((place - 1) % 3 + 1)::int]::double as weight, source_size * 2.0::double as cap,
         (sum(source_size) over ())::double * 1.5::double as budget
  from per),
f as (
  select *, cap / weight as ratio,
         coalesce(sum(cap) over (order by cap / weight, place rows between unbounded preceding and 1 preceding), 0)::double as spent,
         (sum(weight) over (order by cap / weight, place rows between current row and unbounded following))::double as open_weight
  from w),
g as (select *, ratio <= (budget - spent) / open_weight as capped from f),
o as (select spent, open_weight from g where not capped order by ratio, place limit 1),
t as (
  select source, source_size,
         case when capped then cap else (budget - (select spent from o)) * weight / (select open_weight from o) end as target
  from g),
b as (select *, case when source_size > 0 then floor(target / source_size) else 0 end as base from t),
r as (
  select s.doc_id, s.size, b.source_size, b.target, b.base,
         sum(s.size) over (partition by s.source order by s.h range between unbounded preceding and current row) as upto
  from sized s join b on s.source is not distinct from b.source)
select doc_id, size, source_size, target::double as target,
       (size * (base + case when base < 2 and upto <= target - base * source_size then 1 else 0 end))::bigint as taken
from r
"""
}
