"""Queries of the operators around the index: joins, aggregates, windows, sets and functions, each with DuckDB SQL.

They work on the given tables as a user of the index would: reports on removed documents, the
manifest as of a time, requests within days of an event.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from segdedup import keys, releases
from segdedup.config import PORTABLE as C
from segdedup.queries import ORACLE_SQL as index_sql

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


def _read(spark, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


def rows():
    return F.count(F.lit(1))


@query("select doc_id, source from documents d where exists (select 1 from labels l where l.doc_id = d.doc_id and l.toxic = 1)")
def op_join_semi(spark, d):
    toxic = _read(spark, d, "labels").where("toxic = 1").select("doc_id")
    return _read(spark, d, "documents").select("doc_id", "source").join(toxic, "doc_id", "left_semi")


@query("select doc_id, source from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)")
def op_join_anti(spark, d):
    return _read(spark, d, "documents").select("doc_id", "source").join(_read(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@query("select coalesce(d.doc_id, l.doc_id) as doc_id, d.doc_id is not null as has_text, l.doc_id is not null as has_label from (select doc_id from documents where doc_id % 2 = 0) d full outer join (select distinct doc_id from labels) l on d.doc_id = l.doc_id")
def op_join_full(spark, d):
    """Two decisions side by side: which side has a row."""
    x = _read(spark, d, "documents").where("doc_id % 2 = 0").select("doc_id", F.lit(True).alias("x"))
    y = _read(spark, d, "labels").select("doc_id").distinct().withColumn("y", F.lit(True))
    return x.join(y, "doc_id", "full_outer").select("doc_id", F.col("x").isNotNull().alias("has_text"), F.col("y").isNotNull().alias("has_label"))


@query("select e.event_id, max(s.event_id) as signup_id from events e asof join (select user_id, ts, max(event_id) as event_id from events where event_type = 'signup' group by all) s on e.user_id = s.user_id and e.ts >= s.ts where e.event_type = 'purchase' group by e.event_id")
def op_join_asof(spark, d):
    """Each purchase with the user's latest sign-up at or before it: one union, one window, no inequality join."""
    e = _read(spark, d, "events")
    marks = e.where("event_type = 'signup'").groupBy("user_id", "ts").agg(F.max("event_id").alias("signup_id")).select("user_id", "ts", F.lit(0).alias("turn"), "signup_id", F.lit(None).cast("long").alias("event_id"))
    asked = e.where("event_type = 'purchase'").select("user_id", "ts", F.lit(1).alias("turn"), F.lit(None).cast("long").alias("signup_id"), "event_id")
    before = Window.partitionBy("user_id").orderBy("ts", "turn").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = marks.unionByName(asked).withColumn("signup_id", F.last("signup_id", ignorenulls=True).over(before))
    return both.where("turn = 1 and signup_id is not null").select("event_id", "signup_id")


_FENCES = "(values (0, 0, 50), (1, 50, 200), (2, 200, 1000), (3, 1000, 1000000000)) f(shard, lo, hi)"


@query(f"select shard::int as shard, count(*)::bigint as n from documents join {_FENCES} on n_chars >= lo and n_chars < hi group by shard")
def op_join_range(spark, d):
    """Routing by fences: a range join whose small side is a literal of four rows."""
    fences = spark.createDataFrame([(0, 0, 50), (1, 50, 200), (2, 200, 1000), (3, 1000, 1000000000)], "shard int, lo long, hi long")
    return _read(spark, d, "documents").select("n_chars").join(F.broadcast(fences), (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("shard").agg(rows().alias("n"))


@query("select s.user_id, count(*)::bigint as n from events s join events p on s.user_id = p.user_id and p.ts between s.ts and s.ts + interval 3 days where s.event_type = 'signup' and p.event_type = 'error' group by s.user_id")
def op_join_interval(spark, d):
    """Errors within three days after a user's sign-ups."""
    e = _read(spark, d, "events").select("user_id", "ts", "event_type")
    s, p = e.where("event_type = 'signup'").alias("s"), e.where("event_type = 'error'").alias("p")
    met = s.join(p, (F.col("s.user_id") == F.col("p.user_id")) & F.col("p.ts").between(F.col("s.ts"), F.col("s.ts") + F.expr("interval 3 days")))
    return met.groupBy(F.col("s.user_id").alias("user_id")).agg(rows().alias("n"))


_LABELLED = "(select d.doc_id, d.lang, d.source, l.quality from documents d join (select doc_id, max(quality) as quality from labels group by doc_id) l using (doc_id))"


def _labelled(spark, d) -> DataFrame:
    best = _read(spark, d, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    return _read(spark, d, "documents").select("doc_id", "lang", "source").join(best, "doc_id")


@query(f"select lang, source, count(*)::bigint as n, sum(quality)::bigint as good, (grouping(lang) * 2 + grouping(source))::bigint as level from {_LABELLED} group by cube(lang, source)")
def op_cube_removed(spark, d):
    return _labelled(spark, d).cube("lang", "source").agg(rows().alias("n"), F.sum("quality").alias("good"), F.grouping_id().alias("level"))


@query(f"select lang, source, count(*)::bigint as n, (grouping(lang) * 2 + grouping(source))::bigint as level from {_LABELLED} group by rollup(lang, source)")
def op_rollup_removed(spark, d):
    return _labelled(spark, d).rollup("lang", "source").agg(rows().alias("n"), F.grouping_id().alias("level"))


@query(f"select lang, source, quality, count(*)::bigint as n from {_LABELLED} group by grouping sets ((lang, quality), (source))")
def op_grouping_sets(spark, d):
    return _labelled(spark, d).groupingSets([["lang", "quality"], ["source"]], "lang", "source", "quality").agg(rows().alias("n"))


@query("select source, count(*) filter (lang = 'en')::bigint as en, count(*) filter (lang = 'fr')::bigint as fr, count(*) filter (lang = 'de')::bigint as de, count(*) filter (lang = 'es')::bigint as es from documents group by source")
def op_pivot(spark, d):
    return _read(spark, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).agg(rows()).fillna(0)


@query("select doc_id, rank() over w as r, dense_rank() over w as dr, row_number() over (partition by source order by n_chars desc, doc_id) as rn, ntile(4) over (partition by source order by n_chars desc, doc_id)::int as quarter, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from documents window w as (partition by source order by n_chars desc)")
def op_window_rank(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"))
    exact = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    long = lambda c: c.cast("long")
    return _read(spark, d, "documents").select("doc_id", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("dr"), long(F.row_number().over(exact)).alias("rn"), F.ntile(4).over(exact).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("select event_id, lag(event_id) over w as before_id, lead(event_id) over w as after_id, first_value(event_id) over w as first_id, (count(*) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row))::bigint as so_far, (count(*) over (partition by user_id order by ts range between interval 1 day preceding and current row))::bigint as in_day from events window w as (partition by user_id order by ts, event_id)")
def op_window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    day = Window.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)
    e = _read(spark, d, "events").select("event_id", "user_id", "ts", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    return e.select("event_id", F.lag("event_id").over(w).alias("before_id"), F.lead("event_id").over(w).alias("after_id"), F.first("event_id").over(w).alias("first_id"), rows().over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("so_far"), rows().over(day).alias("in_day"))


@query("select source, doc_id, n_chars from documents qualify row_number() over (partition by source order by n_chars desc, doc_id) <= 3")
def op_topk_groups(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return _read(spark, d, "documents").select("source", "doc_id", "n_chars", F.row_number().over(w).alias("place")).where("place <= 3").drop("place")


@query("select * from (select 'intersect' as kind, count(*)::bigint as n from (select l_partkey from lineitem where l_quantity < 10 intersect select l_partkey from lineitem where l_quantity > 40) union all select 'except', count(*) from (select l_partkey from lineitem where l_quantity < 10 except select l_partkey from lineitem where l_quantity > 40) union all select 'except_all', count(*) from (select l_partkey from lineitem where l_quantity < 10 except all select l_partkey from lineitem where l_quantity > 40) union all select 'intersect_all', count(*) from (select l_partkey from lineitem where l_quantity < 10 intersect all select l_partkey from lineitem where l_quantity > 40) union all select 'union', count(*) from (select l_partkey from lineitem where l_quantity < 10 union select l_partkey from lineitem where l_quantity > 40))")
def op_setops(spark, d):
    part = _read(spark, d, "lineitem").select("l_partkey", "l_quantity")
    x, y = part.where("l_quantity < 10").select("l_partkey"), part.where("l_quantity > 40").select("l_partkey")
    out = None
    for kind, made in (("intersect", x.intersect(y)), ("except", x.subtract(y)), ("except_all", x.exceptAll(y)), ("intersect_all", x.intersectAll(y)), ("union", x.union(y).distinct())):
        one = made.agg(rows().alias("n")).select(F.lit(kind).alias("kind"), "n")
        out = one if out is None else out.union(one)
    return out


@query("select page_id, lower(url) as low, length(url)::bigint as n, md5(url) as h, sha256(url) as s, split_part(url, '/', 3) as host, replace(url, 'http', 'x') as swapped, url like '%.com/%' as com, lpad(page_id::varchar, 8, '0') as padded from pages")
def op_string_fns(spark, d):
    u = F.col("url")
    return _read(spark, d, "pages").select("page_id", F.lower(u).alias("low"), F.length(u).cast("long").alias("n"), F.md5(u).alias("h"), F.sha2(u, 256).alias("s"), F.split_part(u, F.lit("/"), F.lit(3)).alias("host"), F.replace(u, F.lit("http"), F.lit("x")).alias("swapped"), u.like("%.com/%").alias("com"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"))


@query("select o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, datediff('day', date '1992-01-01', o_orderdate::date)::int as days, extract(quarter from o_orderdate)::int as quarter, dayofyear(o_orderdate)::int as yday, strftime(last_day(o_orderdate::date), '%Y-%m-%d') as month_end from orders")
def op_date_fns(spark, d):
    o = F.col("o_orderdate")
    return _read(spark, d, "orders").select("o_orderkey", F.date_format(F.date_trunc("month", o), "yyyy-MM").alias("month"), F.datediff(F.to_date(o), F.lit("1992-01-01").cast("date")).alias("days"), F.quarter(o).alias("quarter"), F.dayofyear(o).alias("yday"), F.date_format(F.last_day(o), "yyyy-MM-dd").alias("month_end"))


@query("select conv_id, len(r)::int as turns, array_to_string(list_sort(list_distinct(r)), ',') as roles, list_contains(r, 'user') as asks, list_sum(n)::bigint as chars from (select conv_id, list(role) as r, list(coalesce(length(text), 0)) as n from conversations group by conv_id)")
def op_array_map_json(spark, d):
    """A conversation as arrays of its turns."""
    each = _read(spark, d, "conversations").groupBy("conv_id").agg(F.collect_list("role").alias("r"), F.collect_list(F.coalesce(F.length("text"), F.lit(0)).cast("long")).alias("n"))
    return each.select("conv_id", F.size("r").alias("turns"), F.array_join(F.array_sort(F.array_distinct("r")), ",").alias("roles"), F.array_contains("r", "user").alias("asks"), F.aggregate("n", F.lit(0).cast("long"), lambda a, x: a + x).alias("chars"))


@query("select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*)::bigint as n from events group by all")
def op_tumbling(spark, d):
    """Arrivals by day: the batch twin of streaming.tumbling."""
    w = _read(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(rows().alias("n"))
    return w.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("select epoch(s)::bigint as start_s, count(*)::bigint as n from (select unnest(range(time_bucket(interval 6 hours, ts::timestamp, timestamp '1970-01-01') - interval 18 hours, time_bucket(interval 6 hours, ts::timestamp, timestamp '1970-01-01') + interval 1 second, interval 6 hours)) as s from events) group by s")
def op_sliding(spark, d):
    """Days that start every six hours: the batch twin of streaming.sliding."""
    w = _read(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(rows().alias("n"))
    return w.select(F.unix_seconds("w.start").alias("start_s"), "n")


@query("with g as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows between unbounded preceding and current row) as s from (select user_id, ts, case when lag(ts) over (partition by user_id order by ts) + interval 30 minutes > ts then 0 else 1 end as fresh from events)) select user_id, floor(epoch(min(ts)))::bigint as start_s, count(*)::bigint as n from g group by user_id, s")
def op_session(spark, d):
    """Sessions that end after 30 idle minutes: the batch twin of streaming.sessions."""
    w = _read(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(rows().alias("n"))
    return w.select("user_id", F.unix_seconds("w.start").alias("start_s"), "n")


@query()
def op_hll_sketch(spark, d):
    """Sizes of unions before a merge, from one sketch per release: estimate beside the exact number."""
    ks = releases.key_stream(spark, d).groupBy("release_no").agg(F.hll_sketch_agg("key", F.lit(14)).alias("sketch"))
    exact = releases.key_stream(spark, d).agg(F.countDistinct("key").alias("exact"))
    whole = ks.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("estimate"))
    return whole.crossJoin(exact).select("estimate", "exact")  # one row with one row


@query(index_sql["band_keys_long"])
def op_udtf_band_keys(spark, d):
    """Band keys by a table function that SQL can call beside a table."""
    keys.register(spark, C)
    _read(spark, d, "documents").select("doc_id", "text").createOrReplaceTempView("segdedup_documents")
    return spark.sql("select doc_id, k.band, k.key from segdedup_documents, lateral segdedup_band_keys(text) k")
