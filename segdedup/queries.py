"""The registered queries of the index, its baselines, measures and workloads, with DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from segdedup import baselines, costmodel, keys, policies, releases, scratch, screen, segments, similarity
from segdedup.config import PORTABLE, PRIME, DedupConfig
from segdedup.index import Index, Prepared, ingest_all

C = PORTABLE
QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLE_SQL[f.__name__] = sql
        return f

    return add


# SQL twins

_COEF = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(C.coefficients()))
WORDS = """
base as (
  select doc_id, source, text, lang, n_chars,
         regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w,
         (doc_id % 20 + case when doc_id >= (select count(*) from documents) / 2 then 20 else 0 end)::int as r40, (doc_id % 20)::int as r20
  from documents),
sh as (
  select doc_id, unnest(list_distinct(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
         else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end)) as s
  from base)"""
SIGNED = (
    WORDS
    + f""",
coef(pos, a, b) as (values {_COEF}),
hs as (select doc_id, ('0x' || substr(md5(s), 1, 8))::bigint % {PRIME} as h from sh),
sig as (select doc_id, pos, min((a::bigint * h + b) % {PRIME})::bigint as v from hs cross join coef group by doc_id, pos)"""
)
KEYED = (
    SIGNED
    + f""",
dk as (select doc_id, (pos // {C.rows})::int as band, ('0x' || substr(md5(string_agg(v::varchar, ',' order by pos)), 1, 15))::bigint as key from sig group by doc_id, pos // {C.rows})"""
)


def decided(rule: str = "r40", source: str = "base") -> str:
    """CTEs: rk (release, doc, band, key), lost, ik (internal keys), fs (first release), dec."""
    return (
        KEYED
        + f""",
rk as (select b.{rule} as release_no, dk.* from dk join {source} b using (doc_id)),
win as (select *, min(doc_id) over (partition by release_no, band, key) as winner from rk),
lost as (select release_no, doc_id, min({{'band': band, 'winner': winner}}) as m from win where winner < doc_id group by all),
ik as (select rk.* from rk where not exists (select 1 from lost l where l.doc_id = rk.doc_id)),
fs as (select band, key, min(release_no) as first_release from ik group by band, key),
hist as (select ik.doc_id, min({{'first_release': first_release, 'band': band}}) as m from ik join fs using (band, key) where first_release < release_no group by ik.doc_id),
dec as (
  select b.{rule} as release_no, b.doc_id,
         case when l.doc_id is not null then 'removed_within' when h.doc_id is not null then 'removed_history' else 'kept' end as status,
         coalesce(l.m.band, h.m.band)::int as band, h.m.first_release::int as matched_release
  from {source} b left join lost l using (doc_id) left join hist h using (doc_id))"""
    )


def _docs(spark: SparkSession, sf_dir: str, k: int = 40) -> tuple[DataFrame, DataFrame]:
    docs = releases.documents(spark, sf_dir, k)
    return docs, scratch.written(keys.long_keys(docs, C), "keys")


# the rule


@query("select doc_id, length(n)::bigint as norm_len, md5(n) as norm_md5 from (select doc_id, trim(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+', ' ', 'g'), ' ') as n from documents)")
def normalize_docs(spark, d):
    n = keys.normalise(F.col("text"))
    return scratch.table(spark, d, "documents").select("doc_id", F.length(n).cast("long").alias("norm_len"), F.md5(n).alias("norm_md5"))


@query(f"with {WORDS} select b.doc_id, len(b.w)::bigint as n_words, count(s)::bigint as n_shingles from base b left join sh using (doc_id) group by b.doc_id, len(b.w)")
def shingle_counts(spark, d):
    words = F.filter(F.split(keys.normalise(F.col("text")), " "), lambda w: w != "")
    split = scratch.table(spark, d, "documents").select("doc_id", words.alias("w"))
    n = F.size("w")
    made = F.when(n == 0, F.array().cast("array<string>")).when(n < C.k, F.array(F.array_join("w", " "))).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(n - (C.k - 1), F.lit(1))), lambda i: F.array_join(F.slice("w", i, C.k), " ")))
    return split.select("doc_id", n.cast("long").alias("n_words"), F.size(F.array_distinct(made)).cast("long").alias("n_shingles"))


def _shingles(spark, d) -> DataFrame:
    words = F.filter(F.split(keys.normalise(F.col("text")), " "), lambda w: w != "")
    split = scratch.table(spark, d, "documents").select("doc_id", words.alias("w")).where(F.size("w") > 0)
    n = F.size("w")
    made = F.when(n < C.k, F.array(F.array_join("w", " "))).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(n - (C.k - 1), F.lit(1))), lambda i: F.array_join(F.slice("w", i, C.k), " ")))
    return split.select("doc_id", F.explode(F.array_distinct(made)).alias("s"))


_SETS = """,
st0 as (select doc_id, count(*)::bigint as n, string_agg(s, chr(10) order by s) as content from sh group by doc_id),
cl as (select doc_id, n, min(doc_id) over (partition by content) as rep from st0)"""

_PAIRS = (
    _SETS
    + """,
rs as (select sh.* from sh join cl using (doc_id) where cl.doc_id = cl.rep),
pr as (select x.doc_id as a, y.doc_id as b, count(*)::bigint as inter from rs x join rs y using (s) where x.doc_id < y.doc_id group by all),
jac as (select a, b, inter, (p.n + q.n - inter)::bigint as uni, round(inter / (p.n + q.n - inter), 6) as j from pr join cl p on p.doc_id = a join cl q on q.doc_id = b)"""
)


def _sets(spark, d) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The documents' shingle sets, their classes, and the sets of the representatives."""
    sets = scratch.written(similarity.shingle_sets(scratch.table(spark, d, "documents"), C.k), "shingle-sets")
    found = scratch.written(similarity.classes(sets, "ids"), "classes")
    return sets, found, scratch.written(similarity.representatives(sets, found), "representatives")


def _j():
    """Jaccard of a counted pair; a function, since a Column needs a session."""
    return F.round(F.col("inter") / F.col("uni"), 6).alias("j")


@query(f"with {WORDS}{_PAIRS} select 'pair' as kind, * from jac where inter * 2 >= uni union all select 'class', rep, doc_id, n, n, 1.0 from cl where doc_id <> rep")
def jaccard_pairs(spark, d):
    """Pairs of Jaccard 0.5 or more between representatives of equal shingle sets, and each
    further member of a class (kind class) with its representative."""
    sets, found, chosen = _sets(spark, d)
    pairs = similarity.pairs_above(chosen, 1, 2).select(F.lit("pair").alias("kind"), "a", "b", "inter", "uni", _j())
    own = similarity.star(found).join(sets.select(F.col("doc_id").alias("b"), "n"), "b")
    return pairs.union(own.select(F.lit("class"), "a", "b", "n", "n", F.lit(1.0)))


@query(f"with {SIGNED} select doc_id, pos::int as pos, v as value from sig")
def minhash_signatures(spark, d):
    signed = keys.compute(scratch.table(spark, d, "documents").select("doc_id", "text"), C, "signature")
    return signed.select("doc_id", F.posexplode("signature").alias("pos", "value"))


@query(f"with {KEYED} select doc_id, band, key from dk")
def band_keys_long(spark, d):
    return keys.long_keys(scratch.table(spark, d, "documents").select("doc_id", "text"), C)


@query(f"with {SIGNED} select doc_id, (pos // {C.rows})::int as band, md5(string_agg(v::varchar, ',' order by pos)) as key_hex from sig group by doc_id, pos // {C.rows}")
def band_keys_128(spark, d):
    wide = keys.compute(scratch.table(spark, d, "documents").select("doc_id", "text"), C, "wide")
    return wide.select("doc_id", F.posexplode("wide").alias("band", "key")).select("doc_id", "band", F.lower(F.hex("key")).alias("key_hex"))


_CAND = ", cand as (select x.doc_id as a, y.doc_id as b, count(*)::bigint as shared from dk x join dk y using (band, key) where x.doc_id < y.doc_id group by all)"
_RCAND = ", cand as (select x.doc_id as a, y.doc_id as b, count(*)::bigint as shared from dk x join dk y using (band, key) join cl p on p.doc_id = x.doc_id join cl q on q.doc_id = y.doc_id where x.doc_id < y.doc_id and p.rep = p.doc_id and q.rep = q.doc_id group by all)"


def _candidates(k: DataFrame) -> DataFrame:
    """Pairs that share a band key, of documents given once a class."""
    return k.alias("x").join(k.alias("y"), ["band", "key"]).where("x.doc_id < y.doc_id").groupBy(F.col("x.doc_id").alias("a"), F.col("y.doc_id").alias("b")).agg(F.count(F.lit(1)).alias("shared"))


def _chosen_keys(spark, d, found: DataFrame) -> DataFrame:
    """Band keys of the representatives."""
    docs = scratch.table(spark, d, "documents").select("doc_id", "text")
    return scratch.written(keys.long_keys(similarity.representatives(docs, found), C), "keys")


@query(f"with {KEYED}, kl as (select doc_id, string_agg(key::varchar, ',' order by band) as content from dk group by doc_id), cl as (select doc_id, min(doc_id) over (partition by content) as rep from kl){_RCAND} select 'pair' as kind, * from cand union all select 'class', rep, doc_id, {C.bands} from cl where doc_id <> rep")
def lsh_candidate_pairs(spark, d):
    """Pairs that share a band key, between representatives of equal key lists, and each further
    member of a class (kind class) with its representative."""
    keyed = scratch.written(keys.compute(scratch.table(spark, d, "documents").select("doc_id", "text"), C).where(F.size("keys") > 0), "key-lists")
    found = scratch.written(similarity.classes(keyed, "keys"), "classes")
    long = similarity.representatives(keyed, found).select("doc_id", F.posexplode("keys").alias("band", "key"))
    pairs = _candidates(scratch.written(long, "keys")).select(F.lit("pair").alias("kind"), "a", "b", "shared")
    return pairs.union(similarity.star(found).select(F.lit("class"), "a", "b", F.lit(C.bands).cast("long")))


@query(f"with {KEYED}{_PAIRS}{_RCAND}, est as (select a, b, round(avg((p.v = q.v)::int), 6) as est from cand join sig p on p.doc_id = a join sig q on q.doc_id = b and p.pos = q.pos group by a, b) select a, b, est, coalesce(j, 0.0) as j, round(abs(est - coalesce(j, 0.0)), 6) as abs_err from est left join jac using (a, b) union all select rep, doc_id, 1.0, 1.0, 0.0 from cl where doc_id <> rep")
def sig_estimates(spark, d):
    """Estimated against exact Jaccard of the candidates between representatives of equal
    shingle sets; a further member of a class is listed with its representative."""
    _, found, chosen = _sets(spark, d)
    signed = keys.compute(similarity.representatives(scratch.table(spark, d, "documents").select("doc_id", "text"), found), C, "signature")
    pairs = similarity.counted(_candidates(_chosen_keys(spark, d, found)).select("a", "b"), chosen)
    both = pairs.join(signed.select(F.col("doc_id").alias("a"), F.col("signature").alias("s")), "a").join(signed.select(F.col("doc_id").alias("b"), F.col("signature").alias("t")), "b")
    est = F.round(keys.similarity("s", "t"), 6)
    out = both.select("a", "b", est.alias("est"), _j()).withColumn("abs_err", F.round(F.abs(F.col("est") - F.col("j")), 6))
    return out.union(similarity.star(found).select("a", "b", F.lit(1.0), F.lit(1.0), F.lit(0.0)))


@query("select b::int as b, r::int as r, round(i * 0.05, 2)::double as j, round(1 - pow(1 - pow(round(i * 0.05, 2), r), b), 6)::double as p from (values (16, 8), (8, 4), (32, 4), (20, 5)) t(b, r), range(0, 21) g(i)")
def s_curve(spark, d):
    rows = [(b, r, round(i * 0.05, 2), round(costmodel.lsh_probability(round(i * 0.05, 2), b, r), 6)) for b, r in ((16, 8), (8, 4), (32, 4), (20, 5)) for i in range(21)]
    return spark.createDataFrame(rows, "b int, r int, j double, p double")


@query("select u::double as u, 64 as bits, round(16 * u / pow(2.0, 64) * 1e12, 6)::double as bound_e12 from (values (1e9), (1e12)) t(u)")
def residual_bound(spark, d):
    return spark.createDataFrame([(u, 64, round(costmodel.residual_bound(u) * 1e12, 6)) for u in (1e9, 1e12)], "u double, bits int, bound_e12 double")


@query("select sha256(text) as h, count(*)::bigint as n, min(doc_id) as keep_id from documents group by text having count(*) > 1")
def exact_duplicates(spark, d):
    return scratch.table(spark, d, "documents").groupBy(F.sha2("text", 256).alias("h")).agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("keep_id")).where("n > 1")


# the lifecycle


@query(f"with {decided('r20')} select release_no, doc_id, m.band as band, m.winner as winner from lost")
def within_release_removed(spark, d):
    return screen.within_release(_docs(spark, d, 20)[1])


@query(f"with {decided()} select release_no, count(distinct doc_id)::bigint as n_docs, count(*)::bigint as n_keys from ik group by release_no")
def internal_survivors(spark, d):
    ik = screen.internal_keys(_docs(spark, d)[1])
    return ik.groupBy("release_no").agg(F.countDistinct("doc_id").alias("n_docs"), F.count(F.lit(1)).alias("n_keys"))


@query(f"with {decided()} select doc_id, matched_release as first_release, band from dec where status = 'removed_history'")
def historical_matches(spark, d):
    return screen.bulk(*_docs(spark, d)).where("status = 'removed_history'").select("doc_id", F.col("matched_release").alias("first_release"), "band")


@query(f"with {decided()} select release_no, doc_id from dec where status = 'kept'")
def final_survivors(spark, d):
    return screen.bulk(*_docs(spark, d)).where("status = 'kept'").select("release_no", "doc_id")


@query(f"with {decided()} select * from dec")
def bulk_ingest(spark, d):
    return screen.bulk(*_docs(spark, d))


def _index(spark, policy=None, config=C) -> Index:
    return Index(spark, scratch.new_path(spark, "index"), config, policy)


def _six(docs: DataFrame) -> DataFrame:
    return docs.withColumn("release_no", F.pmod("doc_id", F.lit(6)).cast("int"))


_SIX = decided("r6", "(select *, (doc_id % 6)::int as r6 from base)")


def _committed(index: Index, ready: Prepared, k: int, protected: frozenset[int] = frozenset()) -> Index:
    """Commits and compacts prepared releases 0 to k - 1, without decisions."""
    for r in range(k):
        index.admit(ready, r, f"r{r}", protected=r in protected, decide=False)
    return index


def _members(origins: str):
    """The least release number of a segment's origins."""
    return F.array_min(F.transform(origins, lambda t: F.substring(t, F.lit(2), F.lit(9)).cast("int")))


@query(f"with {decided()} select release_no, doc_id, status from dec")
def ingest_documents_k40(spark, d):
    """Forty releases one after the other through the manifest, fanout 4: the decisions of the bulk form."""
    docs = releases.documents(spark, d, 40)
    return ingest_all(_index(spark, policies.Tiered(4)), docs, list(range(40)))


@query(f"with {_SIX} select release_no, doc_id, status from dec")
def ingest_documents_sequential(spark, d):
    """The manifest-driven run over six releases; its decisions are those of the bulk form."""
    docs = _six(scratch.table(spark, d, "documents").select("doc_id", "text"))
    return ingest_all(_index(spark, policies.Tiered(2)), docs, list(range(6)))


@query(f"with {_SIX} select s as strategy, release_no, count(*) filter (status = 'kept')::bigint as n_final, count(*) filter (status = 'removed_history')::bigint as n_history from dec, (values ('seek'), ('merge'), ('broadcast')) v(s) group by all")
def screen_strategies_agree(spark, d):
    """Search in sorted shards, a join of unpacked keys, and a broadcast release: equal decisions."""
    docs = _six(scratch.table(spark, d, "documents").select("doc_id", "text"))
    out = None
    for strategy in ("seek", "merge", "broadcast"):
        got = ingest_all(_index(spark, policies.Tiered(2)), docs, list(range(6)), strategy)
        part = got.groupBy("release_no").agg(F.count(F.when(F.col("status") == "kept", 1)).alias("n_final"), F.count(F.when(F.col("status") == "removed_history", 1)).alias("n_history"))
        part = part.select(F.lit(strategy).alias("strategy"), "release_no", "n_final", "n_history")
        out = part if out is None else out.union(part)
    return out


@query(f"with {_SIX} select distinct band, key from ik where release_no <> 2")
def withdraw_index_keys(spark, d):
    """The index after six releases at fanout 2 and the withdrawal of a merged one."""
    docs = _six(scratch.table(spark, d, "documents").select("doc_id", "text"))
    index = _index(spark, policies.Tiered(2))
    _committed(index, index.prepare(docs), 6)
    index.withdraw("r2")
    return index.all_keys().select("band", "key").distinct()


_AT = "(values (16, 4, 0, 15), (17, 1, 16, 17), (18, 0, 18, 18), (19, 0, 19, 19)) g(e, level, lo, hi)"


@query(f"with {decided('r20')}, own as (select band, key, min(release_no) as r from ik group by band, key having count(distinct release_no) = 1), v as (select * from (values (3), (16), (18), (19)) x(r)) select 'r' || v.r as tag, g.level::int as level, (select count(*) from (select distinct band, key from ik where release_no between g.lo and g.hi))::bigint as affected_keys, (g.lo < g.hi) as rebuilt, (select count(*) from own where own.r = v.r)::bigint as exclusive_before, 0::bigint as exclusive_left from v join {_AT} on v.r between g.lo and g.hi")
def withdraw_by_level(spark, d):
    """Twenty releases at fanout 2 make segments of levels 4, 1, 0 and the newest: a victim of each is
    withdrawn from the real index, its exclusive keys are looked up there, and the index is rolled back."""
    index = _index(spark, policies.Tiered(2))
    _committed(index, index.prepare(releases.documents(spark, d, 20)), 20)
    before, rows = index.read(), []
    for r in (3, 16, 18, 19):
        done = index.withdraw(f"r{r}")
        own, left = index.exclusive_left(f"r{r}", before)
        rows.append((f"r{r}", done["level"], done["affected_keys"], done["rebuilt"], own, left))
        index.rollback(before["snapshot"])
    return spark.createDataFrame(rows, "tag string, level int, affected_keys long, rebuilt boolean, exclusive_before long, exclusive_left long")


@query(f"with {decided()} select release_no, band, count(distinct key)::bigint as n_keys from ik group by release_no, band")
def commit_segment_sizes(spark, d):
    return screen.internal_keys(_docs(spark, d)[1]).groupBy("release_no", "band").agg(F.countDistinct("key").alias("n_keys"))


_DIGITS = "(values (32, 0, 15, 2), (32, 16, 31, 2), (36, 32, 35, 1), (37, 36, 36, 0), (38, 37, 37, 0), (39, 38, 38, 0), (40, 39, 39, 0)) g(e, lo, hi, level)"


@query(f"with {decided()} select level::int as level, lo::int as first_release, band, count(*)::bigint as n_keys, bit_xor(key) as digest from (select distinct band, level, lo, key from ik join {_DIGITS} on release_no between lo and hi) group by band, level, lo")
def compacted_union_keys(spark, d):
    """The live segments after 40 committed releases at fanout 4, read back: unions of their members."""
    index = _index(spark, policies.Tiered(4))
    _committed(index, index.prepare(releases.documents(spark, d, 40)), 40)
    out = None
    for r in index.live():
        first = min(int(t[1:]) for t in r["origins"])
        part = segments.unpacked(index.segment(r)).select(F.lit(r["level"]).alias("level"), F.lit(first).alias("first_release"), "band", "key")
        out = part if out is None else out.union(part)
    return out.groupBy("level", "first_release", "band").agg(F.count(F.lit(1)).alias("n_keys"), F.bit_xor("key").alias("digest"))


@query(f"with {decided()} select level::int as level, lo::int as first_release, (hi - lo + 1)::int as members, count(*)::bigint as n_keys from (select distinct band, level, lo, hi, key from ik join {_DIGITS} on release_no between lo and hi) group by level, lo, hi")
def compaction_manifest(spark, d):
    """What the manifest says of the same segments."""
    index = _index(spark, policies.Tiered(4))
    _committed(index, index.prepare(releases.documents(spark, d, 40)), 40)
    return index.describe().where("live").select("level", _members("origins").alias("first_release"), F.size("origins").alias("members"), "n_keys")


@query(f"with {_SIX}, one as (select band, key, min(release_no) as r from ik group by band, key having count(distinct release_no) = 1) select r::int as release_no, count(*)::bigint as exclusive_before, 0::bigint as left_after from one group by r")
def victim_exclusive_left(spark, d):
    """Each of six releases withdrawn from the index in turn: its exclusive keys, and those still found there."""
    docs = _six(scratch.table(spark, d, "documents").select("doc_id", "text"))
    index = _index(spark, policies.Tiered(2))
    _committed(index, index.prepare(docs), 6)
    before, rows = index.read(), []
    for r in range(6):
        index.withdraw(f"r{r}")
        rows.append((r, *index.exclusive_left(f"r{r}", before)))
        index.rollback(before["snapshot"])
    return spark.createDataFrame(rows, "release_no int, exclusive_before long, left_after long")


@query(f"with {decided()}, fs2 as (select band, key, min(release_no) as f from ik where release_no <> 2 group by band, key), h2 as (select distinct doc_id from ik join fs2 using (band, key) where f < release_no) select doc_id from dec where status = 'removed_history' and doc_id not in (select doc_id from h2)")
def counterfactual_restored(spark, d):
    """Documents that only release 2 had removed."""
    docs, k = _docs(spark, d)
    removed = screen.bulk(docs, k).where("status = 'removed_history'").select("doc_id")
    without = screen.bulk(docs.where("release_no <> 2"), k.where("release_no <> 2")).where("status = 'kept'").select("doc_id")
    return removed.join(without, "doc_id", "left_semi")


_THREE = decided("r3", "(select *, (doc_id % 3)::int as r3 from base)")


@query(f"with {_THREE}, fin as (select ik.* from ik join dec using (doc_id) where status = 'kept') select 'final' as policy, release_no, count(distinct (band, key))::bigint as missing_keys from ik where not exists (select 1 from fin where fin.band = ik.band and fin.key = ik.key and fin.release_no = ik.release_no) group by release_no")
def commit_final_ablation(spark, d):
    """Keys a release loses if only the survivors of history are committed."""
    docs = scratch.table(spark, d, "documents").select("doc_id", "text").withColumn("release_no", F.pmod("doc_id", F.lit(3)).cast("int"))
    k = scratch.written(keys.long_keys(docs, C), "keys")
    ik = screen.internal_keys(k)
    kept = screen.bulk(docs, k).where("status = 'kept'").select("doc_id")
    final = ik.join(kept, "doc_id", "left_semi").select("release_no", "band", "key").distinct()
    lost = ik.select("release_no", "band", "key").distinct().join(final, ["release_no", "band", "key"], "left_anti")
    return lost.groupBy("release_no").agg(F.count(F.lit(1)).alias("missing_keys")).select(F.lit("final").alias("policy"), "release_no", "missing_keys")


@query("select p::int as n_protected, ((11 - p) % 4 + (11 - p) // 4 % 4 + 1 + p)::bigint as live_segments from (values (0), (1), (3)) t(p)")
def protected_fanout(spark, d):
    """Live segments after 12 committed releases of keys at fanout 4, some of them protected."""
    stream = _stream(spark, d, 12)
    rows = []
    for n in (0, 1, 3):
        index = _index(spark, policies.Tiered(4), STREAM)
        ready = index.prepare_keys(stream)
        rows.append((n, len(_committed(index, ready, 12, frozenset(range(n))).live())))
    return spark.createDataFrame(rows, "n_protected int, live_segments long")


_CANON = f"with {KEYED}, q as (select b.doc_id, coalesce(max(l.quality), -1) as quality from base b left join labels l using (doc_id) group by b.doc_id), win as (select dk.doc_id, first_value(dk.doc_id) over (partition by band, key order by q.quality desc, dk.doc_id) as winner from dk join q using (doc_id)) select doc_id from base where doc_id not in (select doc_id from win where winner <> doc_id)"


@query(_CANON)
def canonical_by_quality(spark, d):
    """Survivors when the best label, then the least doc_id, represents a group."""
    docs, k = _docs(spark, d)
    best = spark.read.parquet(f"{d}/labels.parquet").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    ranked = k.join(best, "doc_id", "left").withColumn("rank", F.struct(-F.coalesce("quality", F.lit(-1)), "doc_id"))
    winner = ranked.groupBy("band", "key").agg(F.min("rank").alias("top"))
    lost = ranked.join(winner, ["band", "key"]).where(F.col("rank") != F.col("top")).select("doc_id").distinct()
    return docs.join(lost, "doc_id", "left_anti").select("doc_id")


# baselines


@query(f"with {decided('r20')}, per as (select release_no, count(*) as n from rk group by release_no) select p.release_no, (sum(n) over (order by p.release_no))::bigint as touches, (select count(*) from dec where dec.release_no = p.release_no and status = 'kept')::bigint as n_final from per p")
def snapshot_rebuild_decisions(spark, d):
    docs, k = _docs(spark, d, 20)
    return baselines.snapshot_rebuild(docs, k, 20)


@query(f"with {KEYED}, pairs as (select distinct x.doc_id, y.doc_id as match_id from dk x join dk y using (band, key) where y.doc_id < x.doc_id), est as (select p.doc_id, match_id, round(avg((s.v = t.v)::int), 6) as est from pairs p join sig s on s.doc_id = p.doc_id join sig t on t.doc_id = match_id and s.pos = t.pos group by all) select doc_id, match_id, est from est where est >= 0.5 qualify row_number() over (partition by doc_id order by est desc, match_id) = 1")
def served_topk(spark, d):
    return baselines.served_topk(scratch.table(spark, d, "documents"), C)


@query(f"with recursive {KEYED}, e as (select distinct x.doc_id as u, y.doc_id as v from dk x join dk y using (band, key) where x.doc_id <> y.doc_id), reach(doc_id, l) as (select doc_id, doc_id from (select distinct doc_id from dk) union select e.v, r.l from reach r join e on e.u = r.doc_id where r.l < e.v) select doc_id, min(l) as label from reach group by doc_id")
def components_labels(spark, d):
    return baselines.transitive(_docs(spark, d)[1])


_STREAM = """
st as (
  select (l_orderkey % 40)::int as release_no, l_partkey,
         ('0x' || substr(md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity::bigint, round(l_extendedprice * 100)::bigint, strftime(l_shipdate, '%Y-%m-%d'))), 1, 15))::bigint as rid
  from lineitem),
ks as (
  select release_no, rid, rid % 10 < 3 as pooled, 0 as band,
         ('0x' || substr(md5(case when rid % 10 < 3 then concat_ws('|', 'p', 0, l_partkey % 500) else concat_ws('|', 'n', 0, rid) end), 1, 15))::bigint as key
  from st)"""


@query(f"with {_STREAM} select release_no, count(*)::bigint as n, count(*) filter (pooled)::bigint as n_pooled, count(distinct key)::bigint as n_distinct from ks group by release_no")
def keystream_lineitem(spark, d):
    ks = releases.key_stream(spark, d)
    return ks.groupBy("release_no").agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("pooled"), 1)).alias("n_pooled"), F.countDistinct("key").alias("n_distinct"))


#: The index of the key stream: one band of 60-bit keys.
STREAM = DedupConfig(p=4, bands=1, family="portable31", shard_bits=4, buckets=4)


def _stream(spark, d, k: int) -> DataFrame:
    """release_no, doc_id, band, key of the stream over k releases."""
    found = releases.key_stream(spark, d, k).select("release_no", F.col("rid").alias("doc_id"), "band", "key")
    return scratch.written(found, "stream")


def _bloom_sql(fp: float) -> str:
    bits, k = costmodel.bloom_bits(3000, fp)
    pos = f"(('0x' || substr(md5(key::varchar), 1, 8))::bigint + i * (('0x' || substr(md5(key::varchar), 9, 8))::bigint + 1)) % {bits}"
    return f"""select s.step::int as step,
 (select count(distinct key) from ins where release_no <= s.step)::bigint as n_inserted,
 (select count(*) from asked where hit_at <= s.step)::bigint as fp, (select count(*) from asked)::bigint as holdout
from (values (4), (9), (19), (29)) s(step)""", f"""
ins as (select * from ks where release_no < 30),
bt as (select {pos} as bit, min(release_no) as set_at from ins, range(0, {k}) g(i) group by 1),
asked as (select rid, max(coalesce(set_at, 1073741824)) as hit_at from (select rid, {pos} as bit from ks, range(0, {k}) g(i) where release_no >= 30 and not pooled) q left join bt using (bit) group by rid)"""


_BLOOM = {fp: _bloom_sql(fp) for fp in (0.01, 0.001)}


@query(f"with {_STREAM}, {_BLOOM[0.01][1]} {_BLOOM[0.01][0]}")
def bloom_fpr(spark, d):
    """False positives of never-ingested rows as the filter passes its capacity of 3000 keys."""
    ks = releases.key_stream(spark, d)
    return baselines.bloom_fpr(ks.where("release_no < 30"), 3000, 0.01, [4, 9, 19, 29], ks.where("release_no >= 30 and not pooled"))


@query(f"with {_STREAM}, {_BLOOM[0.001][1]} {_BLOOM[0.001][0]}")
def bloom_fpr_strict(spark, d):
    ks = releases.key_stream(spark, d)
    return baselines.bloom_fpr(ks.where("release_no < 30"), 3000, 0.001, [4, 9, 19, 29], ks.where("release_no >= 30 and not pooled"))


def _bloom_quarter_sql(fp: float) -> str:
    """As _bloom_sql, but for a filter made for a quarter of the keys that are inserted."""
    k = costmodel.bloom_bits(1_000_000, fp)[1]
    pos = "(('0x' || substr(md5(key::varchar), 1, 8))::bigint + i * (('0x' || substr(md5(key::varchar), 9, 8))::bigint + 1)) % (select bits from cap)"
    return f"""with {_STREAM},
ins as (select * from ks where release_no < 30),
cap as (select ceil(-n0 * ln({fp}) / (ln(2) * ln(2)))::bigint as bits from (select greatest(1, count(distinct key) // 4) as n0 from ins)),
bt as (select {pos} as bit, min(release_no) as set_at from ins, range(0, {k}) g(i) group by 1),
asked as (select rid, max(coalesce(set_at, 1073741824)) as hit_at from (select rid, {pos} as bit from ks, range(0, {k}) g(i) where release_no >= 30 and not pooled) q left join bt using (bit) group by rid)
select s.step::int as step,
 (select count(distinct key) from ins where release_no <= s.step)::bigint as n_inserted,
 (select count(*) from asked where hit_at <= s.step)::bigint as fp, (select count(*) from asked)::bigint as holdout
from (values (1), (4), (9), (19), (29)) s(step)"""


def _bloom_quarter(spark, d, fp: float) -> DataFrame:
    ks = releases.key_stream(spark, d)
    stream = ks.where("release_no < 30")
    n0 = max(1, stream.select("key").distinct().count() // 4)
    return baselines.bloom_fpr(stream, n0, fp, [1, 4, 9, 19, 29], ks.where("release_no >= 30 and not pooled"))


@query(_bloom_quarter_sql(0.01))
def bloom_fpr_quarter(spark, d):
    """As bloom_fpr, the capacity a quarter of the stream's keys: steps before and after it on any table."""
    return _bloom_quarter(spark, d, 0.01)


@query(_bloom_quarter_sql(0.001))
def bloom_fpr_quarter_strict(spark, d):
    return _bloom_quarter(spark, d, 0.001)


def _bloom_decisions_sql(fp: float) -> str:
    """CTEs ending in bd (doc_id): documents that filters made for a quarter of each band's keys call known."""
    k = costmodel.bloom_bits(1_000_000, fp)[1]
    pos = "(('0x' || substr(md5(key::varchar), 1, 8))::bigint + i * (('0x' || substr(md5(key::varchar), 9, 8))::bigint + 1)) % bits"
    return f"""cap as (select ceil(-n0 * ln({fp}) / (ln(2) * ln(2)))::bigint as bits from (select greatest(1, count(*) // {4 * C.bands}) as n0 from (select distinct band, key from ik))),
pk as (select release_no, doc_id, band, key, {pos} as bit from ik, cap, range(0, {k}) g(i)),
bt as (select band, bit, min(release_no) as set_at from pk group by all),
bh as (select release_no, doc_id, band, max(set_at) as all_set from pk join bt using (band, bit) group by all),
bd as (select distinct doc_id from bh where all_set < release_no)"""


@query(f"with {decided()}, {_bloom_decisions_sql(0.01)} select b.doc_id, (case when l.doc_id is not null then 'removed_within' when bd.doc_id is not null then 'removed_history' else 'kept' end) as status from base b left join lost l using (doc_id) left join bd using (doc_id)")
def bloom_decisions(spark, d):
    """Decisions on all documents if a Bloom filter per band, made for a quarter of its keys, held the history."""
    docs, k = _docs(spark, d)
    known = baselines.bloom_decisions(screen.internal_keys(k), 0.01).withColumn("hit", F.lit(True))
    within = screen.within_release(k).select("doc_id", F.lit(True).alias("lost"))
    status = F.when(F.col("lost"), "removed_within").when(F.col("hit"), "removed_history").otherwise("kept")
    return docs.select("doc_id").join(within, "doc_id", "left").join(known, "doc_id", "left").select("doc_id", status.alias("status"))


@query(f"with {decided()}, {_bloom_decisions_sql(0.01)}, truth as (select doc_id, status <> 'kept' as gone from dec), sys as (select 'segmented_index' as system, doc_id, gone as flag from truth union all select 'bloom_bands', t.doc_id, (bd.doc_id is not null or l.doc_id is not null) from truth t left join bd using (doc_id) left join lost l using (doc_id)) select system, count(*)::bigint as n, count(*) filter (flag and not gone)::bigint as fp, count(*) filter (not flag and gone)::bigint as fn from sys join truth using (doc_id) group by system")
def fidelity_vs_oracle(spark, d):
    """False positives and negatives of systems against the exact decisions: the index by its own segments
    and manifest, the Bloom bands beyond their capacity."""
    docs, k = _docs(spark, d)
    truth = scratch.written(screen.bulk(docs, k).select("doc_id", (F.col("status") != "kept").alias("gone")), "truth")
    own = ingest_all(_index(spark, policies.Tiered(4)), docs, list(range(40))).select(F.lit("segmented_index").alias("system"), "doc_id", (F.col("status") != "kept").alias("flag"))
    lost = screen.within_release(k).select("doc_id").union(baselines.bloom_decisions(screen.internal_keys(k), 0.01)).distinct().withColumn("flag", F.lit(True))
    bloom = docs.select("doc_id").join(lost, "doc_id", "left").select(F.lit("bloom_bands").alias("system"), "doc_id", F.coalesce("flag", F.lit(False)).alias("flag"))
    both = own.union(bloom).join(truth, "doc_id")
    count = lambda c: F.count(F.when(c, 1))
    return both.groupBy("system").agg(F.count(F.lit(1)).alias("n"), count(F.col("flag") & ~F.col("gone")).alias("fp"), count(~F.col("flag") & F.col("gone")).alias("fn"))


_NEAR = """,
st as (select doc_id, list_sort(list(s)) as ids, count(*) as n from sh group by doc_id),
cut as (select doc_id, ids, n // 19 as q from st where n >= 19),
lft as (select doc_id, 2 * doc_id as id, ids[1:19 * q] as ids, q from cut),
rgt as (select doc_id, 2 * doc_id + 1 as id, list_concat(ids[1:18 * q], list_transform(range(0, q), lambda i: 'new ' || doc_id || ' ' || i)) as ids, q from cut),
two as (select id, unnest(ids) as s from lft union all select id, unnest(ids) from rgt)"""


@query(f"with {WORDS}{_NEAR}, coef(pos, a, b) as (values {_COEF}), hs as (select id, ('0x' || substr(md5(s), 1, 8))::bigint % {PRIME} as h from two), sig as (select id, pos, min((a::bigint * h + b) % {PRIME})::bigint as v from hs cross join coef group by id, pos), dk as (select id, (pos // {C.rows})::int as band, md5(string_agg(v::varchar, ',' order by pos)) as key from sig group by id, pos // {C.rows}), hit as (select distinct x.id // 2 as doc_id from dk x join dk y on x.band = y.band and x.key = y.key and x.id + 1 = y.id and x.id % 2 = 0) select 0.9::double as j, count(*)::bigint as pairs, count(hit.doc_id)::bigint as found, round({costmodel.lsh_probability(0.9, C.bands, C.rows)!r}, 6)::double as expected from cut left join hit using (doc_id)")
def controlled_similarity(spark, d):
    """Pairs of Jaccard 0.9 exactly (18q of 19q shingles shared, q new ones) made from each document of 19
    shingles or more: how many share a band key, beside the closed form."""
    sets = _shingles(spark, d).groupBy("doc_id").agg(F.sort_array(F.collect_list("s")).alias("ids")).where(F.size("ids") >= 19)
    q = F.expr("int(size(ids) div 19)")
    new = F.transform(F.sequence(F.lit(0), F.col("q") - 1), lambda i: F.concat(F.lit("new "), F.col("doc_id").cast("string"), F.lit(" "), i.cast("string")))
    cut = sets.withColumn("q", q)
    left = cut.select((2 * F.col("doc_id")).alias("id"), F.slice("ids", F.lit(1), 19 * F.col("q")).alias("ids"))
    right = cut.select((2 * F.col("doc_id") + 1).alias("id"), F.concat(F.slice("ids", F.lit(1), 18 * F.col("q")), new).alias("ids"))
    band = scratch.written(keys.keys_of_sets(left.union(right), C), "near-keys")
    met = band.where("id % 2 = 0").withColumn("doc_id", F.expr("id div 2")).join(band.where("id % 2 = 1").withColumn("doc_id", F.expr("id div 2")).drop("id"), ["doc_id", "band", "key"]).select("doc_id").distinct().withColumn("hit", F.lit(1))
    pairs = band.select(F.expr("id div 2").alias("doc_id")).distinct().join(met, "doc_id", "left")
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.count("hit").alias("found")).select(F.lit(0.9).alias("j"), "pairs", "found", F.lit(round(costmodel.lsh_probability(0.9, C.bands, C.rows), 6)).alias("expected"))


@query()
def resident_table_decisions(spark, d):
    """The classical in-memory table over the releases in order: doc_id, kept, bytes so far, stopped at the cap."""
    docs, k = _docs(spark, d)
    return baselines.resident_decisions(docs, k, cap_bytes=1 << 30)


@query("with q as (select vec_id, embedding from embeddings where vec_id % 100 = 0), s as (select q.vec_id as q, e.vec_id, round(list_cosine_similarity(q.embedding::double[], e.embedding::double[]), 6) as c from q cross join embeddings e where e.vec_id <> q.vec_id), r as (select *, row_number() over (partition by q order by c desc, vec_id) as rank from s) select q, rank::int as rank, vec_id from r where rank <= 10")
def knn_exact(spark, d):
    """Ten nearest by cosine; the queries are one vector in a hundred, against all."""
    e = spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    q = F.broadcast(e.where("vec_id % 100 = 0").select(F.col("vec_id").alias("q"), F.col("x").alias("y")))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    cosine = F.round(dot("x", "y") / F.sqrt(dot("x", "x") * dot("y", "y")), 6)
    near = e.join(q, F.col("vec_id") != F.col("q")).select("q", "vec_id", cosine.alias("c"))
    return near.withColumn("rank", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("c"), "vec_id"))).where("rank <= 10").select("q", "rank", "vec_id")


# measures


@query(f"with {decided()} select release_no, count(*)::bigint as n_in, count(*) filter (status <> 'removed_within')::bigint as n_internal, count(*) filter (status = 'kept')::bigint as n_final, round(1 - count(*) filter (status = 'kept') / count(*), 6)::double as removal_rate from dec group by release_no")
def removal_rate_by_release(spark, d):
    n = F.count(F.lit(1))
    kept = F.count(F.when(F.col("status") == "kept", 1))
    return screen.bulk(*_docs(spark, d)).groupBy("release_no").agg(n.alias("n_in"), F.count(F.when(F.col("status") != "removed_within", 1)).alias("n_internal"), kept.alias("n_final"), F.round(1 - kept / n, 6).alias("removal_rate"))


def _merged_sql(t: int, k: int) -> str:
    """Keys written by the merges of k releases at fanout t, each level a union of t^level releases."""
    parts, n, level = [], k - 1, 1
    while t**level <= n:
        parts.append(f"(select count(*) from (select distinct release_no // {t**level}, key from ks where release_no < {t**level * (n // t**level)}))")
        level += 1
    return " + ".join(parts) or "0"


def _live_sql(t: int, k: int) -> tuple[int, str]:
    """Number of live segments and the keys in them after k releases."""
    n, lo, segs = k - 1, 0, []
    level = 0
    while t ** (level + 1) <= n:
        level += 1
    for at in range(level, -1, -1):
        for _ in range((n - lo) // t**at):
            segs.append((lo, lo + t**at - 1))
            lo += t**at
    segs.append((k - 1, k - 1))
    return len(segs), " + ".join(f"(select count(distinct key) from ks where release_no between {a} and {b})" for a, b in segs)


_AMPLIFIED = " union all ".join(f"select {t} as fanout, ingested, ({_merged_sql(t, 40)})::bigint as rewritten, {_live_sql(t, 40)[0]}::bigint as live_segments, ({_live_sql(t, 40)[1]})::bigint as live_keys from n" for t in (2, 4, 16))


@query(f"with {_STREAM}, n as (select count(*)::bigint as ingested from (select distinct release_no, key from ks)), w as ({_AMPLIFIED}) select fanout::int as fanout, ingested, rewritten, round(rewritten / ingested, 6)::double as amplification, live_segments, live_keys from w")
def write_amplification(spark, d):
    """Forty releases of the key stream committed and merged at three fanouts; counts from the manifest's runs."""
    stream, rows = _stream(spark, d, 40), []
    for t in (2, 4, 16):
        index = _index(spark, policies.Tiered(t), STREAM)
        _committed(index, index.prepare_keys(stream), 40)
        runs = index.read()["runs"]
        ingested, again = (sum(r["written"] for r in runs if r["kind"] == kind) for kind in ("admit", "compact"))
        rows.append((t, ingested, again, round(again / ingested, 6), len(index.live()), sum(r["n_keys"] for r in index.live())))
    return spark.createDataFrame(rows, "fanout int, ingested long, rewritten long, amplification double, live_segments long, live_keys long")


@query("with g as (select k::bigint as k from range(2, 41) g(k)) select k::int as release_no, (case when k = 2 then 1 else (k - 2) % 4 + ((k - 2) // 4) % 4 + ((k - 2) // 16) % 4 + 1 end)::bigint as fanout from g union all select 1, 0")
def fanout_by_release(spark, d):
    """Segments that each release of the key stream was to be searched in, as the manifest recorded them."""
    index = _index(spark, policies.Tiered(4), STREAM)
    _committed(index, index.prepare_keys(_stream(spark, d, 40)), 40)
    admitted = index.runs().where("kind = 'admit'")
    return admitted.select((F.substring("tag", 2, 9).cast("int") + 1).alias("release_no"), F.col("fanout").cast("long"))


@query(f"with {decided()}, n as (select count(*) as docs from documents), k as (select count(*) as n from (select distinct release_no, band, key from ik)) select kind, (k.n * 8 * f)::bigint as bytes, docs::bigint as docs, round(k.n * 8 * f / docs, 6)::double as bytes_per_doc from k, n, (values ('index', 1), ('with_sidecar', 2)) v(kind, f)")
def bytes_per_doc(spark, d):
    """Bytes of the packed keys as stored, without and with the sidecars that merges leave beside them."""
    docs = releases.documents(spark, d, 40)
    ready = _index(spark).prepare(docs)
    n, held = docs.count(), None
    for path in ready.sidecars.values():
        part = segments.load(spark, path, C).select(F.length("keys").cast("long").alias("bytes"))
        held = part if held is None else held.union(part)
    m = held.agg(F.sum("bytes")).first()[0]
    return spark.createDataFrame([(kind, m * f, n, round(m * f / n, 6)) for kind, f in (("index", 1), ("with_sidecar", 2))], "kind string, bytes long, docs long, bytes_per_doc double")


@query(f"with {decided()}, sh0 as (select (key % 16)::int as shard, count(*)::bigint as n_keys, bit_xor(key) as digest from (select distinct band, key from ik) group by 1) select * from sh0")
def state_digest(spark, d):
    return screen.internal_keys(_docs(spark, d)[1]).select("band", "key").distinct().groupBy(F.pmod("key", F.lit(16)).cast("int").alias("shard")).agg(F.count(F.lit(1)).alias("n_keys"), F.bit_xor("key").alias("digest"))


_KEPT = " union all ".join(
    f"select '{name}' as policy, {count} as live_segments, ({keys_})::bigint as total_keys"
    for name, count, keys_ in (
        ("tiered", _live_sql(4, 40)[0], _live_sql(4, 40)[1]),
        ("frozen_cap", 13, "(select count(*) from (select distinct release_no // 4, key from ks where release_no < 36)) + (select count(*) from (select distinct release_no, key from ks where release_no >= 36))"),
        ("never", 40, "select count(*) from (select distinct release_no, key from ks)"),
        ("folded", 1, "select count(distinct key) from ks"),
    )
)


@query(f"with {_STREAM}, k as ({_KEPT}), u as (select count(distinct key)::bigint as distinct_keys from ks) select policy, live_segments::bigint as live_segments, total_keys, distinct_keys, round(1 - distinct_keys / total_keys, 6)::double as dup_share from k, u")
def frozen_duplicates(spark, d):
    """Keys held twice by the segments of four selectors over 40 releases: tiered; frozen once a segment
    passes twice a release's size; never merged; that, folded into one at the end."""
    stream, rows = _stream(spark, d, 40), []
    size = stream.count() // 40
    for name, policy in (("tiered", policies.Tiered(4)), ("frozen_cap", policies.FrozenCap(2 * size)), ("never", policies.Never()), ("folded", policies.Never())):
        index = _index(spark, policy, STREAM)
        _committed(index, index.prepare_keys(stream), 40)
        if name == "folded":
            index.fold()
        total, uniq = sum(r["n_keys"] for r in index.live()), index.union().agg(F.sum("n").cast("long")).first()[0]
        rows.append((name, len(index.live()), total, uniq, round(1 - uniq / total, 6)))
    return spark.createDataFrame(rows, "policy string, live_segments long, total_keys long, distinct_keys long, dup_share double")


_ALL_PAIRS = ", sz as (select doc_id, count(*) as n from sh group by doc_id), pr as (select x.doc_id as a, y.doc_id as b, count(*)::bigint as inter from sh x join sh y using (s) where x.doc_id < y.doc_id group by all), jac as (select a, b, inter, p.n + q.n - inter as uni from pr join sz p on p.doc_id = a join sz q on q.doc_id = b)"


@query(f"with {KEYED}{_CAND}{_ALL_PAIRS} select (inter * 10 // uni)::int as bucket, count(*)::bigint as pairs, count(cand.a)::bigint as found from jac left join cand using (a, b) where inter * 10 >= uni group by 1")
def lsh_recall_vs_jaccard(spark, d):
    """Pairs of documents by tenths of Jaccard, and how many of them share a band key. A pair of
    representatives counts as often as their members pair; pairs within a class are counted from its size."""
    _, found, chosen = _sets(spark, d)
    met = _candidates(_chosen_keys(spark, d, found)).select("a", "b", F.lit(1).alias("hit"))
    size = similarity.members(found)
    pairs = similarity.pairs_above(chosen, 1, 10).join(met, ["a", "b"], "left")
    weighed = pairs.join(size.toDF("a", "ma"), "a").join(size.toDF("b", "mb"), "b").withColumn("w", F.col("ma") * F.col("mb"))
    between = weighed.select(F.expr("cast(inter * 10 div uni as int)").alias("bucket"), "w", F.when(F.col("hit") == 1, F.col("w")).otherwise(0).alias("f"))
    within = size.where("members > 1").select(F.lit(10).alias("bucket"), F.expr("members * (members - 1) div 2").alias("w"))
    return between.union(within.select("bucket", "w", "w")).groupBy("bucket").agg(F.sum("w").alias("pairs"), F.sum("f").alias("found"))


@query("select system, n::bigint as n, round(n * b / 1073741824.0, 6)::double as gib from (values ('segmented_index', 128.0), ('with_sidecar', 256.0), ('resident_table', 6500.0), ('graph_substrate', 1536.0)) s(system, b), (values (1000000), (10000000), (100000000), (1000000000)) v(n)")
def memory_model(spark, d):
    per = {"segmented_index": 128, "with_sidecar": 256, "resident_table": 6500, "graph_substrate": baselines.graph_bytes(1)}
    return spark.createDataFrame([(s, n, round(n * b / 2**30, 6)) for s, b in per.items() for n in (10**6, 10**7, 10**8, 10**9)], "system string, n long, gib double")


@query("select rho::double as rho, best_fanout::double as best_fanout from (values (0.5, 2.156), (1.0, 2.718), (2.0, 3.591), (5.0, 5.572)) t(rho, best_fanout)")
def fanout_model(spark, d):
    """The optimum fan-out by the closed form, for given cost ratios."""
    import math

    rows = [(r, round(math.exp(1 + costmodel.lambert_w0((r - 1) / math.e)), 3)) for r in (0.5, 1.0, 2.0, 5.0)]
    return spark.createDataFrame([(float(a), float(b)) for a, b in rows], "rho double, best_fanout double")


@query(f"with {_STREAM}, h as (select key, release_no from ks where release_no < 39), a as (select distinct key from ks where release_no = 39) select s::int as s, (select count(*) from a)::bigint as asked, (select count(*) from a where exists (select 1 from h where h.key = a.key))::bigint as matched, (select count(*) from (select distinct release_no % s, key from h))::bigint as held from (values (1), (4), (16), (64)) v(s)")
def screen_vs_segments(spark, d):
    """The last release searched in the same history cut into 1, 4, 16 and 64 segments: equal answers.

    The history's 39 releases fill at most 39 of 64 segments.
    """
    stream = _stream(spark, d, 40)
    index, rows = _index(spark, policies.Never(), STREAM), []
    own = index.prepare_keys(stream.where("release_no = 39"))
    asked = segments.load(spark, own.sidecars[39], STREAM)
    for s in (1, 4, 16, 64):
        cut = index.prepare_keys(stream.where("release_no < 39").withColumn("release_no", F.pmod("release_no", F.lit(s)).cast("int")))
        hits = None
        for path in cut.sidecars.values():
            part = segments.probe(asked, segments.load(spark, path, STREAM), "merge")
            hits = part if hits is None else hits.union(part)
        rows.append((s, own.n_keys[39], hits.distinct().count(), sum(cut.n_keys.values())))
    return spark.createDataFrame(rows, "s int, asked long, matched long, held long")


# workloads


@query(f"with {WORDS}, bw as (select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w from benchmark), bs as (select item_id, unnest(list_distinct(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end)) as s from bw), bn as (select item_id, count(*) as n from bs group by item_id), m as (select item_id, doc_id, count(*) as c from bs join sh using (s) group by all) select item_id, doc_id, round(c / n, 6)::double as share from m join bn using (item_id) where c / n >= 0.5")
def contamination_screen(spark, d):
    """Share of a benchmark item's shingles that a document holds."""
    sh = _shingles(spark, d)
    items = spark.read.parquet(f"{d}/benchmark.parquet").select(F.col("item_id").alias("doc_id"), "text")
    words = F.filter(F.split(keys.normalise(F.col("text")), " "), lambda w: w != "")
    split = items.select("doc_id", words.alias("w")).where(F.size("w") > 0)
    n = F.size("w")
    made = F.when(n < C.k, F.array(F.array_join("w", " "))).otherwise(F.transform(F.sequence(F.lit(1), F.greatest(n - (C.k - 1), F.lit(1))), lambda i: F.array_join(F.slice("w", i, C.k), " ")))
    bs = split.select(F.col("doc_id").alias("item_id"), F.explode(F.array_distinct(made)).alias("s"))
    size = bs.groupBy("item_id").agg(F.count(F.lit(1)).alias("n"))
    met = bs.join(sh, "s").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("c")).join(size, "item_id")
    return met.where(F.col("c") / F.col("n") >= 0.5).select("item_id", "doc_id", F.round(F.col("c") / F.col("n"), 6).alias("share"))


@query(f"with {decided('r20')}, tox as (select b.source, b.r20, avg(l.toxic) as share from base b join labels l using (doc_id) group by all), v as (select source, r20, share from tox order by share desc, source limit 1) select v.source, round(v.share, 6)::double as toxic_share, (select count(*) from (select band, key from ik group by band, key having count(distinct release_no) = 1 and min(release_no) = v.r20))::bigint as exclusive_keys from v")
def withdraw_by_label(spark, d):
    """The source with the largest share of toxic labels as victim, and the keys only it has."""
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "source")
    share = docs.join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").groupBy("source", F.pmod("doc_id", F.lit(20)).cast("int").alias("release_no")).agg(F.avg("toxic").alias("share"))
    victim = share.orderBy(F.desc("share"), "source").limit(1)
    owners = screen.internal_keys(_docs(spark, d, 20)[1]).groupBy("band", "key").agg(F.min("release_no").alias("release_no"), F.countDistinct("release_no").alias("n")).where("n = 1")
    counted = owners.groupBy("release_no").agg(F.count(F.lit(1)).alias("exclusive_keys"))
    return victim.join(counted, "release_no", "left").select("source", F.round("share", 6).alias("toxic_share"), F.coalesce("exclusive_keys", F.lit(0)).alias("exclusive_keys"))


def _dedup_units(units: DataFrame) -> DataFrame:
    """units: release_no, doc_id, text -> doc_id, status."""
    k = scratch.written(keys.long_keys(units, C), "keys")
    return screen.bulk(units, k).select("doc_id", "status")


@query()
def pages_dedup(spark, d):
    """Pages' extracted text, released by page_id % 10."""
    html = spark.read.parquet(f"{d}/pages.parquet").select("page_id", "html")
    bare = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</\1>", " "), r"<[^>]*>", " ")
    units = scratch.spread(html.select(F.col("page_id").alias("doc_id"), F.pmod("page_id", F.lit(10)).cast("int").alias("release_no"), bare.alias("text")))
    return _dedup_units(units).withColumnRenamed("doc_id", "page_id")


@query()
def conversation_dedup(spark, d):
    """Turns as units, released by conv_id % 10; a unit's identity is (conv_id, turn)."""
    turns = spark.read.parquet(f"{d}/conversations.parquet")
    units = scratch.spread(turns.select(F.struct("conv_id", "turn").alias("doc_id"), F.pmod("conv_id", F.lit(10)).cast("int").alias("release_no"), "text"))
    return _dedup_units(units).select("doc_id.conv_id", "doc_id.turn", "status")


#: Places where an ingestion can be cut off.
FAULTS = ("keys written", "removed written", "internal written", "sidecar written", "decisions written", "before swap", "swapped", "merged", "before merge swap")


@query()
def retry_digest(spark, d):
    """Five releases at fanout 2; the last one crashes at each point in turn and is ingested again: per
    point whether the SHA-256 of every band and the decisions are those of an undisturbed run."""
    docs = scratch.table(spark, d, "documents").select("doc_id", "text").withColumn("release_no", F.pmod("doc_id", F.lit(5)).cast("int"))
    index = _index(spark, policies.Tiered(2))
    _committed(index, index.prepare(docs.where("release_no < 4")), 4)
    start, last = index.read()["snapshot"], docs.where("release_no = 4").select("doc_id", "text")

    def outcome() -> tuple:
        got = index.ingest(last, "r4").groupBy("status").agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("doc_id"))).collect()
        return index.digest(), sorted(map(tuple, got))

    want, rows = outcome(), []
    for point in FAULTS:
        index.rollback(start)

        def crash(here: str, point=point) -> None:
            if here == point:
                raise RuntimeError(point)

        try:
            index.ingest(last, "r4", fault=crash)
            crashed = False
        except RuntimeError:
            crashed = True
        rows.append((point, crashed, outcome() == want))
    return spark.createDataFrame(rows, "point string, crashed boolean, equal boolean")


@query()
def ml_minhash_pairs(spark, d):
    """Pairs between representatives of equal word sets; further members at distance 0."""
    return baselines.ml_minhash(scratch.table(spark, d, "documents").select("doc_id", "text"))

