"""The hand example, the planner, the cost model and the manifest's lifecycle."""

import math

import pytest

from segdedup import baselines, costmodel, keys, policies, screen, segments, streaming
from segdedup.config import DedupConfig
from segdedup.index import Conflict, Index, ingest_all
from segdedup.manifest import Manifest

SMALL = DedupConfig(p=32, bands=8, family="portable31")
WORDS = "one two three four five six seven eight nine ten eleven twelve".split()


def test_hand_chain(spark):
    """r0: a-b share band 0, b-c band 1; key 20 goes with b, so d survives; e removes f."""
    rows = [(0, 1, 0, 1), (0, 1, 1, 10), (0, 2, 0, 1), (0, 2, 1, 20), (0, 3, 0, 2), (0, 3, 1, 20), (1, 4, 0, 3), (1, 4, 1, 20), (1, 5, 0, 4), (1, 5, 1, 40), (2, 6, 0, 4), (2, 6, 1, 50)]
    k = spark.createDataFrame(rows, "release_no int, doc_id long, band int, key long")
    got = {r.doc_id: r.status for r in screen.bulk(k.select("release_no", "doc_id").distinct(), k).collect()}
    assert got == {1: "kept", 2: "removed_within", 3: "removed_within", 4: "kept", 5: "kept", 6: "removed_history"}


@pytest.mark.parametrize("t", [2, 3, 4, 8, 16])
@pytest.mark.parametrize("k", [40, 64])
def test_counters(t, k):
    step, flat = policies.run(policies.Tiered(t), k), policies.run(policies.Tiered(t, coalesce=True), k)
    assert step["written"] == costmodel.rewritten(k, t) and flat["written"] == costmodel.rewritten(k, t, coalesce=True)
    assert len(step["live"]) == costmodel.live_segments(k, t) and sum(step["fanout"]) == costmodel.total_fanout(k, t)


def test_cost_model():
    for rho, best in ((0.5, 2.156), (1.0, 2.718), (2.0, 3.591), (5.0, 5.572)):
        assert abs(math.exp(1 + costmodel.lambert_w0((rho - 1) / math.e)) - best) < 1e-3
    assert abs(costmodel.residual_bound(1e9) - 8.7e-10) < 1e-11
    assert len(policies.run(policies.Never(), 10)["live"]) == 10 and len(policies.run(policies.FoldAll(), 10)["live"]) == 2
    assert baselines.graph_bytes(1) == 1536
    with pytest.raises(ValueError):
        DedupConfig(p=10, bands=3)


def test_lifecycle(spark, tmp_path):
    """Sequential equals bulk; retry keeps the state; withdrawal is the union of the others."""
    texts = [(i, None if i == 5 else "" if i == 6 else " ".join(WORDS[j % 12] + str(i % 4) for j in range(8))) for i in range(12)]
    docs = spark.createDataFrame([(i, t, i // 4) for i, t in texts], "doc_id long, text string, release_no int")
    index = Index(spark, str(tmp_path / "ix"), SMALL, policies.Tiered(2))
    seq = {(r.release_no, r.doc_id): r.status for r in ingest_all(index, docs, [0, 1, 2]).collect()}
    k = keys.long_keys(docs, SMALL)
    assert seq == {(r.release_no, r.doc_id): r.status for r in screen.bulk(docs, k).collect()}
    before = index.digest()
    index.ingest(docs.where("release_no = 2").select("doc_id", "text"), "r2")
    assert index.digest() == before
    with pytest.raises(Conflict):
        index.ingest(docs.where("release_no = 0").select("doc_id", "text"), "r0")
    assert index.withdraw("r0")["rebuilt"] and index.withdraw("r0")["affected_keys"] == 0
    own = screen.internal_keys(k)
    left = {(r.band, r.key) for r in index.all_keys().collect()}
    assert left == {(r.band, r.key) for r in own.where("release_no <> 0").collect()}
    with pytest.raises(Conflict):
        Index(spark, str(tmp_path / "ix"), DedupConfig())


def _texts(n=24, k=4):
    return [(i, i // (n // k), " ".join(WORDS[j % 12] + str(i % 5) for j in range(8))) for i in range(n)]


@pytest.mark.parametrize("policy", [policies.Never(), policies.Tiered(2), policies.Tiered(2, coalesce=True), policies.FoldAll(), policies.FrozenCap(20)])
def test_compaction_changes_nothing(spark, tmp_path, policy):
    """Decisions, digest and keys are those of the bulk form, whatever is merged and by whatever search."""
    docs = spark.createDataFrame(_texts(), "doc_id long, release_no int, text string")
    want = {r.doc_id: r.status for r in screen.bulk(docs, keys.long_keys(docs, SMALL)).collect()}
    own = {(r.band, r.key) for r in screen.internal_keys(keys.long_keys(docs, SMALL)).collect()}
    for strategy in ("seek", "broadcast", "merge"):
        index = Index(spark, str(tmp_path / strategy), SMALL, policy)
        got = {r.doc_id: r.status for r in ingest_all(index, docs, [0, 1, 2, 3], strategy).collect()}
        assert got == want and {(r.band, r.key) for r in index.all_keys().distinct().collect()} == own
        assert sum(n for _, n, _ in index.digest()) == len(own)


def test_merge_paths_and_plans(spark, tmp_path):
    """Joined and dealt merges agree; a probe and a joined merge shuffle nothing."""
    stream = spark.range(600).selectExpr("cast(id % 3 as int) release_no", "id doc_id", "cast(id % 8 as int) band", "cast(conv(substr(md5(cast(id % 400 as string)), 1, 15), 16, 10) as long) key")
    index = Index(spark, str(tmp_path / "ix"), SMALL, policies.Never())
    ready = index.prepare_keys(stream)
    parts = [segments.load(spark, ready.sidecars[r], SMALL) for r in range(3)]
    joined, dealt = (segments.merged(parts, SMALL, how) for how in ("joined", "dealt"))
    rows = lambda df: sorted((r.band, r.shard, r.n, bytes(r["keys"])) for r in df.collect())
    assert rows(joined) == rows(dealt) and len(rows(joined)) == SMALL.bands << SMALL.shard_bits
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan(joined) and "Exchange" not in plan(segments.probe(parts[0], parts[1], "merge"))
    assert "Exchange" in plan(dealt)  # a union of bucketed tables is not taken for dealt already
    both = segments.probe(parts[0], parts[1], "merge").collect()
    one, two = ({(r.band, r.key) for r in segments.unpacked(p).collect()} for p in parts[:2])
    assert {(r.band, r.key) for r in both} == one & two and one & two


def test_withdrawal_and_rollback(spark, tmp_path):
    docs = spark.createDataFrame(_texts(30, 5), "doc_id long, release_no int, text string")
    index = Index(spark, str(tmp_path / "ix"), SMALL, policies.Tiered(2))
    ready = index.prepare(docs)
    for r in range(5):
        index.admit(ready, r, f"r{r}", protected=r == 1, decide=False)
    before, digest = index.read(), index.digest()
    own = {r: {(x.band, x.key) for x in segments.unpacked(index.sidecar(f"r{r}")).collect()} for r in range(5)}
    for r in range(5):
        done = index.withdraw(f"r{r}")
        others = set().union(*(own[o] for o in own if o != r))
        assert {(x.band, x.key) for x in index.all_keys().collect()} == others
        assert index.exclusive_left(f"r{r}", before) == (len(own[r] - others), 0)
        assert done["rebuilt"] == (r not in (1, 4)) or done["level"] == 0
        index.rollback(before["snapshot"])
        assert index.digest() == digest
    detail = {(r.doc_id, r.level) for r in index.match_detail(ready, 0).collect()}
    assert detail and index.fold() > 0 and len(index.live()) == 2  # the protected one stays


def test_two_writers(spark, tmp_path):
    """Of many writers of one snapshot exactly one is first."""
    from concurrent.futures import ThreadPoolExecutor

    manifest = Manifest(spark, str(tmp_path / "m"))
    state = manifest.read()

    def publish(i: int) -> bool:
        try:
            Manifest(spark, str(tmp_path / "m")).publish(state, newest=str(i))
            return True
        except Conflict:
            return False

    with ThreadPoolExecutor(8) as pool:
        won = list(pool.map(publish, range(24)))
    assert sum(won) == 1 and manifest.read()["newest"] == str(won.index(True)) and manifest.snapshots() == [1]


def test_withdrawal_of_an_own_segment_starts_no_job(spark, tmp_path):
    docs = spark.createDataFrame(_texts(12, 2), "doc_id long, release_no int, text string")
    index = Index(spark, str(tmp_path / "ix"), SMALL, policies.Never())
    ready = index.prepare(docs)
    for r in range(2):
        index.admit(ready, r, f"r{r}", decide=False)
    spark.sparkContext.setJobGroup("withdraw", "withdraw")
    try:
        assert not index.withdraw("r0")["rebuilt"]
        assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("withdraw")) == 0
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_identity_of_file_and_row(spark, tmp_path):
    """The smallest (file, row) represents a group, also across files."""
    rows = [("b", 1, "x y z u v w"), ("a", 9, "x y z u v w"), ("a", 10, "x y z u v w"), ("c", 1, "p q r s t u")]
    docs = spark.createDataFrame(rows, "file string, row long, text string").selectExpr("struct(file, row) as doc_id", "text")
    index = Index(spark, str(tmp_path / "ix"), SMALL)
    got = {tuple(r.doc_id): r.status for r in index.ingest(docs, "r0").collect()}
    assert got == {("a", 9): "kept", ("a", 10): "removed_within", ("b", 1): "removed_within", ("c", 1): "kept"}
    assert {r.status for r in index.ingest(docs.where("doc_id.file = 'c'"), "r1").collect()} == {"removed_history"}


def test_stream_of_releases(spark, tmp_path):
    """A micro-batch is a release; a restart that finds nothing new changes nothing."""
    for r in range(3):
        spark.createDataFrame([x[::2] for x in _texts() if x[1] == r], "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / f"in/{r}"))
    index = Index(spark, str(tmp_path / "ix"), SMALL)
    for _ in range(2):
        source = spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
        streaming.ingest_stream(index, source, str(tmp_path / "ck")).awaitTermination(120)
    docs = spark.createDataFrame(_texts(), "doc_id long, release_no int, text string").where("release_no < 3")
    own = {(r.band, r.key) for r in screen.internal_keys(keys.long_keys(docs, SMALL)).collect()}
    assert {(r.band, r.key) for r in index.all_keys().collect()} == own and index.read()["newest"] == "s2"


def test_baselines(spark):
    rows = [(0, 1, 0, 1), (0, 1, 1, 10), (0, 2, 0, 1), (0, 2, 1, 20), (1, 3, 0, 2), (1, 3, 1, 20), (1, 4, 0, 3), (1, 4, 1, 10)]
    k = spark.createDataFrame(rows, "release_no int, doc_id long, band int, key long")
    docs = k.select("release_no", "doc_id").distinct()
    got = {r.doc_id: (r.kept, r.bytes) for r in baselines.resident_decisions(docs, k, 1 << 20).collect()}
    assert got == {1: (True, 200), 2: (False, 200), 3: (True, 400), 4: (False, 400)}  # 20 is not held: 2 was dropped
    cut = {r.doc_id: r.stopped for r in baselines.resident_decisions(docs, k, 250).collect()}
    assert cut == {1: False, 2: False, 3: True, 4: True}
    known = {r.doc_id for r in baselines.bloom_decisions(screen.internal_keys(k), 1e-9, share=1).collect()}
    assert known == {4}  # 3's key 20 went with 2
    assert baselines.capabilities(spark).count() == 6 and costmodel.advise(1e9, 2**40, 40, True, True) == "segmented_index"
