"""The segmented index: sidecars, sorted segments, a manifest of snapshots.

Everything an attempt writes lies in folders of its own; only the manifest's next snapshot makes
any of it visible, and it is published by an operation that fails if somebody else was first. So a
crash at any point leaves the last snapshot, and a retry of the same tag gives the same state.

A release is prepared (band keys, survivors within the release, its packed sidecar) and admitted
(probed against the live segments, committed, compacted). The sidecar of a release is written in
the form of a segment, so a commit writes nothing but the manifest; after a merge the sidecar stays
as the source of a later withdrawal.
"""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from segdedup import keys as K
from segdedup import screen, segments
from segdedup.config import DedupConfig
from segdedup.manifest import Conflict, Manifest
from segdedup.policies import Segment, Tiered

__all__ = ["Conflict", "Index", "Prepared", "ingest_all"]

#: Packed bytes of a release up to which its rows are broadcast for the probe.
BROADCAST_BYTES = 64 << 20


@dataclass
class Prepared:
    """Releases whose keys are ready: folders of an attempt and the number of keys of each release."""

    keys: str  # release_no, doc_id, band, key of the survivors within a release
    removed: str  # release_no, doc_id, band, winner of the others
    sidecars: dict[int, str]
    n_keys: dict[int, int]


class Index:
    def __init__(self, spark: SparkSession, root: str, config: DedupConfig, policy=None):
        self.spark, self.root, self.config = spark, root.rstrip("/"), config
        self.policy = policy or Tiered(config.fanout)
        self.manifest = Manifest(spark, self.root)
        if self.read()["config"] not in (None, config.digest):
            raise Conflict("the index was built with another configuration; start a new generation")

    # the manifest

    def read(self, snapshot: int | None = None) -> dict:
        return self.manifest.read(snapshot)

    def swap(self, state: dict, rows: list[dict], newest: str | None, run: dict | None = None) -> dict:
        """Publishes the next snapshot; raises Conflict if somebody else has."""
        return self.manifest.publish(state, config=self.config.digest, rows=rows, newest=newest, runs=[*state["runs"], run] if run else state["runs"])

    def rollback(self, snapshot: int) -> dict:
        """Publishes an older snapshot's content as the newest one."""
        old, state = self.read(snapshot), self.read()
        return self.manifest.publish(state, rows=old["rows"], newest=old["newest"], runs=old["runs"])

    def live(self, state: dict | None = None) -> list[dict]:
        return [r for r in (state or self.read())["rows"] if r["live"]]

    def describe(self, snapshot: int | None = None) -> DataFrame:
        """The manifest as a table."""
        rows = [(r["seg_id"], r["level"], r["tag"], r["origins"], r["protected"], r["live"], r["n_keys"]) for r in self.read(snapshot)["rows"]]
        return self.spark.createDataFrame(rows, "seg_id string, level int, tag string, origins array<string>, protected boolean, live boolean, n_keys long")

    def runs(self) -> DataFrame:
        """What each commit and compaction did: kind, tag, segments probed, keys asked, keys written, seconds."""
        rows = [(i, r["kind"], r["tag"], r["fanout"], r["asked"], r["written"], float(r["seconds"])) for i, r in enumerate(self.read()["runs"])]
        return self.spark.createDataFrame(rows, "place int, kind string, tag string, fanout int, asked long, written long, seconds double")

    # segments

    def segment(self, row: dict) -> DataFrame:
        """The packed rows of a manifest row's segment."""
        return segments.load(self.spark, row["path"], self.config)

    def sidecar(self, tag: str, state: dict | None = None) -> DataFrame:
        """The packed keys of one release."""
        row = [r for r in (state or self.read())["rows"] if r["tag"] == tag][-1]
        return segments.load(self.spark, row["path"], self.config)

    def all_keys(self, state: dict | None = None) -> DataFrame:
        """band, key of every live segment."""
        out = self.spark.createDataFrame([], "band int, key long")
        for r in self.live(state):
            out = out.union(segments.unpacked(self.segment(r)))
        return out

    def union(self, state: dict | None = None) -> DataFrame:
        """The packed union of all live segments."""
        rows = self.live(state)
        if not rows:
            return segments.packed(self.spark.createDataFrame([], "band int, key long"), self.config)
        return segments.merged([self.segment(r) for r in rows], self.config)

    def digest(self) -> list[tuple[int, int, str]]:
        """Of each band the number of distinct keys and the SHA-256 over its shards' SHA-256 in order."""
        shards = self.union().select("band", "shard", "n", F.sha2("keys", 256).alias("sha"))
        whole = F.sha2(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("shard", "sha"))), lambda s: s["sha"]), ""), 256)
        return [tuple(r) for r in shards.groupBy("band").agg(F.sum("n"), whole).orderBy("band").collect()]

    # the lifecycle

    def prepare(self, docs: DataFrame, fault=lambda point: None) -> Prepared:
        """Keys and sidecars of one or many releases at once; docs: release_no, doc_id, text."""
        return self.prepare_keys(K.long_keys(docs.select("release_no", "doc_id", "text"), self.config), fault)

    def prepare_keys(self, keys: DataFrame, fault=lambda point: None) -> Prepared:
        """The same from band keys: release_no, doc_id, band, key. doc_id may be a struct of file and row."""
        attempt = f"{self.root}/attempts/{uuid.uuid4().hex}"
        keys.write.parquet(f"{attempt}/all")
        fault("keys written")
        keys = self.spark.read.parquet(f"{attempt}/all")
        screen.within_release(keys).write.parquet(f"{attempt}/removed")
        fault("removed written")
        removed = self.spark.read.parquet(f"{attempt}/removed").select("release_no", "doc_id")
        keys.join(removed, ["release_no", "doc_id"], "left_anti").write.parquet(f"{attempt}/internal")
        fault("internal written")
        internal = self.spark.read.parquet(f"{attempt}/internal")
        numbers = sorted(r[0] for r in keys.select("release_no").distinct().collect())  # releases of this attempt
        if numbers:
            rows = segments.packed(internal.select(F.col("release_no").alias("tag_no"), "band", "key"), self.config, numbers)
            segments.save(rows, f"{attempt}/sidecars", self.config, by="tag_no")
        fault("sidecar written")
        paths = {r: f"{attempt}/sidecars/tag_no={r}" for r in numbers}
        sizes = {r: 0 for r in numbers}
        if numbers:
            found = self.spark.read.parquet(f"{attempt}/sidecars").groupBy("tag_no").agg(F.sum("n").cast("long")).collect()
            sizes = {int(a): int(n) for a, n in map(tuple, found)}
        return Prepared(f"{attempt}/internal", f"{attempt}/removed", paths, sizes)

    def _matched(self, asked: DataFrame, asked_keys: int, state: dict, tag: str, strategy: str) -> DataFrame | None:
        """band, key of a release's keys that a live segment of another tag has."""
        history = [r for r in self.live(state) if r["tag"] != tag and r["n_keys"]]
        if not history or not asked_keys:
            return None
        if strategy == "auto":
            strategy = "broadcast" if 8 * asked_keys <= BROADCAST_BYTES else "seek"
        if strategy == "broadcast" and 8 * asked_keys > BROADCAST_BYTES:
            raise ValueError(f"{8 * asked_keys} bytes of keys are too many to broadcast")
        out = None
        for r in history:
            if strategy == "merge":
                part = segments.unpacked(asked).join(segments.unpacked(self.segment(r)), ["band", "key"], "left_semi")
            else:
                part = segments.probe(asked, self.segment(r), "broadcast" if strategy == "broadcast" else "merge")
            out = part if out is None else out.union(part)
        return out.distinct()

    def admit(self, ready: Prepared, release: int, tag: str, protected: bool = False, fault=lambda point: None, strategy: str = "seek", decide: bool = True) -> DataFrame | None:
        """Probes, commits and compacts a prepared release; gives doc_id, status, band, segment of what is removed or kept.

        The newest tag may be admitted again: its own segment is neither probed nor kept. decide:
        False commits without decisions (a rebuild of the index alone).
        """
        state = self.read()
        if any(tag in r["origins"] and r["tag"] != tag for r in self.live(state)):
            raise Conflict(f"{tag} is merged already; use replace()")
        began, out = time.time(), None
        path, n = ready.sidecars.get(release), ready.n_keys.get(release, 0)
        if path is None:  # an empty release has a segment of empty shards
            path = f"{self.root}/attempts/{uuid.uuid4().hex}/sidecar"
            segments.save(segments.packed(self.spark.createDataFrame([], "band int, key long"), self.config), path, self.config)
        probed = [r for r in self.live(state) if r["tag"] != tag and r["n_keys"]]
        if decide:
            out = f"{self.root}/attempts/{uuid.uuid4().hex}/decisions"
            self._decide(ready, release, path, n, state, tag, strategy).write.parquet(out)
            fault("decisions written")
        rows = [r | {"live": r["live"] and r["tag"] != tag} for r in state["rows"]]
        rows.append({"seg_id": f"l0-{uuid.uuid4().hex[:12]}", "level": 0, "tag": tag, "origins": [tag], "protected": protected, "live": True, "n_keys": n, "path": path})
        fault("before swap")
        self.swap(state, rows, tag, {"kind": "admit", "tag": tag, "fanout": len(probed), "asked": n, "written": n, "seconds": time.time() - began})
        fault("swapped")
        self.compact(fault)
        return self.spark.read.parquet(out) if out else None

    def _decide(self, ready: Prepared, release: int, path: str, n: int, state: dict, tag: str, strategy: str) -> DataFrame:
        own = F.col("release_no") == release
        removed = self.spark.read.parquet(ready.removed).where(own).select("doc_id", F.lit("removed_within").alias("status"), "band")
        internal = self.spark.read.parquet(ready.keys).where(own).select("doc_id", "band", "key")
        matched = self._matched(segments.load(self.spark, path, self.config), n, state, tag, strategy)
        if matched is None:
            return removed.unionByName(internal.select("doc_id").distinct().select("doc_id", F.lit("kept").alias("status"), F.lit(None).cast("int").alias("band")))
        hit = internal.join(matched.withColumn("hit", F.lit(True)), ["band", "key"], "left").groupBy("doc_id").agg(F.min(F.when(F.col("hit"), F.col("band"))).alias("band"))
        return removed.unionByName(hit.select("doc_id", F.when(F.col("band").isNull(), "kept").otherwise("removed_history").alias("status"), "band"))

    def ingest(self, docs: DataFrame, tag: str, protected: bool = False, fault=lambda point: None, strategy: str = "seek") -> DataFrame:
        """Decisions (doc_id, status) on a release; commits it and compacts. docs: doc_id, text.

        Documents without words have no keys and are kept.
        """
        ready = self.prepare(docs.select(F.lit(0).alias("release_no"), "doc_id", "text"), fault)
        return decided(docs, self.admit(ready, 0, tag, protected, fault, strategy))

    def match_detail(self, ready: Prepared, release: int) -> DataFrame:
        """doc_id, band, level, origins of every segment that holds one of a prepared release's keys."""
        asked, out = segments.load(self.spark, ready.sidecars[release], self.config), None
        for r in self.live():
            part = segments.probe(asked, self.segment(r)).select("band", "key", F.lit(r["level"]).alias("level"), F.array(*[F.lit(t) for t in r["origins"]]).alias("origins"))
            out = part if out is None else out.union(part)
        internal = self.spark.read.parquet(ready.keys).where(F.col("release_no") == release)
        return internal.join(out, ["band", "key"]).select("doc_id", "band", "level", "origins")

    def compact(self, fault=lambda point: None) -> int:
        """Runs the policy's merges; returns the keys written. Decisions never change: a merge is a union."""
        state = self.read()
        live = {r["seg_id"]: r for r in self.live(state)}
        plan = self.policy.plan([Segment(r["seg_id"], r["level"], r["origins"], r["protected"], r["n_keys"]) for r in live.values()], state["newest"])
        began, rows, written, made = time.time(), list(state["rows"]), 0, dict(live)
        for merge in plan:
            inputs = [made[s.seg_id] for s in merge.inputs]
            origins = [t for r in inputs for t in r["origins"]]
            new = self._merge(inputs, merge.level, origins)
            fault("merged")
            written += new["n_keys"]
            made[f"merge-{merge.level}-{'-'.join(s.seg_id for s in merge.inputs)}"] = new
            gone = {r["seg_id"] for r in inputs}
            rows = [r | {"live": r["live"] and r["seg_id"] not in gone} for r in rows] + [new]
        if plan:
            fault("before merge swap")
            self.swap(state, rows, state["newest"], {"kind": "compact", "tag": None, "fanout": 0, "asked": 0, "written": written, "seconds": time.time() - began})
        return written

    def _merge(self, inputs: list[dict], level: int, origins: list[str], path: str | None = None) -> dict:
        """Writes the union of manifest rows' segments; the new manifest row."""
        seg = f"l{level}-{uuid.uuid4().hex[:12]}"
        place = f"{self.root}/segments/{seg}"
        segments.save(segments.merged([self.segment(r) for r in inputs], self.config, path), place, self.config)
        n = segments.load(self.spark, place, self.config).agg(F.sum("n")).first()[0]
        return {"seg_id": seg, "level": level, "tag": None, "origins": origins, "protected": False, "live": True, "n_keys": int(n), "path": place}

    def fold(self) -> int:
        """Merges all live segments but protected ones into one; returns the keys written."""
        state = self.read()
        inputs = [r for r in self.live(state) if not r["protected"]]
        if len(inputs) < 2:
            return 0
        new = self._merge(inputs, 1 + max(r["level"] for r in inputs), [t for r in inputs for t in r["origins"]])
        gone = {r["seg_id"] for r in inputs}
        rows = [r | {"live": r["live"] and r["seg_id"] not in gone} for r in state["rows"]] + [new]
        self.swap(state, rows, None, {"kind": "fold", "tag": None, "fanout": 0, "asked": 0, "written": new["n_keys"], "seconds": 0.0})
        return new["n_keys"]

    def withdraw(self, tag: str) -> dict:
        """Takes a release out: metadata only where its segment is its own, else a rebuild of the
        merged segment from the other members' sidecars."""
        state = self.read()
        hit = [r for r in self.live(state) if tag in r["origins"]]
        if not hit:
            return {"tag": tag, "level": None, "affected_keys": 0, "rebuilt": False}
        row = hit[0]
        rows = [r | {"live": r["live"] and r["seg_id"] != row["seg_id"]} for r in state["rows"]]
        members = [t for t in row["origins"] if t != tag]
        if members:
            sidecars = [[r for r in state["rows"] if r["tag"] == t][-1] for t in members]
            rows.append(self._merge(sidecars, row["level"], members))
        self.swap(state, rows, state["newest"] if state["newest"] != tag else None)
        return {"tag": tag, "level": row["level"], "affected_keys": row["n_keys"], "rebuilt": bool(members)}

    def replace(self, docs: DataFrame, tag: str, **options) -> DataFrame:
        """Replays a tag that is merged already: withdraw, then ingest."""
        self.withdraw(tag)
        return self.ingest(docs, tag, **options)

    def exclusive_left(self, tag: str, state: dict | None = None) -> tuple[int, int]:
        """Keys that only this release brought in among all committed ones, and how many of them the live index holds.

        state: a snapshot from before the withdrawal names the releases; the live index is read now.
        """
        then = state or self.read()
        others = {t for r in self.live(then) for t in r["origins"]} - {tag}
        own = segments.unpacked(self.sidecar(tag, then))
        for t in sorted(others):
            own = own.join(segments.unpacked(self.sidecar(t, then)), ["band", "key"], "left_anti")
        own = own.persist()
        found = own.count(), own.join(self.all_keys(), ["band", "key"], "left_semi").count()
        own.unpersist()
        return found


def decided(docs: DataFrame, decisions: DataFrame) -> DataFrame:
    """doc_id, status of every document: one without keys is kept."""
    return docs.select("doc_id").join(decisions.select("doc_id", "status"), "doc_id", "left").select("doc_id", F.coalesce("status", F.lit("kept")).alias("status"))


def ingest_all(index: Index, docs: DataFrame, releases: list[int], strategy: str = "seek") -> DataFrame:
    """Ingestion of prepared releases one after the other through the manifest: release_no, doc_id, status."""
    ready, out = index.prepare(docs), None
    for r in releases:
        part = index.admit(ready, r, f"r{r}", strategy=strategy).select(F.lit(r).alias("release_no"), "doc_id", "status")
        out = part if out is None else out.union(part)
    kept = docs.select("release_no", "doc_id").join(out, ["release_no", "doc_id"], "left")
    return kept.select("release_no", "doc_id", F.coalesce("status", F.lit("kept")).alias("status"))
