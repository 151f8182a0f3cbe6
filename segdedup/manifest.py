"""The manifest: JSON snapshots, each put in place by an operation that fails if the name is taken.

Reading and publishing are driver-side file operations, never Spark jobs, so a withdrawal that only
takes a segment's name out of the list costs the same whatever the index holds.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import SparkSession


class Conflict(RuntimeError):
    """Another writer published the snapshot first, or the configuration differs."""


class Manifest:
    def __init__(self, spark: SparkSession, root: str):
        self.root = f"{root.rstrip('/')}/manifest"
        self._jvm = spark.sparkContext._jvm
        self._conf = spark.sparkContext._jsc.hadoopConfiguration()
        self._fs = self._path(self.root).getFileSystem(self._conf)
        self._fs.mkdirs(self._path(self.root))

    def _path(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(name)

    def _file(self, n: int):
        return self._path(f"{self.root}/{n:08d}.json")

    def snapshots(self) -> list[int]:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(self.root))]
        return sorted(int(n[:-5]) for n in names if n.endswith(".json") and not n.startswith("."))

    def read(self, snapshot: int | None = None) -> dict:
        """The latest snapshot, or an older one."""
        known = self.snapshots() if snapshot is None else [snapshot]
        if not known:
            return {"snapshot": 0, "config": None, "newest": None, "rows": [], "runs": []}
        stream = self._fs.open(self._file(known[-1]))
        try:
            return json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def publish(self, state: dict, **changes) -> dict:
        """The next snapshot, state with changes; raises Conflict if somebody else has published it."""
        new = state | changes | {"snapshot": state["snapshot"] + 1}
        draft, target = self._path(f"{self.root}/.{uuid.uuid4().hex}"), self._file(new["snapshot"])
        out = self._fs.create(draft, False)
        out.write(bytearray(json.dumps(new).encode()))
        out.close()
        try:
            self._put(draft, target)
        except Exception as error:
            if self._fs.exists(target):
                raise Conflict(f"snapshot {new['snapshot']} exists") from error
            raise
        finally:
            self._fs.delete(draft, False)
        return new

    def _put(self, draft, target) -> None:
        """Puts the whole draft under the target's name, or fails if there is one.

        A local hard link and a rename at the name node are such operations. An object store must
        offer a conditional create; one that does not refuses the option.
        """
        scheme = self._fs.getUri().getScheme()
        if scheme == "file":
            local = lambda p: self._jvm.java.io.File(p.toUri().getPath()).toPath()
            self._jvm.java.nio.file.Files.createLink(local(target), local(draft))
        elif scheme in ("hdfs", "viewfs"):
            options = self._jvm.org.apache.hadoop.fs.Options.Rename
            none = self._jvm.java.lang.reflect.Array.newInstance(options.NONE.getClass(), 1)
            none[0] = options.NONE
            self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(draft.toUri(), self._conf).rename(draft, target, none)
        else:
            stream = self._fs.open(draft)
            body = self._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)
            stream.close()
            out = self._fs.createFile(target).overwrite(False).must("fs.option.create.conditional.overwrite", True).build()
            out.write(body)
            out.close()
