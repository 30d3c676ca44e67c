"""A table of immutable shards with size-tiered compaction and a versioned manifest; DataFrame writes only.

An arrival becomes one small shard, a folder of Parquet files, and is never changed. Shards of similar size
share a tier (powers of ``fanout`` over ``base_bytes``). When a tier holds ``fanout`` of them they are
merged into one shard with files of about ``target_bytes``; shards of the target size join no tier.
An arrival of many small files, ``fanout`` times those it needs, is rewritten by itself, whatever its size, as no
tier may ever take it. So a row is rewritten once a tier, the logarithm of the table's size, and once as it arrives.

What the table holds is what the newest manifest names. A manifest is written beside the others and
renamed to its version; the loser of a race reads the new manifest and tries again. That needs a store whose rename is whole or
not at all and refuses a name that is taken, as HDFS and local disks have; on one that lacks it, manifests have to go to one that has.
Shards without a manifest, left by a crash or still being written, are no part of the table; ``vacuum`` removes those that no
manifest kept names once they are older than a grace period, which must exceed the longest write.

Rows of all kinds are kept as they are, repeated ones, nulls and very long texts included; an empty arrival commits no shard, and a
table of empty arrivals is empty. Further columns are kept; an arrival has the columns of the table. Shards of equal size are merged in order of their names.
"""

from __future__ import annotations

import json
import math
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


class ShardedTable:
    """A table under ``root``, any path that Spark can write."""

    def __init__(self, spark: SparkSession, root: str, *, fanout: int = 4, base_bytes: int = 1 << 20, target_bytes: int = 128 << 20):
        self.spark, self.root = spark, root.rstrip("/")
        self.fanout, self.base_bytes, self.target_bytes = fanout, base_bytes, target_bytes
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._conf = spark.sparkContext._jsc.hadoopConfiguration()
        self._fs = self._path(self.root).getFileSystem(self._conf)

    def _list(self, folder: str) -> list[str]:
        p = self._path(folder)
        return sorted(s.getPath().getName() for s in self._fs.listStatus(p)) if self._fs.exists(p) else []

    def versions(self) -> list[int]:
        return [int(n[1:-5]) for n in self._list(f"{self.root}/manifest") if n.startswith("v") and n.endswith(".json")]

    def manifest(self, version: int | None = None) -> dict:
        """``version`` and ``shards``; version 0 is the empty table."""
        version = max(self.versions(), default=0) if version is None else version
        if not version:
            return {"version": 0, "shards": []}
        stream = self._fs.open(self._path(f"{self.root}/manifest/v{version:010d}.json"))
        try:
            return json.loads(bytes(stream.readAllBytes()))
        finally:
            stream.close()

    def _publish(self, version: int, shards: list[dict]) -> bool:
        """Whether the manifest became that version; False if another writer has it."""
        final = self._path(f"{self.root}/manifest/v{version:010d}.json")
        if self._fs.exists(final):
            return False
        draft = self._path(f"{self.root}/manifest/.{uuid.uuid4().hex}")
        out = self._fs.create(draft, True)
        out.write(bytearray(json.dumps({"version": version, "shards": shards}, indent=1).encode()))
        out.close()
        context = self.spark.sparkContext._jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self._conf)
        none = self.spark.sparkContext._gateway.new_array(self.spark.sparkContext._jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            context.rename(draft, final, none)
        except Exception:
            self._fs.delete(draft, False)
            if self._fs.exists(final):
                return False
            raise
        return True

    def commit(self, added: list[dict], removed: set[str] = frozenset()) -> int:
        """The new version: the newest one's shards without ``removed`` and with ``added``.

        If a shard to be removed has gone meanwhile, another compaction took it; nothing is committed then.
        """
        while True:
            now = self.manifest()
            if not removed <= {s["id"] for s in now["shards"]}:
                return now["version"]
            if self._publish(now["version"] + 1, [s for s in now["shards"] if s["id"] not in removed] + added):
                return now["version"] + 1

    def describe(self, folder: str, level: int) -> dict | None:
        """A shard's entry in the manifest; None if it has no rows, by the footers of its files."""
        files = [s.getLen() for s in self._fs.listStatus(self._path(folder)) if s.getPath().getName().endswith(".parquet")]
        rows = self.spark.read.parquet(folder).count() if files else 0
        return {"id": folder.rsplit("/", 1)[-1], "path": folder, "bytes": sum(files), "files": len(files), "rows": rows, "level": level} if rows else None

    def needed(self, size: int) -> int:
        """Files for so many bytes."""
        return max(1, round(size / self.target_bytes))

    def loose(self, shard: dict) -> bool:
        """Whether a shard lies as it arrived, in far more files than it needs."""
        return not shard["level"] and shard.get("files", 1) >= self.fanout * self.needed(shard["bytes"])

    def tier(self, size: int) -> int:
        return max(0, math.floor(math.log(max(size, 1) / self.base_bytes, self.fanout)) + 1) if size >= self.base_bytes else 0

    def append(self, arrival: DataFrame) -> int:
        folder = f"{self.root}/data/{uuid.uuid4().hex}"
        arrival.write.parquet(folder)
        entry = self.describe(folder, 0)
        if entry is None:
            self._fs.delete(self._path(folder), True)
            return self.manifest()["version"]
        return self.commit([entry])

    def append_all(self, rows: DataFrame, by: str) -> list[int]:
        """One arrival for each value of ``by``, written in one pass and committed one after the other."""
        stage = f"{self.root}/data/{uuid.uuid4().hex}"
        rows.write.partitionBy(by).parquet(stage)
        entries = [self.describe(f"{stage}/{n}", 0) for n in self._list(stage) if n.startswith(f"{by}=")]
        out = []
        for e in filter(None, entries):
            out.append(self.commit([e | {"id": f"{stage.rsplit('/', 1)[-1]}-{e['id']}"}]))
            self.compact()
        return out

    def due(self) -> list[dict] | None:
        """Shards of the lowest tier that holds enough similar ones, else the smallest loose one."""
        tiers: dict[int, list[dict]] = {}
        shards = self.manifest()["shards"]
        for s in shards:
            if s["bytes"] < self.target_bytes:
                tiers.setdefault(self.tier(s["bytes"]), []).append(s)
        full = [v for _, v in sorted(tiers.items()) if len(v) >= self.fanout]
        loose = sorted(filter(self.loose, shards), key=lambda s: (s["bytes"], s["id"]))
        return sorted(full[0], key=lambda s: (s["bytes"], s["id"])) if full else loose[:1] or None

    def compact(self) -> int:
        """Merge until no tier is full and no shard loose; the number of merges."""
        merges = 0
        while run := self.due():
            folder = f"{self.root}/data/{uuid.uuid4().hex}"
            files = self.needed(sum(s["bytes"] for s in run))
            self.spark.read.parquet(*[s["path"] for s in run]).coalesce(files).write.parquet(folder)
            entry = self.describe(folder, 1 + max(s["level"] for s in run))
            self.commit([entry] if entry else [], {s["id"] for s in run})
            merges += 1
        return merges

    def read(self, version: int | None = None, schema=None) -> DataFrame | None:
        """The rows of a version; None for the empty table if no ``schema`` is given."""
        paths = [s["path"] for s in self.manifest(version)["shards"]]
        if paths:
            return self.spark.read.parquet(*paths)
        return None if schema is None else self.spark.createDataFrame([], schema)

    def _changed(self, path) -> int:
        """When a file, or the last one in a folder, was written, in milliseconds."""
        status = self._fs.getFileStatus(path)
        inner = [self._changed(s.getPath()) for s in self._fs.listStatus(path)] if status.isDirectory() else []
        return max([status.getModificationTime(), *inner])

    def vacuum(self, keep: int = 1, grace_s: float = 7 * 86_400) -> None:
        """Remove old manifests, and the data that none of the newest ``keep`` names and that is older than the grace period.

        Younger data may belong to a writer that has not committed yet. No grace is safe only without other writers.
        """
        # What is written from now on is not looked at, whatever its manifest says later.
        before = int((time.time() - grace_s) * 1000)
        versions = self.versions()
        named = {s["path"] for v in versions[-keep:] for s in self.manifest(v)["shards"]}
        for v in versions[:-keep]:
            self._fs.delete(self._path(f"{self.root}/manifest/v{v:010d}.json"), False)
        for n in self._list(f"{self.root}/data"):
            folder = f"{self.root}/data/{n}"
            if folder in named:
                continue
            if grace_s > 0 and self._changed(self._path(folder)) > before:
                continue
            inner = [f"{folder}/{x}" for x in self._list(folder)]
            if any(p in named for p in inner):
                for p in inner:
                    if p not in named:
                        self._fs.delete(self._path(p), True)
            else:
                self._fs.delete(self._path(folder), True)
