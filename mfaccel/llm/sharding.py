"""Sharding: small immutable shards per arrival, size-tiered compaction, versioned manifests.

An arrival is written as immutable Parquet shards and becomes visible when a manifest that lists them is renamed into
place: readers see all of it or nothing. Compaction looks at the sizes that the newest manifest lists. Shards under
FULL of the target are put in tiers by a power of TIER_RATIO; a tier of FAN_IN shards or more is merged: Spark packs
its files into partitions of the target size and writes each as one shard, without a shuffle. Tiers are merged one at a time, the
smallest shards first, until none is full; shards of different tiers never go into one merge. A merge is committed on the manifest that is the newest by then, if that still lists
what was merged. Files that no kept manifest lists are removed by vacuum(), not by a commit, so that readers of an older
version can finish; files that were never listed are spared for a day, as their commit may be yet to come. A lost executor costs only its tasks: what they wrote is not listed.

All file operations go through Hadoop's file system API, so the store may be anywhere that Spark writes. The rename is
atomic where the file system's is (HDFS, local); the driver handles one entry per shard, never rows.

Edge cases: an arrival without rows adds a version without shards; null values, repeated rows, very long texts and any
columns are stored as they are; an empty store reads as an empty table of its schema; arrivals of another schema are
refused.
"""

from __future__ import annotations

import json
import math
import time
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TARGET_BYTES, FAN_IN, TIER_RATIO, FULL = 64 << 20, 4, 4, 0.75
#: Age from which a file that no version has listed counts as left behind: longer than any write takes.
GRACE_SECONDS = 86_400.0


class Conflict(RuntimeError):
    """Another writer took the version, or shards that a merge read are gone."""


@dataclass(frozen=True)
class Shard:
    path: str
    bytes: int
    arrival: str


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, schema: StructType | None = None):
        self.spark, self.root = spark, root.rstrip("/")
        jvm = spark._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())
        if self.version() < 0:
            if schema is None:
                raise ValueError("a new store needs a schema")
            self._commit(0, {"shards": [], "schema": schema.jsonValue(), "did": "create"})

    # --- manifests -------------------------------------------------------------------------------------------------

    def _manifest(self, version: int):
        return self._path(f"{self.root}/manifests/v{version:010d}.json")

    def versions(self) -> list[int]:
        folder = self._path(f"{self.root}/manifests")
        names = [x.getPath().getName() for x in self._fs.listStatus(folder)] if self._fs.exists(folder) else []
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def version(self) -> int:
        return max(self.versions(), default=-1)

    def manifest(self, version: int | None = None) -> dict:
        stream = self._fs.open(self._manifest(self.version() if version is None else version))
        try:
            return json.loads(bytes(stream.readAllBytes()).decode())
        finally:
            stream.close()

    def shards(self, version: int | None = None) -> list[Shard]:
        return [Shard(**x) for x in self.manifest(version)["shards"]]

    def _commit(self, version: int, content: dict) -> int:
        draft = self._path(f"{self.root}/manifests/.draft-{uuid.uuid4().hex}")
        stream = self._fs.create(draft, False)
        stream.write(bytearray(json.dumps(content | {"version": version}).encode()))
        stream.close()
        if self._fs.exists(self._manifest(version)) or not self._fs.rename(draft, self._manifest(version)):
            self._fs.delete(draft, False)
            raise Conflict(f"version {version} exists")
        return version

    def _change(self, did: str, change, tries: int = 20) -> int:
        """Applies a change of the list of shards to the newest version, again if another writer was faster."""
        for _ in range(tries):
            now = self.manifest()
            new = change([Shard(**x) for x in now["shards"]])
            try:
                return self._commit(now["version"] + 1, {"shards": [vars(s) for s in new], "schema": now["schema"], "did": did})
            except Conflict:
                continue
        raise Conflict(f"{tries} other commits came first")

    # --- writing ---------------------------------------------------------------------------------------------------

    def _written(self, folder: str, arrival: str | None = None) -> list[Shard]:
        found, files = [], self._fs.listFiles(self._path(folder), True)
        while files.hasNext():
            status = files.next()
            path = status.getPath().toString()
            if path.endswith(".parquet") and status.getLen():
                found.append(Shard(path, int(status.getLen()), arrival or path.rsplit("/", 2)[1].rpartition("=")[2]))
        return sorted(found, key=lambda s: s.path)

    def _fits(self, df: DataFrame) -> None:
        have = StructType.fromJson(self.manifest()["schema"])
        if [(f.name, f.dataType) for f in have] != [(f.name, f.dataType) for f in df.schema]:
            raise ValueError("the arrival has another schema than the store")

    def append(self, df: DataFrame, arrival: str) -> int:
        self._fits(df)
        folder = f"{self.root}/data/{uuid.uuid4().hex}"
        df.write.parquet(folder)
        new = self._written(folder, arrival)
        return self._change(f"append {arrival}", lambda old: old + new)

    def append_each(self, df: DataFrame, arrival: F.Column) -> int:
        """Several arrivals in one pass over the rows; each is a version of its own, in the order of their names."""
        self._fits(df)
        folder, name = f"{self.root}/data/{uuid.uuid4().hex}", f"arrival_{uuid.uuid4().hex}"
        df.withColumn(name, arrival).write.partitionBy(name).parquet(folder)
        by: dict[str, list[Shard]] = {}
        for shard in self._written(folder):
            by.setdefault(shard.arrival, []).append(shard)
        for each in sorted(by):
            self._change(f"append {each}", lambda old, new=by[each]: old + new)
        return self.version()

    def read(self, version: int | None = None) -> DataFrame:
        now = self.manifest(version)
        schema, paths = StructType.fromJson(now["schema"]), [x["path"] for x in now["shards"]]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    # --- compaction ------------------------------------------------------------------------------------------------

    @staticmethod
    def full_tiers(shards: list[Shard], target: int, fan_in: int) -> list[list[Shard]]:
        tiers: dict[int, list[Shard]] = {}
        for s in shards:
            if s.bytes < FULL * target:
                tiers.setdefault(int(math.log(max(s.bytes, 1), TIER_RATIO)), []).append(s)
        return [tiers[t] for t in sorted(tiers) if len(tiers[t]) >= fan_in]

    def compact(self, target: int = TARGET_BYTES, fan_in: int = FAN_IN) -> int:
        """Merges one full tier after another, the smallest first, until there is none whose merge lessens the number of shards."""
        stuck: set[frozenset[str]] = set()
        while tiers := [t for t in self.full_tiers(self.shards(), target, fan_in) if frozenset(s.path for s in t) not in stuck]:
            if not self._merge(tiers[0], target):
                stuck.add(frozenset(s.path for s in tiers[0]))
        return self.version()

    def _merge(self, old: list[Shard], target: int) -> bool:
        """Writes the rows of a tier as shards of the target size; false, and nothing changes, if they are not fewer."""
        folder = f"{self.root}/data/{uuid.uuid4().hex}"
        schema = StructType.fromJson(self.manifest()["schema"])
        wanted = {"spark.sql.files.maxPartitionBytes": str(target), "spark.sql.files.minPartitionNum": "1", "spark.sql.files.openCostInBytes": "0"}
        kept = {k: self.spark.conf.get(k, None) for k in wanted}
        try:
            for k, v in wanted.items():
                self.spark.conf.set(k, v)
            self.spark.read.schema(schema).parquet(*[s.path for s in old]).write.parquet(folder)
        finally:
            for k, v in kept.items():
                self.spark.conf.unset(k) if v is None else self.spark.conf.set(k, v)
        new, gone = self._written(folder, "merged"), {s.path for s in old}
        if len(new) >= len(old):
            self._fs.delete(self._path(folder), True)
            return False

        def change(now: list[Shard]) -> list[Shard]:
            if not gone <= {s.path for s in now}:
                raise Conflict("merged shards are not listed any more")
            return [s for s in now if s.path not in gone] + new

        self._change(f"merge {len(old)} into {len(new)}", change)
        return True

    def vacuum(self, keep: int = 1, grace: float = GRACE_SECONDS) -> int:
        """Removes shards and manifests of all versions but the newest `keep`. A file that no version has listed may belong to an
        append or a merge that has yet to commit: it goes only when it is older than `grace` seconds. Returns the number of files."""
        versions = self.versions()
        kept = {s.path for v in versions[-keep:] for s in self.shards(v)}
        dropped = {s.path for v in versions[:-keep] for s in self.shards(v)} - kept
        for v in versions[:-keep]:
            self._fs.delete(self._manifest(v), False)
        removed, folder = 0, self._path(f"{self.root}/data")
        files = self._fs.listFiles(folder, True) if self._fs.exists(folder) else None
        while files is not None and files.hasNext():
            status = files.next()
            path = status.getPath().toString()
            if path in dropped or path not in kept and time.time() - status.getModificationTime() / 1000 > grace:
                removed += bool(self._fs.delete(status.getPath(), False))
        return removed
