"""Sharding by size-tiered compaction, with DataFrame operations only.

Arrivals are appended as small immutable shards. Shards of similar size are merged, a handful at
a time, until they reach a target size. What the store holds is said by the newest manifest
alone; a manifest is one file that is written aside and put into place in one step that fails
where the place is taken. A reader sees all of a change or none; of two writers of the same
version one fails, reads the newer manifest and applies its change to that.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace
from functools import reduce

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TARGET_BYTES = 128 << 20
FAN_IN = 4
#: Manifests of up to this many shards are broadcast, at some 200 bytes each; longer ones are joined.
BROADCAST_SHARDS = 50_000
#: Merges in one job: each is one task that reads its shards and writes one file.
MERGES_PER_JOB = 64


@dataclass(frozen=True)
class Shard:
    path: str
    rows: int
    bytes: int
    tier: int


@dataclass(frozen=True)
class Manifest:
    version: int
    shards: tuple[Shard, ...]


class VersionTaken(Exception):
    """Another writer has committed this version."""


class ShardsGone(Exception):
    """Another writer has merged these shards already."""


def plan_merges(shards, target: int = TARGET_BYTES, fan_in: int = FAN_IN, final: bool = False) -> list[list[Shard]]:
    """Groups of similarly sized shards to merge: from the smallest, neighbours within a factor of fan_in whose sum stays within the target.

    A group has fan_in members at least, or is within a factor of two of the target; with
    `final`, two are enough. Shards of half the target or more are done.
    """
    small = sorted((s for s in shards if 2 * s.bytes < target), key=lambda s: (s.bytes, s.path))
    groups, group, total = [], [], 0
    for s in small:
        if group and (total + s.bytes > target or s.bytes > fan_in * max(1, group[0].bytes) and not final):
            groups.append(group)
            group, total = [], 0
        group.append(s)
        total += s.bytes
    groups.append(group)
    return [g for g in groups if len(g) >= (2 if final else fan_in) or len(g) > 1 and 2 * sum(s.bytes for s in g) >= target]


class ShardStore:
    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(f"{self.root}/manifests"))

    # manifests

    def versions(self) -> list[int]:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(f"{self.root}/manifests"))]
        return sorted(int(n[1:]) for n in names if n.startswith("v") and n[1:].isdigit())

    def manifest(self, version: int | None = None) -> Manifest:
        """The newest, or an older one that has not been vacuumed; version 0 is the empty store."""
        known = self.versions()
        version = (known[-1] if known else 0) if version is None else version
        if version == 0:
            return Manifest(0, ())
        rows = self.spark.read.text(f"{self.root}/manifests/v{version}").collect()  # one file, a line for each shard
        return Manifest(version, tuple(sorted((Shard(**json.loads(r[0])) for r in rows if r[0]), key=lambda s: s.path)))

    def commit(self, m: Manifest) -> Manifest:
        """Write the manifest aside as one file and put it into place, unless the version exists."""
        jvm = self.spark._jvm
        aside, place = f"{self.root}/manifests/.aside-v{m.version}-{jvm.java.util.UUID.randomUUID()}", f"{self.root}/manifests/v{m.version}"
        out = self._fs.create(self._path(aside), True)
        out.write(bytearray("\n".join(json.dumps(asdict(s)) for s in m.shards).encode()))
        out.close()
        try:
            if self._fs.getScheme() == "file":
                # a rename on a local disk replaces what is there; a second name for the file does not
                paths = [jvm.java.io.File(self._path(p).toUri().getPath()).toPath() for p in (place, aside)]
                jvm.java.nio.file.Files.createLink(*paths)
            else:
                options = jvm.java.lang.reflect.Array.newInstance(jvm.java.lang.Class.forName("org.apache.hadoop.fs.Options$Rename"), 1)
                options[0] = getattr(jvm.org.apache.hadoop.fs, "Options$Rename").NONE
                jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._path(place).toUri(), self.spark._jsc.hadoopConfiguration()).rename(self._path(aside), self._path(place), options)
        except Py4JJavaError as e:
            if not self._fs.exists(self._path(place)):
                raise
            raise VersionTaken(m.version) from e
        finally:
            self._fs.delete(self._path(aside), False)
        return m

    def change(self, shards_after) -> Manifest:
        """Commit shards_after(shards of the newest version), again from the start whenever another writer was quicker."""
        while True:
            now = self.manifest()
            try:
                return self.commit(Manifest(now.version + 1, tuple(shards_after(now.shards))))
            except VersionTaken:
                continue

    # shards

    def _written(self, folder: str, schema, tier: int) -> list[Shard]:
        """The files of a folder with their rows: sizes from the file system, row counts from the footers."""
        df = self.spark.read.schema(schema).parquet(folder)
        meta = df.metadataColumn("_metadata")
        found = df.select(meta.getField("file_path").alias("path"), meta.getField("file_size").alias("bytes")).groupBy("path", "bytes").count().collect()
        return [Shard(r["path"], r["count"], r["bytes"], tier) for r in found]

    def _folder(self) -> str:
        return f"{self.root}/shards/{self.spark._jvm.java.util.UUID.randomUUID()}"

    def append(self, arrivals: DataFrame) -> Manifest:
        """Each partition of the arrivals becomes one small shard; nothing is shuffled. No rows: a new version with the same shards."""
        folder = self._folder()
        arrivals.write.parquet(folder)
        added = self._written(folder, arrivals.schema, 0)
        return self.change(lambda shards: (*shards, *added))

    def merge(self, groups: list[list[Shard]], schema) -> Manifest:
        """Replace each group by one file. A task reads the shards of its group one after the other; no shuffle. ShardsGone, and nothing changed, where another writer has merged any of them."""
        made, folders = [], []
        for a in range(0, len(groups), MERGES_PER_JOB):
            part, folder = groups[a : a + MERGES_PER_JOB], self._folder()
            folders.append(folder)
            runs = [self.spark.read.schema(schema).parquet(*(s.path for s in g)).coalesce(1) for g in part]
            reduce(DataFrame.union, runs).write.parquet(folder)
            tier = 1 + max(s.tier for g in part for s in g)
            made += [replace(s, tier=tier) for s in self._written(folder, schema, tier)]
        gone = {s.path for g in groups for s in g}

        def after(shards):
            if not gone <= {s.path for s in shards}:
                raise ShardsGone(sorted(gone - {s.path for s in shards}))
            return (*(s for s in shards if s.path not in gone), *made)

        try:
            return self.change(after)
        except ShardsGone:
            for folder in folders:
                self._fs.delete(self._path(folder), True)
            raise

    def compact(self, schema, *, target: int = TARGET_BYTES, fan_in: int = FAN_IN, final: bool = False, vacuum: bool = False) -> Manifest:
        """Merge tier by tier until no group of similar shards is left; with `final` also the odd ones."""
        while groups := plan_merges(self.manifest().shards, target, fan_in, final):
            try:
                self.merge(groups, schema)
            except ShardsGone:
                continue  # plan anew from what the other writer has left
            if vacuum:
                self.vacuum()
        return self.manifest()

    def vacuum(self) -> None:
        """Delete manifests before the newest, and shards that only they named."""
        known = self.versions()
        live = {s.path for s in self.manifest().shards}
        for v in known[:-1]:
            for s in self.manifest(v).shards:
                if s.path not in live:
                    self._fs.delete(self._path(s.path), False)
            self._fs.delete(self._path(f"{self.root}/manifests/v{v}"), True)

    def read(self, schema, version: int | None = None) -> DataFrame:
        """The rows of a version, repeated rows as often as they came, with __shard, the file that holds each; the schema may have any columns but that one."""
        m = self.manifest(version)
        if not m.shards:
            return self.spark.createDataFrame([], schema).withColumn("__shard", F.lit(None).cast("string"))
        df = self.spark.read.schema(schema).parquet(*(s.path for s in m.shards))
        return df.withColumn("__shard", df.metadataColumn("_metadata").getField("file_path"))


def op5(spark, sf_dir: str) -> DataFrame:
    """For each document the shard that holds it after compaction, with the shard's size and tier."""
    from llm.store import table, workspace

    docs = table(spark, sf_dir, "documents")
    store = ShardStore(spark, workspace(spark, "shards"))
    store.append(docs)
    store.compact(docs.schema, vacuum=True)
    m = store.compact(docs.schema, final=True, vacuum=True)
    shards = spark.createDataFrame([(s.path, k, s.rows, s.bytes, s.tier, m.version) for k, s in enumerate(m.shards)], "__shard string, shard_id long, shard_rows long, shard_bytes long, tier int, version int")
    # texts become sizes and digests before anything moves; a manifest of bounded length goes to the rows
    rows = store.read(docs.schema).select("doc_id", *(c for c in ("source",) if c in docs.columns), F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"), "__shard")
    return rows.join(F.broadcast(shards) if len(m.shards) <= BROADCAST_SHARDS else shards, "__shard").drop("__shard")
