"""Size-tiered compaction of shards under a versioned manifest (DataFrame writers only on the data path).

Arrivals are appended as small immutable shards, one Parquet file each. A compaction takes the runs of one size tier
and rewrites them as files of about the target size; it never shuffles: files are read whole and written whole. What
the table holds is what the newest manifest lists. A manifest is a small JSON file, written under a temporary name and
renamed to its version, which must not exist: of two writers one fails, and readers see the old or the new version. The
rename is atomic where the file system's is (HDFS; a store of objects needs a committer that is). Every attempt writes to a
folder of its own, so a writer that is lost before its commit is in nobody's way. The last RETAIN versions stay readable;
vacuum() deletes what only older ones list, and what lost attempts have left ORPHAN_HOURS ago.
"""

from __future__ import annotations

import json
import math
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TARGET_BYTES = 128 << 20
#: Sizes within one tier differ by this factor at most.
TIER_FACTOR = 4
#: Runs of one tier that start a merge.
MIN_RUNS = 4
#: Versions that stay readable.
RETAIN = 8
#: Age at which a file that no version lists is taken for left behind.
ORPHAN_HOURS = 24


class ShardStore:
    """Immutable shards in a folder that all executors reach, and the manifest versions over them."""

    def __init__(self, spark: SparkSession, path: str, target_bytes: int = TARGET_BYTES, tier_factor: int = TIER_FACTOR, min_runs: int = MIN_RUNS) -> None:
        self.spark, self.path, self.target, self.factor, self.min_runs = spark, path.rstrip("/"), target_bytes, tier_factor, min_runs
        self._jvm = spark._jvm
        self._fs = self._path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(f"{self.path}/_manifests"))

    def _path(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(name)

    def versions(self) -> list[int]:
        found = self._fs.listStatus(self._path(f"{self.path}/_manifests"))
        return sorted(int(n[1:-5]) for s in found if (n := s.getPath().getName()).startswith("v") and n.endswith(".json"))

    def manifest(self, version: int | None = None) -> dict:
        """{"version", "schema", "next", "shards": [{"file", "bytes", "tier", "level"}]}; version 0 is empty."""
        version = max(self.versions(), default=0) if version is None else version
        if not version:
            return {"version": 0, "schema": None, "next": 0, "shards": []}
        stream = self._fs.open(self._path(f"{self.path}/_manifests/v{version:012d}.json"))
        try:
            return json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def _commit(self, manifest: dict) -> dict:
        """The next version. The rename is atomic and fails where that version exists."""
        manifest = manifest | {"version": manifest["version"] + 1}
        name = f"{self.path}/_manifests/v{manifest['version']:012d}.json"
        draft = self._path(f"{name}.{self._jvm.java.util.UUID.randomUUID().toString()}.tmp")
        out = self._fs.create(draft, False)
        try:
            out.write(bytearray(json.dumps(manifest).encode()))
        finally:
            out.close()
        if not self._moved(draft, self._path(name)):
            self._fs.delete(draft, False)
            raise RuntimeError(f"version {manifest['version']} was committed by another writer")
        return manifest

    def _moved(self, source, target) -> bool:
        """Renames unless target exists."""
        from py4j.protocol import Py4JJavaError

        hadoop, context = self._jvm.org.apache.hadoop.fs, self.spark.sparkContext
        options = context._gateway.new_array(hadoop.Options.Rename, 1)
        options[0] = hadoop.Options.Rename.NONE
        try:
            hadoop.FileContext.getFileContext(self._fs.getUri(), context._jsc.hadoopConfiguration()).rename(source, target, options)
        except Py4JJavaError as error:
            kind = error.java_exception.getClass().getSimpleName()
            if kind == "UnsupportedFileSystemException":  # a file system without FileContext
                return not self._fs.exists(target) and self._fs.rename(source, target)
            if kind == "FileAlreadyExistsException":
                return False
            raise
        return True

    def _tier(self, size: int) -> int:
        return int(math.log(max(size, 1), self.factor))

    def _landed(self, folder: str) -> list[dict]:
        """The files a finished job left in folder, by name."""
        found = sorted((s.getPath().getName(), s.getLen()) for s in self._fs.listStatus(self._path(f"{self.path}/{folder}")))
        return [{"file": f"{folder}/{n}", "bytes": size, "tier": self._tier(size)} for n, size in found if n.startswith("part-")]

    def _attempt(self) -> str:
        return self._jvm.java.util.UUID.randomUUID().toString()[:8]

    def append(self, rows: DataFrame, arrivals: int = 1) -> dict:
        """Every partition of rows becomes a small shard; one job writes them, and that many manifest versions list them, each its share."""
        now = self.manifest()
        schema = rows.schema.json()
        if now["schema"] not in (None, schema):
            raise ValueError("the arrivals' columns differ from the table's")
        folder = f"level0/batch-{now['next']:08d}-{self._attempt()}"
        rows.write.option("compression", "zstd").parquet(f"{self.path}/{folder}")
        landed = [x | {"level": 0} for x in self._landed(folder)]
        for k in range(arrivals):
            now = self._commit(now | {"schema": schema, "next": now["next"] + 1, "shards": now["shards"] + landed[k::arrivals]})
        return now

    def _plan(self, shards: list[dict]) -> Iterator[list[dict]]:
        """Runs of one tier below the target size, from the smallest tier."""
        tiers: dict[int, list[dict]] = {}
        for x in shards:
            if x["bytes"] < self.target * 3 // 4:
                tiers.setdefault(x["tier"], []).append(x)
        for _, runs in sorted(tiers.items()):
            if len(runs) >= self.min_runs:
                yield runs

    def compact(self, retain: int = RETAIN) -> dict:
        """Merges until no tier has enough runs. Each merge is one job without a shuffle and one manifest version; the last retain versions stay readable."""
        now = self.manifest()
        while runs := next(self._plan(now["shards"]), None):
            total = sum(x["bytes"] for x in runs)
            files = max(1, min(round(total / self.target), len(runs) // 2))
            folder = f"level{max(x['level'] for x in runs) + 1}/merge-{now['next']:08d}-{self._attempt()}"
            self.read(runs=runs).coalesce(files).write.option("compression", "zstd").parquet(f"{self.path}/{folder}")
            gone = {x["file"] for x in runs}
            landed = [x | {"level": max(r["level"] for r in runs) + 1} for x in self._landed(folder)]
            now = self._commit(now | {"next": now["next"] + 1, "shards": [x for x in now["shards"] if x["file"] not in gone] + landed})
            self.vacuum(retain)
        return now

    def vacuum(self, retain: int = RETAIN, orphan_hours: float = ORPHAN_HOURS) -> list[str]:
        """Deletes manifests but for the last retain ones, the files that only those listed, and old files that no manifest lists; returns the files."""
        versions = self.versions()
        listed = {v: {x["file"] for x in self.manifest(v)["shards"]} for v in versions}
        kept = set().union(*(listed[v] for v in versions[-retain:]))
        gone = set().union(*(listed[v] for v in versions[:-retain])) - kept if len(versions) > retain else set()
        for v in versions[:-retain]:
            self._fs.delete(self._path(f"{self.path}/_manifests/v{v:012d}.json"), False)
        limit = self._jvm.java.lang.System.currentTimeMillis() - orphan_hours * 3_600_000
        for level in self._fs.listStatus(self._path(self.path)):
            if level.isDirectory() and level.getPath().getName().startswith("level"):
                for folder in self._fs.listStatus(level.getPath()):
                    for f in self._fs.listStatus(folder.getPath()) if folder.getModificationTime() < limit else ():
                        name = f"{level.getPath().getName()}/{folder.getPath().getName()}/{f.getPath().getName()}"
                        if f.isFile() and f.getPath().getName().startswith("part-") and name not in kept:
                            gone.add(name)
        for name in sorted(gone):
            self._fs.delete(self._path(f"{self.path}/{name}"), False)
        return sorted(gone)

    def read(self, version: int | None = None, runs: list[dict] | None = None) -> DataFrame:
        """Rows of a version, or of some of its shards."""
        from pyspark.sql.types import StructType

        now = self.manifest(version)
        if now["schema"] is None:
            raise ValueError("nothing was appended yet")
        schema = StructType.fromJson(json.loads(now["schema"]))
        files = [f"{self.path}/{x['file']}" for x in (now["shards"] if runs is None else runs)]
        if not files:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*files)


def shard(docs: DataFrame, path: str, arrivals: int = 4, target_bytes: int = TARGET_BYTES) -> ShardStore:
    """Appends docs in arrivals, each a manifest version with its share of the small shards that one job writes, compacts after the last, and returns the store.

    Every row is kept with all its columns, repeated rows and nulls too; an empty table gives a store without rows.
    """
    store = ShardStore(docs.sparkSession, path, target_bytes)
    store.append(docs, arrivals)
    store.compact()
    return store


def shard_report(store: ShardStore) -> DataFrame:
    """Every row of the newest version with the shard it is in: doc_id, shard, level, version, n_chars, text_crc32."""
    version, file = store.manifest()["version"], F.input_file_name()
    text = F.coalesce(F.col("text"), F.lit(""))
    return store.read().select(
        "doc_id",
        F.concat_ws("/", F.regexp_extract(file, r"/((?:batch|merge)-\d+)-[0-9a-f]+/", 1), F.regexp_extract(file, r"/part-(\d+)", 1)).alias("shard"),
        F.regexp_extract(file, r"/level(\d+)/", 1).cast("int").alias("level"),
        F.lit(version).cast("long").alias("version"),
        F.length(text).cast("long").alias("n_chars"),
        F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"),
    )
