"""Size-tiered compaction of immutable shards under a versioned manifest.

``append`` writes an arrival as small shards and commits them. ``compact``
groups live shards into tiers of similar size and rewrites a tier with enough
runs into files near the target size, without a shuffle. A version is one
manifest file that lists the live shards; it is written aside and renamed into
place, which fails if another writer took that version first. Readers see one
version whole; shards are never changed, so a lost writer leaves no trace.

Only DataFrame readers and writers touch rows; commits are file-system calls.
"""

from __future__ import annotations

import json
import uuid
from collections import defaultdict
from dataclasses import asdict, dataclass
from math import ceil, log

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

TARGET, RATIO, RUNS = 128 << 20, 4.0, 4


@dataclass(frozen=True)
class File:
    name: str
    size: int
    tier: int


class Conflict(RuntimeError):
    """Another writer committed this version first."""


class ShardStore:
    def __init__(self, spark: SparkSession, folder: str, target: int = TARGET, ratio: float = RATIO, runs: int = RUNS, compression: str = "zstd"):
        self.spark, self.folder = spark, folder.rstrip("/")
        self.target, self.ratio, self.runs, self.compression = target, ratio, runs, compression
        self.jvm = spark.sparkContext._jvm
        self.conf = spark.sparkContext._jsc.hadoopConfiguration()

    # files

    def path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")

    def fs(self):
        return self.path("x").getFileSystem(self.conf)

    def list(self, name: str) -> list:
        fs, path = self.fs(), self.path(name)
        return list(fs.listStatus(path)) if fs.exists(path) else []

    def version(self) -> int:
        """The newest committed version, 0 before the first."""
        return max((int(s.getPath().getName()[1:-5]) for s in self.list("manifest") if s.getPath().getName().startswith("v")), default=0)

    def manifest(self, version: int | None = None) -> dict:
        version = self.version() if version is None else version
        if not version:
            return {"version": 0, "schema": None, "files": []}
        stream = self.fs().open(self.path(f"manifest/v{version:09d}.json"))
        try:
            got = json.loads(self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()
        return got | {"files": [File(**f) for f in got["files"]]}

    def commit(self, base: int, schema: dict, files: list[File]) -> int:
        """Publish ``files`` as the version after ``base``; Conflict if that exists."""
        version, fs = base + 1, self.fs()
        aside, final = self.path(f"manifest/.{uuid.uuid4().hex}"), self.path(f"manifest/v{version:09d}.json")
        out = fs.create(aside, False)
        out.write(bytearray(json.dumps({"version": version, "schema": schema, "files": [asdict(f) for f in files]}).encode()))
        out.close()
        options = self.spark.sparkContext._gateway.new_array(self.jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), self.conf).rename(aside, final, options)
        except Exception as e:
            fs.delete(aside, False)
            if fs.exists(final):
                raise Conflict(str(final)) from e
            raise
        return version

    # rows

    def tier(self, size: int) -> int:
        """0 for the smallest shards; ``ratio`` times the size is one tier up; target size and more is the last."""
        small = self.target / self.ratio**6
        return min(6, max(0, 1 + int(log(max(size, 1) / small, self.ratio)))) if size > small else 0

    def write(self, rows: DataFrame) -> list[File]:
        name = f"shards/{uuid.uuid4().hex}"
        rows.write.option("compression", self.compression).parquet(f"{self.folder}/{name}")
        found = [(f"{name}/{s.getPath().getName()}", s.getLen()) for s in self.list(name) if s.getPath().getName().startswith("part-")]
        return [File(n, size, self.tier(size)) for n, size in found]

    def append(self, rows: DataFrame) -> int:
        """Write an arrival as shards, one for each of its partitions, and commit them.

        Rows are kept as they are: nulls, repeated rows, long texts and extra columns, which must be those of the
        store's schema. An empty arrival commits a version all the same.
        """
        base = self.manifest()
        schema = json.loads(rows.schema.json())
        if base["schema"] not in (None, schema):
            raise ValueError("the arrival has another schema than the store")
        return self.commit(base["version"], schema, base["files"] + self.write(rows))

    def read(self, version: int | None = None, files: list[File] | None = None) -> DataFrame:
        """The rows of a version, or of some of its files; none for an empty one."""
        got = self.manifest(version)
        files = got["files"] if files is None else files
        if got["schema"] is None:
            raise ValueError("the store has no version yet")
        schema = StructType.fromJson(got["schema"])
        return self.spark.read.schema(schema).parquet(*self.paths(files)) if files else self.spark.createDataFrame([], schema)

    def paths(self, files: list[File]) -> list[str]:
        """The folders of these files where nothing else lies in them, which Spark lists in parallel; else the files."""
        by_folder: dict[str, list[str]] = defaultdict(list)
        for f in files:
            by_folder[f.name.rsplit("/", 1)[0]].append(f.name)
        out = []
        for folder, names in by_folder.items():
            there = sum(x.getPath().getName().startswith("part-") for x in self.list(folder))
            out += [f"{self.folder}/{folder}"] if there == len(names) else [f"{self.folder}/{n}" for n in names]
        return out

    def plan(self, files: list[File]) -> list[list[File]]:
        """Tiers to merge: ``runs`` shards or more of similar size, below the target size."""
        tiers: dict[int, list[File]] = defaultdict(list)
        for f in files:
            if f.size < self.target / 2:
                tiers[f.tier].append(f)
        return [sorted(t, key=lambda f: (f.size, f.name)) for _, t in sorted(tiers.items()) if len(t) >= self.runs]

    def compact(self) -> int:
        """Merge until no tier has enough runs; each round commits one version.

        A tier becomes files of the target size, or one file if it is smaller.
        Splits of its shards are grouped, not shuffled: rows of a shard stay
        together and no key decides where a row goes.
        """
        while groups := self.plan((base := self.manifest())["files"]):
            merged, gone = [], set()
            for group in groups:
                count = max(1, ceil(sum(f.size for f in group) / self.target))
                if count >= len(group):
                    continue
                rows = self.read(base["version"], group)
                merged += self.write(rows.coalesce(count))
                gone |= {f.name for f in group}
            if not gone:
                break
            self.commit(base["version"], base["schema"], [f for f in base["files"] if f.name not in gone] + merged)
        return self.version()

    def expire(self, keep: int = 1) -> int:
        """Delete the shards and manifests that the newest ``keep`` versions do not list."""
        newest = self.version()
        live = {f.name for v in range(max(1, newest - keep + 1), newest + 1) for f in self.manifest(v)["files"]}
        fs, n = self.fs(), 0
        for folder in self.list("shards"):
            name = f"shards/{folder.getPath().getName()}"
            for s in self.list(name):
                if s.getPath().getName().startswith("part-") and f"{name}/{s.getPath().getName()}" not in live:
                    n += fs.delete(s.getPath(), False)
        for v in range(1, newest - keep + 1):
            fs.delete(self.path(f"manifest/v{v:09d}.json"), False)
        return n
