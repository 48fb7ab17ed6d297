"""Sharding with size-tiered compaction and a versioned manifest.

A store is a folder with immutable Parquet shards and manifests.  Appending writes the arrivals as small shards;
compaction merges the shards of one size tier into files of a target size, tier by tier, until no tier holds enough
shards.  A merge reads whole shards into tasks of about the target size, so that no row is shuffled.  Every change
writes a new manifest beside the old ones and commits it with one rename that fails if that version exists, so readers
see a version whole or not at all.  Rows are handled by DataFrame operations alone.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import scratch

MB = 1 << 20


class CommitConflict(RuntimeError):
    """Another writer has committed this version."""


@dataclass(frozen=True)
class Settings:
    arrival_rows: int = 4096
    target_bytes: int = 128 * MB
    least_bytes: int = 1 * MB
    ratio: int = 4
    fan_in: int = 4
    codec: str = "zstd"


class Store:
    """Shards and manifests under a path that driver and executors share."""

    def __init__(self, spark: SparkSession, path: str, settings: Settings = Settings()):
        self.spark, self.path, self.settings = spark, path.rstrip("/"), settings

    # -- manifest ---------------------------------------------------------------------------------

    def _fs(self):  # noqa: ANN202
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(self.path)
        return jvm, at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def version(self) -> int:
        """The newest committed version; 0 for a new store."""
        jvm, fs = self._fs()
        at = jvm.org.apache.hadoop.fs.Path(f"{self.path}/manifest")
        if not fs.exists(at):
            return 0
        names = [s.getPath().getName() for s in fs.listStatus(at)]
        return max((int(n[1:]) for n in names if n.startswith("v")), default=0)

    def manifest(self, version: int | None = None) -> DataFrame:
        """file, bytes, rows, generation, version (that added the file) of a version's files."""
        at = self.version() if version is None else version
        return self.spark.read.schema("file string, bytes bigint, rows bigint, generation int, version bigint").parquet(f"{self.path}/manifest/v{at:09d}")

    def _commit(self, rows: DataFrame, version: int) -> None:
        """Write a manifest aside, then give it its name; the rename never replaces a version that is there."""
        jvm, fs = self._fs()
        aside, final = f"{self.path}/aside-{uuid.uuid4().hex}", f"{self.path}/manifest/v{version:09d}"
        rows.coalesce(1).write.parquet(aside)
        hadoop = jvm.org.apache.hadoop.fs
        fs.mkdirs(hadoop.Path(f"{self.path}/manifest"))
        kind = getattr(hadoop, "Options$Rename")
        options = self.spark.sparkContext._gateway.new_array(kind, 1)
        options[0] = kind.NONE
        conf = self.spark.sparkContext._jsc.hadoopConfiguration()
        try:
            hadoop.FileContext.getFileContext(fs.getUri(), conf).rename(hadoop.Path(aside), hadoop.Path(final), options)
        except Exception as e:
            fs.delete(hadoop.Path(aside), True)
            if fs.exists(hadoop.Path(final)):
                raise CommitConflict(f"version {version} is there already") from e
            raise

    def _measure(self, folder: str, generation: int, version: int) -> DataFrame:
        """The files that a job wrote, with their sizes and rows; only file metadata and no column is read."""
        shards = self.spark.read.parquet(folder)
        meta = shards.metadataColumn("_metadata")  # also where the data have a column of this name
        files = shards.select(meta["file_path"].alias("file"), meta["file_size"].alias("bytes"))
        counted = files.groupBy("file", "bytes").agg(F.count(F.lit(1)).alias("rows"))
        return counted.select("file", "bytes", "rows", F.lit(generation).alias("generation"), F.lit(version).cast("bigint").alias("version"))

    # -- changes ----------------------------------------------------------------------------------

    def append(self, df: DataFrame) -> int:
        """Write arrivals as shards of at most `arrival_rows` rows and commit a version with them."""
        at = self.version()
        folder = f"{self.path}/shards/{uuid.uuid4().hex}"
        df.write.option("maxRecordsPerFile", self.settings.arrival_rows).option("compression", self.settings.codec).parquet(folder)
        new = self._measure(folder, 0, at + 1)
        self._commit(self.manifest(at).unionByName(new) if at else new, at + 1)
        return at + 1

    def tiers(self, version: int | None = None) -> DataFrame:
        """The manifest with each file's tier: powers of `ratio` above `least_bytes`; files that are large enough have none."""
        s = self.settings
        tier = F.floor(F.log(float(s.ratio), F.greatest(F.col("bytes"), F.lit(s.least_bytes)) / s.least_bytes)).cast("int")
        return self.manifest(version).withColumn("tier", F.when(2 * F.col("bytes") < s.target_bytes, tier))

    def compact_once(self) -> int | None:
        """Merge the lowest tier that holds `fan_in` shards or more; the new version, or None if there is none.

        The shards of a tier are alike in size.  They are read in order of size with splits of the target size, which
        puts whole shards side by side in one task until the target is reached; each task writes one file."""
        s, at = self.settings, self.version()
        if not at:
            return None
        tiers = self.tiers(at)
        full = self.full()
        if full is None:
            return None
        chosen = tiers.filter(F.col("tier") == full)
        names = [r[0] for r in chosen.orderBy("bytes", "file").select("file").collect()]  # names only, as Spark's own file index holds them
        generation = chosen.agg(F.max("generation")).first()[0] + 1
        folder = f"{self.path}/shards/{uuid.uuid4().hex}"
        reader = self.spark.newSession()  # its settings are its own
        reader.conf.set("spark.sql.files.maxPartitionBytes", str(s.target_bytes))
        reader.conf.set("spark.sql.files.openCostInBytes", "0")
        reader.conf.set("spark.sql.files.minPartitionNum", "1")
        reader.read.parquet(*names).write.option("compression", s.codec).parquet(folder)
        rest = tiers.filter((F.col("tier") != full) | F.col("tier").isNull()).drop("tier")
        self._commit(rest.unionByName(self._measure(folder, generation, at + 1)), at + 1)
        return at + 1

    def compact(self, most: int | None = None) -> int:
        """Merge until no tier is full; the newest version.

        A merge that makes as many files as it read is the last one, so the loop ends; with `most`, RuntimeError is raised
        if after so many merges a tier is still full."""
        before, merges = self.manifest().count() if self.version() else 0, 0
        while self.compact_once() is not None:
            merges += 1
            after = self.manifest().count()
            if after >= before:
                break
            if merges == most and self.full() is not None:
                raise RuntimeError(f"a tier is still full after {most} merges")
            before = after
        return self.version()

    def full(self) -> int | None:
        """The lowest tier that holds `fan_in` shards or more."""
        return self.tiers().filter("tier is not null").groupBy("tier").count().filter(F.col("count") >= self.settings.fan_in).agg(F.min("tier")).first()[0]

    def read(self, version: int | None = None) -> DataFrame:
        """The rows of a version."""
        names = [r[0] for r in self.manifest(version).select("file").collect()]
        if not names:  # files without rows are in no manifest, but hold the columns
            return self.spark.read.option("recursiveFileLookup", "true").parquet(f"{self.path}/shards").limit(0)
        return self.spark.read.parquet(*names)

    def placement(self, key: str = "doc_id", version: int | None = None) -> DataFrame:
        """Which file of a version holds each row: key, file_no (by the files' smallest keys), file_rows, file_bytes, generation, version."""
        at = self.version() if version is None else version
        shards = self.read(at)
        where = shards.select(F.col(key).alias("_key"), shards.metadataColumn("_metadata")["file_path"].alias("file"))
        files = self.manifest(at).join(where.groupBy("file").agg(F.min("_key").alias("_first")), "file", "left")
        ordered = files.groupBy().agg(F.array_sort(F.collect_list(F.struct("_first", "file", "rows", "bytes", "generation", "version"))).alias("f"))
        numbered = ordered.select(F.posexplode("f").alias("file_no", "f")).select("file_no", "f.file", "f.rows", "f.bytes", "f.generation", "f.version")
        found = where.join(numbered, "file")
        return found.select(F.col("_key").alias(key), F.col("file_no").cast("bigint"), F.col("rows").alias("file_rows"), F.col("bytes").alias("file_bytes"), "generation", "version")

    def vacuum(self, keep: int = 1) -> int:
        """Delete the shard files that none of the newest `keep` versions names; how many went."""
        jvm, fs = self._fs()
        at = self.version()
        named: set[str] = set()
        for v in range(max(1, at - keep + 1), at + 1):
            named |= {r[0].rsplit("/", 1)[1] for r in self.manifest(v).select("file").collect()}
        gone, found = 0, fs.listFiles(jvm.org.apache.hadoop.fs.Path(f"{self.path}/shards"), True)
        while found.hasNext():
            p = found.next().getPath()
            if p.getName().endswith(".parquet") and p.getName() not in named:
                gone += fs.delete(p, False)
        return gone


def compacted(df: DataFrame, settings: Settings = Settings(), path: str | None = None) -> Store:
    """Append df to a new store and compact it.

    All columns and rows are kept as they are: nulls, repeated rows and very long texts need nothing special; columns
    whose names differ by case only can't be written by Parquet's reader rules and raise before anything is committed.
    An empty table commits a version whose files hold no rows."""
    store = Store(df.sparkSession, path or scratch(df.sparkSession, "shards"), settings)
    store.append(df)
    store.compact()
    return store
