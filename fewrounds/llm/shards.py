"""Sharding by size-tiered compaction.

Arrivals are appended as small immutable shards, one Parquet file each.  Shards of like size form a tier; a tier that
holds ``fan_in`` shards is merged into files of about ``target_bytes``.  Spark's own file packing does the merging: it
deals the tier's files, largest first, into read tasks of the target size, and each task writes one file, so nothing is
shuffled.  Every change ends in one manifest, a JSON file of a new version, put in place whole and only if the version
doesn't exist: by a hard link on a file system of this machine, elsewhere by a rename that fails where the target exists,
as HDFS has it.  (Stores of objects whose rename overwrites need a committer of their own; don't share a root between
writers there.)  Readers see whole versions only, and a batch that is in the manifest is not appended again, so a lost
writer just starts anew.  Shards are named by their number in the order of commits.

Writers and readers may work on one root at once: nothing that a version of the last ``VACUUM_SECONDS`` names, and no file
younger than that, is ever deleted, and only ``vacuum`` deletes.

Defined results: rows, columns, nulls and repeated rows stay as they come; an empty arrival adds a version without
shards; a lost writer leaves files that no manifest names, which ``vacuum`` deletes once they are old.
"""

from __future__ import annotations

import json
import math
import os
import time
import uuid
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .spool import folder


@dataclass(frozen=True)
class Shard:
    file: str  # below the store's data folder
    size: int
    tier: int
    name: str = ""


VACUUM_SECONDS = 7 * 24 * 3600


class Superseded(RuntimeError):
    """Another writer was first with a change to the same shards."""


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = 512 << 20, fan_in: int = 8, small_bytes: int = 1 << 20):
        self.spark, self.root = spark, root.rstrip("/")
        self.target, self.fan_in, self.small = target_bytes, fan_in, small_bytes
        self.jvm = spark.sparkContext._jvm
        self.fs = self._path("").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self.fs.mkdirs(self._path("manifest"))
        self.fs.mkdirs(self._path("data"))

    def _path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}" if name else self.root)

    # versions

    def version(self) -> int:
        names = [s.getPath().getName() for s in self.fs.listStatus(self._path("manifest"))]
        return max((int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")), default=0)

    def manifest(self, version: int | None = None) -> dict:
        version = self.version() if version is None else version
        if not version:
            return {"version": 0, "batches": [], "shards": [], "named": 0}
        stream = self.fs.open(self._path(f"manifest/v{version}.json"))
        try:
            raw = self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return json.loads(raw)

    def shards(self, version: int | None = None) -> list[Shard]:
        return [Shard(*s) for s in self.manifest(version)["shards"]]

    def _commit(self, added: list[Shard], removed: set[str], batch: str | None) -> int:
        """Puts the next version in place; raises if another writer was first with changes to the same shards."""
        while True:
            now = self.manifest()
            have = {s[0] for s in now["shards"]}
            if not removed <= have:
                raise Superseded("another writer has merged these shards")
            if batch is not None and batch in now["batches"]:
                return now["version"]
            fresh = [[s.file, s.size, s.tier, f"shard-{now['named'] + k:08d}"] for k, s in enumerate(added)]
            new = {"version": now["version"] + 1, "batches": now["batches"] + ([batch] if batch is not None else []), "shards": [s for s in now["shards"] if s[0] not in removed] + fresh, "named": now["named"] + len(fresh)}
            draft = self._path(f"manifest/.{uuid.uuid4().hex}")
            stream = self.fs.create(draft, False)
            stream.write(bytearray(json.dumps(new).encode()))
            stream.close()
            final = self._path(f"manifest/v{new['version']}.json")
            try:
                if self._placed(draft, final):
                    return new["version"]
            finally:
                self.fs.delete(draft, False)

    def _placed(self, draft, final) -> bool:
        """Puts a file under its last name unless that exists."""
        if self.fs.getScheme() == "file":
            try:
                os.link(draft.toUri().getPath(), final.toUri().getPath())
            except FileExistsError:
                return False
            return True
        return not self.fs.exists(final) and bool(self.fs.rename(draft, final))

    # writing

    def tier_of(self, size: int) -> int:
        return 0 if size <= self.small else 1 + int(math.log(size / self.small, self.fan_in))

    def _write(self, df: DataFrame) -> list[Shard]:
        folder = uuid.uuid4().hex
        df.write.option("compression", "zstd").parquet(f"{self.root}/data/{folder}")
        files = [(s.getPath().getName(), s.getLen()) for s in self.fs.listStatus(self._path(f"data/{folder}"))]
        return [Shard(f"{folder}/{n}", int(size), self.tier_of(int(size))) for n, size in sorted(files) if n.endswith(".parquet")]

    def append(self, df: DataFrame, batch: str | None = None) -> int:
        """Adds the rows as small shards and commits them; a batch id that is known already adds nothing."""
        now = self.manifest()
        if batch is not None and batch in now["batches"]:
            return now["version"]
        return self._commit(self._write(df), set(), batch)

    @contextmanager
    def _packing(self):
        """Whole files are dealt into read tasks of the target size while this holds."""
        wanted = {"spark.sql.files.maxPartitionBytes": str(self.target), "spark.sql.files.openCostInBytes": "0", "spark.sql.files.minPartitionNum": "1"}
        before = {k: self.spark.conf.get(k, None) for k in wanted}
        try:
            for k, v in wanted.items():
                self.spark.conf.set(k, v)
            yield
        finally:
            for k, v in before.items():
                self.spark.conf.unset(k) if v is None else self.spark.conf.set(k, v)

    def compact(self) -> int:
        """Merges every tier that has ``fan_in`` shards, until none has; shards near the target size rest."""
        while True:
            tiers: dict[int, list[Shard]] = {}
            for s in self.shards():
                if 2 * s.size <= self.target:
                    tiers.setdefault(s.tier, []).append(s)
            due = {t: own for t, own in tiers.items() if len(own) >= self.fan_in}
            if not due:
                return self.version()
            own = due[min(due)]
            with self._packing():
                merged = self._write(self.read_files([s.file for s in own]))
            if len(merged) >= len(own):  # nothing gained: the session doesn't pack files
                merged = self._write(self.read_files([s.file for s in own]).coalesce(max(1, -(-sum(s.size for s in own) // self.target))))
            try:
                self._commit(merged, {s.file for s in own}, None)
            except Superseded:  # another writer has merged some of them; what is due now is seen anew
                continue

    def vacuum(self, older_than: float = VACUUM_SECONDS) -> None:
        """Deletes data folders that were last written before ``older_than`` seconds ago and that no manifest younger
        than that, nor the last one, names."""
        limit = (time.time() - older_than) * 1000
        files = {s.getPath().getName(): s.getModificationTime() for s in self.fs.listStatus(self._path("manifest"))}
        versions = sorted(int(n[1:-5]) for n in files if n.startswith("v") and n.endswith(".json"))
        ended = {v: files[f"v{after}.json"] for v, after in zip(versions, versions[1:], strict=False)}  # when a version was replaced
        used = {s.file.split("/")[0] for v in versions if ended.get(v, limit) >= limit for s in self.shards(v)}
        for s in self.fs.listStatus(self._path("data")):
            if s.getPath().getName() not in used and s.getModificationTime() < limit:
                self.fs.delete(s.getPath(), True)

    # reading

    def read_files(self, files: list[str]) -> DataFrame:
        return self.spark.read.parquet(*(f"{self.root}/data/{f}" for f in files))

    def read(self, version: int | None = None) -> DataFrame:
        """The rows of a version that has shards."""
        return self.read_files([s.file for s in self.shards(version)])


def shared_folder(spark: SparkSession) -> str:
    """A new folder where all executors see it."""
    return f"{folder(spark)}/shards-{uuid.uuid4().hex}"


def sharded(docs: DataFrame, arrivals: int = 4, target_bytes: int = 64 << 20, fan_in: int = 4, root: str | None = None) -> tuple[ShardStore, DataFrame]:
    """Appends the rows in several arrivals, compacts after each, and gives the store and its last version."""
    spark = docs.sparkSession
    store = ShardStore(spark, root or shared_folder(spark), target_bytes, fan_in)
    turn = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(arrivals))
    for k in range(arrivals):
        store.append(docs.where(turn == k), f"arrival-{k}")
        store.compact()
    return store, store.read()
