"""Size-tiered shards of a table, under a versioned manifest.

Arrivals are appended as small immutable Parquet files. Files of similar size (one tier: sizes within a factor of ``growth``) are
merged, ``fan_in`` or more at once, into files of about ``target_bytes``; a file never spans two groups and is read once
a merge. A version is one manifest, a JSON list of the live files, created under its number in one
step that fails if the number exists, so that two writers can't both commit it; the loser reads the new manifest and tries again.
Readers see the files of one version only. Replaced files stay for readers of older versions until ``vacuum``, which spares what
writers have written and not yet committed: each leaves an intent before its first file.

A file's merges are bounded by the number of tiers, so each byte is rewritten a logarithmic number of times.

Defined cases: an empty arrival commits a version without new files; nulls, ties and repeated rows are rows like others; arrivals
must have the columns and types of the first, in any order, others are refused (as are names that clash only in case, by Spark); a store without a manifest
is version 0 and has no files.
"""

from __future__ import annotations

import json
import math
import time
import uuid
from collections import defaultdict
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


@dataclass(frozen=True)
class Shard:
    path: str
    bytes: int
    version: int


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = 128 << 20, growth: float = 4.0, fan_in: int = 4):
        self.spark, self.root, self.target, self.growth, self.fan_in = spark, root.rstrip("/"), target_bytes, growth, fan_in
        self._fs = self._path(root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _path(self, text: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(text)

    # --- manifests ---

    def version(self) -> int:
        """The newest committed version."""
        folder = self._path(f"{self.root}/manifest")
        if not self._fs.exists(folder):
            return 0
        names = [s.getPath().getName() for s in self._fs.listStatus(folder)]
        return max((int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json")), default=0)

    def shards(self, version: int | None = None) -> list[Shard]:
        version = self.version() if version is None else version
        if not version:
            return []
        stream = self._fs.open(self._path(self._manifest(version)))
        try:
            text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        return [Shard(**s) for s in json.loads(text)["shards"]]

    def _manifest(self, version: int) -> str:
        return f"{self.root}/manifest/v{version:010d}.json"

    def _publish(self, version: int, shards: list[Shard], schema: str) -> bool:
        """Commit a manifest: written aside whole, then renamed to its number, which must be new."""
        jvm, aside = self.spark._jvm, self._path(f"{self.root}/manifest/.{uuid.uuid4().hex}")
        stream = self._fs.create(aside, False)
        stream.write(bytearray(json.dumps({"version": version, "schema": json.loads(schema), "shards": [asdict(s) for s in shards]}), "utf-8"))
        stream.close()
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._fs.getUri(), self.spark._jsc.hadoopConfiguration())
        options = self.spark.sparkContext._gateway.new_array(jvm.org.apache.hadoop.fs.Options.Rename, 0)
        try:
            context.rename(aside, self._path(self._manifest(version)), options)
            return True
        except Exception as error:
            self._fs.delete(aside, False)
            if "FileAlreadyExists" in str(error) or "exists" in str(error):
                return False
            raise

    def _schema(self, version: int) -> str | None:
        if not version:
            return None
        stream = self._fs.open(self._path(self._manifest(version)))
        try:
            return json.dumps(json.loads(self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))["schema"])
        finally:
            stream.close()

    # --- writing ---

    def _write(self, df: DataFrame) -> tuple[str, list[tuple[str, int]]]:
        """Files of df under a new folder, with sizes; Spark's committer keeps one attempt of each task. An intent stands before the first
        file, so that vacuum leaves the folder alone until its version is committed."""
        name = uuid.uuid4().hex
        self._fs.create(self._path(f"{self.root}/intents/{name}"), False).close()
        df.write.option("compression", "zstd").parquet(f"{self.root}/data/{name}")
        return name, self._listed(f"{self.root}/data/{name}")

    def _claim(self, name: str) -> None:
        """Take a written folder for a commit: from now on vacuum can't declare its intent dead. One rename decides between the two."""
        self._fs.mkdirs(self._path(f"{self.root}/commits"))
        intent = self._path(f"{self.root}/intents/{name}")
        if not self._fs.exists(intent) or not self._fs.rename(intent, self._path(f"{self.root}/commits/{name}")):
            raise RuntimeError(f"the files of {name} were given up by a vacuum before their commit; write them again")

    def _done(self, name: str) -> None:
        self._fs.delete(self._path(f"{self.root}/commits/{name}"), False)

    def _listed(self, folder: str) -> list[tuple[str, int]]:
        if not self._fs.exists(self._path(folder)):
            return []
        found = self._fs.listFiles(self._path(folder), True)
        files = []
        while found.hasNext():
            status = found.next()
            if status.getPath().getName().endswith(".parquet"):
                files.append((status.getPath().toString(), int(status.getLen())))
        return sorted(files)

    def append(self, df: DataFrame) -> int:
        """Commit the rows of df as new small shards; returns the version."""
        schema = self._schema(self.version())
        fitted = self._fitted(df, schema)
        name, files = self._write(fitted)
        self._claim(name)
        while True:
            now = self.version()
            self._fitted(df, self._schema(now))  # another writer may have come first
            new = [Shard(p, b, now + 1) for p, b in files]
            if self._publish(now + 1, self.shards(now) + new, self._schema(now) or fitted.schema.json()):
                self._done(name)
                return now + 1

    @staticmethod
    def _fitted(df: DataFrame, schema: str | None) -> DataFrame:
        """df with its columns in the store's order; another set of columns or other types are refused."""
        if schema is None:
            return df
        known = StructType.fromJson(json.loads(schema))
        types = {f.name: f.dataType.simpleString() for f in known}
        if len(df.columns) != len(types) or {f.name: f.dataType.simpleString() for f in df.schema} != types:
            raise ValueError(f"the store has columns {types}, the arrival {dict(df.dtypes)}")
        return df.select(*types)

    def tier(self, size: int) -> int:
        """Tier 0 is target-sized; each tier below is smaller by the growth factor."""
        return max(0, math.ceil(math.log(self.target / max(size, 1), self.growth)))

    def plan(self, shards: list[Shard]) -> list[list[Shard]]:
        """Groups to merge: shards of one tier, filled in order of size up to the target, fan_in or more."""
        tiers = defaultdict(list)
        for s in shards:
            if (k := self.tier(s.bytes)) > 0:
                tiers[k].append(s)
        groups = []
        for k in sorted(tiers, reverse=True):
            group, held = [], 0
            for s in sorted(tiers[k], key=lambda s: (s.bytes, s.path)):
                if group and held + s.bytes > self.target:
                    groups.append(group)
                    group, held = [], 0
                group.append(s)
                held += s.bytes
            groups.append(group)
        return [g for g in groups if len(g) >= self.fan_in or len(g) > 1 and sum(s.bytes for s in g) >= 0.75 * self.target]

    def compact(self) -> int:
        """Merge until no tier holds a group to merge; returns the version. Each commit leaves fewer shards, so it ends."""
        while True:
            now = self.version()
            groups = self.plan(self.shards(now))
            if not groups:
                return now
            name, merged = self._merge(groups)
            self._claim(name)
            gone = {s.path for g in groups for s in g}
            while True:
                now = self.version()
                live = self.shards(now)
                if not gone <= {s.path for s in live}:
                    break  # another compaction took some of them: plan anew
                if self._publish(now + 1, [s for s in live if s.path not in gone] + [Shard(p, b, now + 1) for p, b in merged], self._schema(now)):
                    break
            self._done(name)

    def _merge(self, groups: list[list[Shard]]) -> tuple[str, list[tuple[str, int]]]:
        """All groups in one job, a task and a file each: rows go by their file's group number, which is at most a target in size."""
        number = {s.path: k for k, g in enumerate(groups) for s in g}
        lookup = self.spark.createDataFrame([(p.rpartition("/data/")[2], k) for p, k in number.items()], "file string, grp int")
        rows = self.spark.read.schema(StructType.fromJson(json.loads(self._schema(self.version())))).parquet(*number)
        data = rows.select(F.struct(*rows.columns).alias("row"), F.element_at(F.split(F.col("_metadata.file_path"), "/data/"), -1).alias("file"))
        joined = data.join(F.broadcast(lookup), "file")  # one short row a merged file
        placed = joined.repartitionById(len(groups), F.col("grp")).select("row.*")
        return self._write(placed)

    # --- reading ---

    def read(self, version: int | None = None) -> DataFrame:
        """The rows of one version (the newest by default), with the manifest's schema."""
        version = self.version() if version is None else version
        files, schema = [s.path for s in self.shards(version)], self._schema(version)
        known = StructType.fromJson(json.loads(schema)) if schema else "empty int"
        return self.spark.read.schema(known).parquet(*files) if files else self.spark.createDataFrame([], known)

    def _names(self, folder: str, before: float | None = None) -> set[str]:
        """Names in a folder, of entries last changed before a time."""
        if not self._fs.exists(self._path(folder)):
            return set()
        return {s.getPath().getName() for s in self._fs.listStatus(self._path(folder)) if before is None or s.getModificationTime() / 1000 < before}

    def vacuum(self, keep: int = 1, patience: float = 7 * 86_400) -> int:
        """Delete files that none of the newest keep versions lists and that no writer is about to commit; returns how many.

        A writer is given ``patience`` seconds from its intent to its commit; after that the intent is declared dead, by a rename
        that its writer's claim can't have won too. Files are listed first, intents next and manifests last: a file whose intent is gone by
        then was committed before the manifests are read.
        """
        files = self._listed(f"{self.root}/data")
        for name in self._names(f"{self.root}/intents", time.time() - patience):
            self._fs.mkdirs(self._path(f"{self.root}/dead"))
            self._fs.rename(self._path(f"{self.root}/intents/{name}"), self._path(f"{self.root}/dead/{name}"))
        spared = self._names(f"{self.root}/intents") | self._names(f"{self.root}/commits")
        now = self.version()
        live = {s.path for v in range(max(1, now - keep + 1), now + 1) for s in self.shards(v)}
        gone = [p for p, _ in files if p not in live and p.rpartition("/data/")[2].partition("/")[0] not in spared]
        for p in gone:
            self._fs.delete(self._path(p), False)
        for v in range(1, now - keep + 1):
            self._fs.delete(self._path(self._manifest(v)), False)
        return len(gone)


def arrivals(df: DataFrame, key: str, shares: tuple[int, ...] = (8, 4, 2, 1, 1)) -> list[DataFrame]:
    """df cut by a hash of key into arrivals whose sizes are as the shares."""
    total, low, made = sum(shares), 0, []
    slot = F.pmod(F.xxhash64(key, F.lit(3)), F.lit(total))
    for share in shares:
        made.append(df.filter((slot >= low) & (slot < low + share)))
        low += share
    return made
