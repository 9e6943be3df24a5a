"""Size-tiered compaction of immutable shards with a versioned manifest (operator 4).

A store is a folder: ``data/<batch>/part-*.parquet`` are immutable shards and
``versions/<number>`` lists the live ones, a JSON line each. A commit renames a finished list
to the next number and fails if that exists, so readers see all of a change or nothing, and
of two writers one wins. A writer announces its batch under ``intents/`` before it writes and
withdraws that after its commit, so cleaning never takes shards that are about to be
committed. Only DataFrame functions touch rows.
"""

from __future__ import annotations

import json
import uuid
from collections import defaultdict
from collections.abc import Callable
from dataclasses import asdict, dataclass
from functools import reduce

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from binflow.storage import hadoop_path

#: runs that one job merges, and the age at which an announced write counts as given up
RUNS_AT_ONCE, FORGOTTEN_MS = 512, 7 * 24 * 3600 * 1000
UNION_SETTING = "spark.sql.unionOutputPartitioning"
MANIFEST = "path string, bytes bigint, sequence bigint"


class CommitConflict(Exception):
    """Another writer has committed this version."""


@dataclass(frozen=True)
class Shard:
    path: str
    bytes: int
    sequence: int


class ShardStore:
    """Append, compact and read one store.

    ``target_bytes`` is the size of finished shards; ``fan_in`` similarly sized shards make a
    run that is merged; ``floor_bytes`` is the width of the lowest tier.
    """

    def __init__(self, spark: SparkSession, path: str, target_bytes: int = 128 << 20, fan_in: int = 4, floor_bytes: int = 1 << 20):
        self.spark, self.path = spark, path.rstrip("/")
        self.target, self.fan_in, self.floor = target_bytes, fan_in, floor_bytes

    def version(self) -> int:
        """Number of the last commit; 0 before the first."""
        fs, p = hadoop_path(self.spark, f"{self.path}/versions")
        if not fs.exists(p):
            return 0
        return max((int(s.getPath().getName()) for s in fs.listStatus(p) if s.getPath().getName().isdigit()), default=0)

    def manifest(self, version: int | None = None) -> list[Shard]:
        """Live shards of a version, in order of arrival. One entry a file: its size follows the number of files, not of rows."""
        version = self.version() if version is None else version
        if not version:
            return []
        rows = self.spark.read.schema(MANIFEST).json(f"{self.path}/versions/{version}").orderBy("sequence", "path").collect()
        return [Shard(**r.asDict()) for r in rows]

    def _commit(self, base: int, shards: list[Shard]) -> int:
        """Make ``shards`` the state after version ``base``."""
        jvm = self.spark.sparkContext._jvm
        fs, draft = hadoop_path(self.spark, f"{self.path}/versions/_draft-{uuid.uuid4().hex}")
        stream = fs.create(draft, False)
        stream.write(bytearray("".join(json.dumps(asdict(s)) + "\n" for s in shards).encode()))
        stream.close()
        final = jvm.org.apache.hadoop.fs.Path(f"{self.path}/versions/{base + 1}")
        rename = jvm.org.apache.hadoop.fs.Options.Rename
        how = self.spark.sparkContext._gateway.new_array(rename, 1)
        how[0] = rename.NONE
        try:
            jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), fs.getConf()).rename(draft, final, how)
        except Py4JJavaError as e:
            fs.delete(draft, False)
            if not fs.exists(final):
                raise
            raise CommitConflict(f"version {base + 1} exists") from e
        return base + 1

    def _announce(self, batch: str) -> None:
        fs, p = hadoop_path(self.spark, f"{self.path}/intents/{batch}")
        fs.create(p, False).close()

    def _withdraw(self, batch: str) -> None:
        fs, p = hadoop_path(self.spark, f"{self.path}/intents/{batch}")
        fs.delete(p, False)

    def _files(self, folder: str, sequence: int) -> list[Shard]:
        fs, p = hadoop_path(self.spark, folder)
        found = [(s.getPath().getName(), s.getLen()) for s in fs.listStatus(p) if s.getPath().getName().startswith("part-")] if fs.exists(p) else []
        return [Shard(f"{folder}/{name}", size, sequence) for name, size in sorted(found)]

    def append(self, rows: DataFrame) -> int:
        """Add an arrival as one shard per task and commit it; returns the version."""
        return self.append_dealt(rows, None)[-1]

    def append_dealt(self, rows: DataFrame, deal: Column | None, arrivals: int = 1, after_each: Callable[[], None] = lambda: None) -> list[int]:
        """Write rows once, dealt to ``arrivals`` by the number ``deal``, and commit one arrival after the other; returns the versions.

        The rows are read once. A commit that another writer has overtaken is tried again on
        the newer version: shards are only added.
        """
        batch = f"{self.version() + 1}-{uuid.uuid4().hex}"
        marks = [batch] if deal is None else [f"{batch}@__arrival={k}" for k in range(arrivals)]
        for mark in marks:
            self._announce(mark)
        folder, versions = f"{self.path}/data/{batch}", []
        if deal is None:
            rows.write.parquet(folder)
        else:
            rows.withColumn("__arrival", deal).write.partitionBy("__arrival").parquet(folder)
        for k in range(arrivals):
            while True:
                base = self.version()
                try:
                    versions.append(self._commit(base, [*self.manifest(base), *self._files(folder if deal is None else f"{folder}/__arrival={k}", base + 1)]))
                    break
                except CommitConflict:
                    continue
            self._withdraw(marks[k])
            after_each()
        return versions

    def tier(self, size: int) -> int:
        """Power of ``fan_in`` times the floor that a size reaches."""
        t, edge = 0, self.floor
        while size > edge and edge < self.target:
            t, edge = t + 1, edge * self.fan_in
        return t

    def plan(self, shards: list[Shard]) -> list[list[Shard]]:
        """Runs to merge: similarly sized unfinished shards, ``fan_in`` at least, cut where they fill the target."""
        tiers: dict[int, list[Shard]] = defaultdict(list)
        for s in shards:
            if s.bytes < self.target // 2:
                tiers[self.tier(s.bytes)].append(s)
        runs = []
        for _, members in sorted(tiers.items()):
            if len(members) < self.fan_in:
                continue
            run, size = [], 0
            for s in members:
                if run and size + s.bytes > self.target:
                    runs.append(run)
                    run, size = [], 0
                run.append(s)
                size += s.bytes
            runs.append(run)
        return [r for r in runs if len(r) > 1]

    def _merge(self, runs: list[list[Shard]], folder: str) -> None:
        """One task and one file a run: a union would otherwise put one-task inputs together into one task."""
        parts = [self.spark.read.parquet(*(s.path for s in run)).coalesce(1) for run in runs]
        before = self.spark.conf.get(UNION_SETTING, "true")
        self.spark.conf.set(UNION_SETTING, "false")
        try:
            reduce(DataFrame.union, parts).write.parquet(folder)
        finally:
            self.spark.conf.set(UNION_SETTING, before)

    def compact(self) -> int:
        """Merge all planned runs, again while any are left, one commit a pass; returns the version.

        Every run is read by one task and written as one file, without a shuffle; RUNS_AT_ONCE
        runs make a job. If another writer commits meanwhile, the pass is planned anew.
        """
        while True:
            base = self.version()
            shards = self.manifest(base)
            runs = self.plan(shards)
            if not runs:
                return base
            batch = f"{base + 1}-{uuid.uuid4().hex}"
            self._announce(batch)
            new = []
            for at in range(0, len(runs), RUNS_AT_ONCE):
                folder = f"{self.path}/data/{batch}/{at}"
                self._merge(runs[at : at + RUNS_AT_ONCE], folder)
                new += self._files(folder, base + 1)
            gone = {s.path for r in runs for s in r}
            try:
                self._commit(base, [*(s for s in shards if s.path not in gone), *new])
            except CommitConflict:
                continue
            finally:
                self._withdraw(batch)
            if len(new) >= len(gone):
                return base + 1

    def vacuum(self, keep_versions: int = 1, forgotten_ms: int = FORGOTTEN_MS) -> int:
        """Delete shards that none of the last ``keep_versions`` versions lists; returns how many.

        Batches of announced, unfinished writes are left alone, unless the announcement is
        older than ``forgotten_ms`` (the writer is gone). Files are listed before the
        announcements, and those before the versions: what is committed in between is seen.
        """
        fs, data = hadoop_path(self.spark, f"{self.path}/data")
        found, walk = [], fs.listFiles(data, True) if fs.exists(data) else None
        while walk and walk.hasNext():
            path = walk.next().getPath()
            if path.getName().startswith("part-"):
                found.append(path)
        _, intents = hadoop_path(self.spark, f"{self.path}/intents")
        now = self.spark.sparkContext._jvm.System.currentTimeMillis()
        announced = {s.getPath().getName() for s in fs.listStatus(intents) if now - s.getModificationTime() < forgotten_ms} if fs.exists(intents) else set()
        last = self.version()
        tail = lambda path: path[path.rindex("/data/") :]  # noqa: E731  the same file whatever scheme its path is written with
        live = {tail(s.path) for v in range(max(1, last - keep_versions + 1), last + 1) for s in self.manifest(v)}

        def pending(path: str) -> bool:
            _, _, batch, inner, *_ = tail(path).split("/")
            return batch in announced or f"{batch}@{inner}" in announced

        gone = [p for p in found if tail(p.toString()) not in live and not pending(p.toString())]
        for p in gone:
            fs.delete(p, False)
        return len(gone)

    def read(self, version: int | None = None, with_shard: bool = False) -> DataFrame:
        """Rows of a version; ``with_shard`` adds the file name as ``shard``. A store without shards cannot be read."""
        shards = self.manifest(version)
        if not shards:
            raise FileNotFoundError(f"{self.path} has no committed shards")
        rows = self.spark.read.parquet(*(s.path for s in shards))
        return rows.withColumn("shard", F.element_at(F.split(F.col("_metadata.file_path"), "/"), -1)) if with_shard else rows


def shard_table(rows: DataFrame, path: str, arrivals: int = 4, target_bytes: int = 128 << 20, fan_in: int = 4, floor_bytes: int = 1 << 20, keep_versions: int | None = None) -> ShardStore:
    """Store a table as ``arrivals`` arrivals (dealt by a hash of the row), compacting after each.

    All versions stay readable, or with ``keep_versions`` the last ones. All rows and columns
    are kept as they are: nulls, empty and long texts, ties, repeated rows and extra columns
    (but ``__arrival``). An empty table leaves one shard without rows, so its schema can be
    read back.
    """
    store = ShardStore(rows.sparkSession, path, target_bytes, fan_in, floor_bytes)
    deal = F.pmod(F.xxhash64(*rows.columns), F.lit(arrivals))

    def settle() -> None:
        store.compact()
        if keep_versions:
            store.vacuum(keep_versions)

    store.append_dealt(rows, deal, arrivals, settle)
    if not store.manifest():
        store.append(rows.limit(0).coalesce(1))
    return store
