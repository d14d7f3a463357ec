"""Size-tiered shards under a versioned manifest, in DataFrame operations only.

Arrivals are appended as runs of small immutable Parquet shards. Compaction takes the
runs in order of size; where FAN_IN or more are of similar size (each within SIMILAR
times the smallest of them), it merges them into one run of files of about the target
size and goes on with the result, until no tier is full. A row is so rewritten about
log(total / arrival) / log(FAN_IN) times. Merging reads whole shards and writes them
together without a shuffle, so no key decides how large a task is.

A manifest lists the live runs of one version. A writer puts the next version's content
to a file of its own and then claims the version's name by exclusive creation; a
second writer of the same version fails and starts again from the newer one. A claim
whose writer died before its manifest was there is taken over after CLAIM_SECONDS.
Readers use one version's list of files, so they never see half a change; shards that no
kept version lists are removed by ``vacuum``, those that none ever listed after
ORPHAN_SECONDS, as a writer may be about to commit them.

Edge cases: an empty arrival makes a run without rows; null texts, long texts and
repeated rows are stored as they are; a column named like the store's own
(``_arrival``) is kept, the store's gets another name; a failed write leaves files that
no version lists.
"""

from __future__ import annotations

import json
import time
import uuid
from collections.abc import Callable
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, fresh, new_path

TARGET_BYTES = 64 << 20
FAN_IN, SIMILAR = 4, 2.0
ARRIVALS = 8
SPLIT = "_arrival"
#: Age from which a claim without a manifest, and shards that no version lists, count as left behind; tries of a commit.
CLAIM_SECONDS, ORPHAN_SECONDS, TRIES = 120, 86_400, 20


class Conflict(RuntimeError):
    """Another writer has committed this version."""


@dataclass(frozen=True)
class Run:
    name: str
    level: int
    bytes: int
    files: tuple[str, ...]


class ShardStore:
    """A table of immutable shards in ``root``, a path that the driver and all executors can reach."""

    def __init__(self, spark: SparkSession, root: str, target_bytes: int = TARGET_BYTES, fan_in: int = FAN_IN, similar: float = SIMILAR, claim_seconds: float = CLAIM_SECONDS, orphan_seconds: float = ORPHAN_SECONDS):
        self.claim_seconds, self.orphan_seconds = claim_seconds, orphan_seconds
        self.spark, self.root, self.target_bytes, self.fan_in, self.similar = spark, root, target_bytes, fan_in, similar
        self._jvm = spark._jvm
        self._fs = self._path("").getFileSystem(spark._jsc.hadoopConfiguration())

    def _path(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}" if name else self.root)

    # manifests
    def versions(self) -> list[int]:
        if not self._fs.exists(self._path("manifests")):
            return []
        return sorted(int(n.removesuffix(".json")) for s in self._fs.listStatus(self._path("manifests")) if (n := s.getPath().getName()).endswith(".json"))

    def manifest(self, version: int | None = None) -> tuple[int, list[Run]]:
        """(version, live runs); version 0 is the empty store."""
        known = self.versions()
        version = (known[-1] if known else 0) if version is None else version
        if not version:
            return 0, []
        stream = self._fs.open(self._path(f"manifests/{version:012d}.json"))
        try:
            text = bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()
        return version, [Run(**(r | {"files": tuple(r["files"])})) for r in json.loads(text)]

    def commit(self, base: int, runs: list[Run]) -> int:
        version = base + 1
        draft, claim, final = (self._path(f"manifests/{n}") for n in (f".{uuid.uuid4().hex}", f".{version:012d}.claim", f"{version:012d}.json"))
        out = self._fs.create(draft, True)
        out.write(bytearray(json.dumps([asdict(r) for r in runs]).encode()))
        out.close()
        try:
            if not self._fs.exists(final) and self._age(claim) > self.claim_seconds:
                self._fs.delete(claim, False)
            self._fs.create(claim, False).close()
        except Exception as e:
            self._fs.delete(draft, False)
            raise Conflict(f"version {version} is taken") from e
        if self._fs.exists(final) or not self._fs.rename(draft, final):
            raise Conflict(f"version {version} can't be written")
        return version

    def _age(self, path) -> float:
        """Seconds since the file was written; below 0 where there is none."""
        return time.time() - self._fs.getFileStatus(path).getModificationTime() / 1000 if self._fs.exists(path) else -1.0

    def change(self, edit: Callable[[list[Run]], list[Run] | None]) -> int:
        """Commits ``edit`` of the newest version's runs, again from a newer one where another writer was first; None: no change."""
        for attempt in range(TRIES):
            base, runs = self.manifest()
            new = edit(runs)
            if new is None:
                return base
            try:
                return self.commit(base, new)
            except Conflict:
                time.sleep(min(0.05 * 2**attempt, 2.0))
        raise Conflict(f"no commit in {TRIES} tries")

    # writing
    def _listed(self, folder: str, name: str, level: int) -> Run:
        found = [(s.getPath().getName(), s.getLen()) for s in self._fs.listStatus(self._path(folder)) if s.getPath().getName().endswith(".parquet")]
        return Run(name, level, sum(n for _, n in found), tuple(sorted(f"{folder}/{f}" for f, _ in found)))

    def append(self, arrival: DataFrame) -> int:
        """One arrival as a run of small shards, one for each task."""
        name = uuid.uuid4().hex
        arrival.write.parquet(f"{self.root}/data/{name}")
        run = self._listed(f"data/{name}", name, 0)
        return self.change(lambda runs: [*runs, run])

    def append_each(self, rows: DataFrame, arrival) -> int:
        """Arrivals told apart by a column, written in one pass, committed one after another."""
        name = uuid.uuid4().hex
        split = fresh(rows, SPLIT)
        rows.withColumn(split, arrival).write.partitionBy(split).parquet(f"{self.root}/data/{name}")
        version = self.manifest()[0]
        parts = sorted(s.getPath().getName() for s in self._fs.listStatus(self._path(f"data/{name}")) if s.isDirectory() and s.getPath().getName().startswith(f"{split}="))
        for part in parts:
            run = self._listed(f"data/{name}/{part}", f"{name}-{part.partition('=')[2]}", 0)
            version = self.change(lambda runs, run=run: [*runs, run])
        return version

    def full_tier(self, runs: list[Run]) -> list[Run]:
        """The smallest runs of similar size, if there are enough of them."""
        ordered = sorted(runs, key=lambda r: (r.bytes, r.name))
        for i, first in enumerate(ordered):
            tier = [r for r in ordered[i:] if r.bytes <= self.similar * max(first.bytes, 1)]
            if len(tier) >= self.fan_in:
                return tier
        return []

    def compact(self) -> int:
        """Merges full tiers until there is none; returns the version reached."""
        while True:
            version, runs = self.manifest()
            tier = self.full_tier(runs)
            if not tier:
                return version
            total, name = sum(r.bytes for r in tier), uuid.uuid4().hex
            files = [f"{self.root}/{f}" for r in tier for f in r.files]
            if files:
                merged = self.spark.read.parquet(*files).coalesce(max(1, round(total / self.target_bytes)))
                merged.write.parquet(f"{self.root}/data/{name}")
            else:
                self._fs.mkdirs(self._path(f"data/{name}"))
            gone = {r.name for r in tier}
            merged_run = self._listed(f"data/{name}", name, 1 + max(r.level for r in tier))
            # where another writer has merged one of these runs, this result is left to vacuum
            self.change(lambda runs: [*(r for r in runs if r.name not in gone), merged_run] if gone <= {r.name for r in runs} else None)

    def vacuum(self, keep_versions: int = 1) -> int:
        """Removes manifests before the newest ``keep_versions`` and shards that none of these lists."""
        if keep_versions < 1:
            raise ValueError("the newest version is always kept")
        known = self.versions()
        kept = known[-keep_versions:]
        live = {f for v in kept for r in self.manifest(v)[1] for f in r.files}
        removed = 0
        for v in known:
            if v in kept:
                continue
            for f in {f for r in self.manifest(v)[1] for f in r.files} - live:
                removed += bool(self._fs.delete(self._path(f), False))
            self._fs.delete(self._path(f"manifests/{v:012d}.json"), False)
        # files of writers that died before they listed them
        prefix = self._fs.makeQualified(self._path("")).toString() + "/"
        if self._fs.exists(self._path("data")):
            files = self._fs.listFiles(self._path("data"), True)
            while files.hasNext():
                s = files.next()
                name = s.getPath().toString().removeprefix(prefix)
                if name.endswith(".parquet") and name not in live and time.time() - s.getModificationTime() / 1000 > self.orphan_seconds:
                    removed += bool(self._fs.delete(s.getPath(), False))
        return removed

    # reading
    def read(self, schema=None, version: int | None = None) -> DataFrame:
        """The rows of a version, with the hidden column ``_metadata`` of Spark's file sources."""
        files = [f"{self.root}/{f}" for r in self.manifest(version)[1] for f in r.files]
        if not files:
            return self.spark.createDataFrame([], schema)
        reader = self.spark.read.schema(schema) if schema is not None else self.spark.read
        return reader.parquet(*files)

    def live(self, version: int | None = None) -> DataFrame:
        """(shard, run, level, version): one row per live file."""
        version, runs = self.manifest(version)
        return self.spark.createDataFrame([(f, r.name, r.level, version) for r in runs for f in r.files], "shard string, run string, level int, version long")


def op2_size_tiered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents arrive in ARRIVALS parts, are compacted and read back from the newest version."""
    docs = documents(spark, sf_dir)
    store = ShardStore(spark, new_path(spark, "shards"))
    store.append_each(docs, F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(ARRIVALS)))
    version = store.compact()
    store.vacuum()
    level = {r.name: r.level for r in store.manifest(version)[1]}
    rows = store.read(docs.schema).select("doc_id", F.expr("_metadata.file_path").alias("path"), F.octet_length("text").cast("long").alias("text_bytes"), F.md5(F.col("text").cast("binary")).alias("text_md5"))
    # a run's name is its folder's, or, before compaction, the folders' above the shard
    name = F.coalesce(F.regexp_extract("path", f"/data/([0-9a-f]+)/{SPLIT}=", 1), F.lit(""))
    run = F.when(name != "", F.concat(name, F.lit("-"), F.regexp_extract("path", f"/{SPLIT}=([^/]+)/", 1))).otherwise(F.regexp_extract("path", "/data/([0-9a-f]+)/", 1))
    levels = F.create_map(*[F.lit(x) for pair in level.items() for x in pair]) if level else F.create_map().cast("map<string,int>")
    return rows.select("doc_id", F.regexp_extract("path", "(data/.*)$", 1).alias("shard"), F.element_at(levels, run).alias("level"), F.lit(version).cast("long").alias("version"), "text_bytes", "text_md5")
