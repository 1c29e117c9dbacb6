"""Size-tiered compaction of immutable shards under versioned manifests (DataFrame API only).

Every append writes one *run*: a folder of small Parquet shards that never change.  ``compact``
merges runs of a similar size, a tier at a time, into a run of target-sized files.  A manifest
lists the live runs and nothing else; it becomes visible by one rename that fails if another
writer took the version first, and the loser tries again on the newer manifest.  A reader
therefore sees all of a change or none of it, and any earlier version until it is vacuumed.

The merge is a narrow plan, scan, ``coalesce``, write: no shuffle, each row is rewritten once a
tier, so about log_fanout(total / first arrival) times in all.

Defined results: an empty arrival commits a version without a run; nulls, repeated rows and extra
columns are data like any other; an arrival whose columns differ from the store's is refused.
"""

from __future__ import annotations

import json
import math
import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql.types import StructType

from .storage import Files, unused


@dataclass(frozen=True)
class Run:
    """One immutable folder of shards."""

    name: str
    rows: int
    size: int
    files: int


@dataclass(frozen=True)
class Manifest:
    version: int = 0
    schema: str | None = None
    runs: tuple[Run, ...] = field(default=())

    def text(self) -> str:
        return json.dumps({"version": self.version, "schema": self.schema, "runs": [vars(r) for r in self.runs]})

    @staticmethod
    def parse(text: str) -> Manifest:
        raw = json.loads(text)
        return Manifest(raw["version"], raw["schema"], tuple(Run(**r) for r in raw["runs"]))


class _Merged(Exception):
    """Another writer has merged these runs."""


class ShardStore:
    """A table kept as runs.

    target_bytes: size of a compacted file; fanout: runs of one tier that are merged together;
    first_tier_bytes: runs up to this size are tier 0, each further tier is ``fanout`` times larger.
    """

    def __init__(self, spark: SparkSession, root: str, *, target_bytes: int = 64 << 20, fanout: int = 4, first_tier_bytes: int = 4 << 20):
        if fanout < 2 or target_bytes < 1 or first_tier_bytes < 1:
            raise ValueError("fanout must be 2 or more and sizes positive")
        self.spark, self.target_bytes, self.fanout, self.first_tier_bytes = spark, target_bytes, fanout, first_tier_bytes
        self.files = Files(spark, root)
        self.files.make(self.files.at("manifests"))

    def versions(self) -> list[int]:
        return [int(n[:-5]) for n in self.files.names(self.files.at("manifests")) if n.endswith(".json") and n[0].isdigit()]

    def manifest(self, version: int | None = None) -> Manifest:
        known = self.versions()
        if not known and not version:
            return Manifest()
        return Manifest.parse(self.files.read(self._manifest_path(known[-1] if version is None else version)))

    def tier(self, run: Run) -> int:
        return max(0, math.ceil(math.log(max(run.size, 1) / self.first_tier_bytes, self.fanout) - 1e-9))

    def read(self, version: int | None = None) -> DataFrame:
        """The rows of a version, the newest by default."""
        manifest = self.manifest(version)
        if manifest.schema is None:
            raise ValueError("the store has no schema yet; append first")
        return self._load(manifest, manifest.runs)

    def append(self, arrival: DataFrame) -> int:
        """Add one arrival as a run of small shards; returns the committed version."""
        self._fits(self.manifest(), arrival.schema)
        return self._add(self._write(arrival), arrival.schema)

    def append_parts(self, arrivals: DataFrame, part: Column) -> list[int]:
        """Add several arrivals in one scan: the rows of each value of ``part``, in turn, as a run and a version."""
        self._fits(self.manifest(), arrivals.schema)
        column, folder = unused(arrivals.columns, "part"), self.files.at("runs", f".{uuid.uuid4().hex}")
        arrivals.withColumn(column, part).write.partitionBy(column).parquet(folder)
        parts = sorted((n for n in self.files.names(folder) if n.startswith(f"{column}=")), key=lambda n: (not n[len(column) + 1 :].isdigit(), len(n), n))
        versions = []
        for name in parts:
            run = uuid.uuid4().hex
            self.files.publish(f"{folder}/{name}", self.files.at("runs", run))
            versions.append(self._add(self._measure(run, arrivals.schema), arrivals.schema))
        self.files.remove(folder)
        return versions or [self._add(Run("", 0, 0, 0), arrivals.schema)]

    def _fits(self, now: Manifest, schema: StructType) -> None:
        if now.schema and [(f.name, f.dataType) for f in StructType.fromJson(json.loads(now.schema))] != [(f.name, f.dataType) for f in schema]:
            raise ValueError("the arrival's columns differ from the store's")

    def _add(self, run: Run, schema: StructType) -> int:
        def change(now: Manifest) -> Manifest:
            self._fits(now, schema)
            return Manifest(now.version + 1, now.schema or schema.json(), now.runs + ((run,) if run.rows else ()))

        return self._commit(change)

    def compact(self) -> list[int]:
        """Merge while some tier holds ``fanout`` runs or more; returns the versions it committed."""
        committed = []
        while group := self._due(now := self.manifest()):
            names, size = {r.name for r in group}, sum(r.size for r in group)
            merged = self._write(self._load(now, group).coalesce(max(1, round(size / self.target_bytes))))
            if merged.rows != sum(r.rows for r in group):
                raise RuntimeError(f"a merge wrote {merged.rows} of {sum(r.rows for r in group)} rows; nothing was committed")

            def change(latest: Manifest, names=names, merged=merged) -> Manifest:
                if not names <= {r.name for r in latest.runs}:
                    raise _Merged
                return Manifest(latest.version + 1, latest.schema, tuple(r for r in latest.runs if r.name not in names) + (merged,))

            try:
                committed.append(self._commit(change))
            except _Merged:
                self.files.remove(self.files.at("runs", merged.name))
        return committed

    def vacuum(self, keep_versions: int = 1) -> list[str]:
        """Delete runs that none of the newest versions lists; returns their names.  Not to be run during an append or merge."""
        known = self.versions()
        live = {r.name for v in known[-keep_versions:] for r in self.manifest(v).runs}
        dead = [n for n in self.files.names(self.files.at("runs")) if n not in live]
        for name in dead:
            self.files.remove(self.files.at("runs", name))
        for version in known[:-keep_versions]:
            self.files.remove(self._manifest_path(version))
        return dead

    def _due(self, manifest: Manifest) -> list[Run]:
        tiers: dict[int, list[Run]] = {}
        for run in manifest.runs:
            tiers.setdefault(self.tier(run), []).append(run)
        return next((runs for _, runs in sorted(tiers.items()) if len(runs) >= self.fanout), [])

    def _load(self, manifest: Manifest, runs) -> DataFrame:
        schema = StructType.fromJson(json.loads(manifest.schema))
        if not runs:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*(self.files.at("runs", r.name) for r in runs))

    def _write(self, rows: DataFrame) -> Run:
        name = uuid.uuid4().hex
        folder = self.files.at("runs", name)
        rows.write.parquet(folder)
        return self._measure(name, rows.schema)

    def _measure(self, name: str, schema: StructType) -> Run:
        folder = self.files.at("runs", name)
        sizes = self.files.sizes(folder)
        counted = self.spark.read.schema(schema).parquet(folder).count() if sizes else 0
        return Run(name, counted, sum(sizes.values()), len(sizes))

    def _manifest_path(self, version: int) -> str:
        return self.files.at("manifests", f"{version:012d}.json")

    def _commit(self, change) -> int:
        while True:
            after = change(self.manifest())
            draft = self.files.at("manifests", f".draft-{uuid.uuid4().hex}")
            self.files.write(draft, after.text())
            if self.files.publish(draft, self._manifest_path(after.version)):
                return after.version
            self.files.remove(draft)
