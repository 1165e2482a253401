"""Sharding by size-tiered compaction (DataFrame functions and the session's file system only).

A shard table is a folder of immutable runs and numbered manifests.  ``append`` writes
arrivals as runs of small shards; ``compact`` merges runs of a similar size, a tier at a
time, into files near the target size, without a shuffle: the shards of the merged runs
are read side by side and concatenated.  Every change commits the next manifest by an
atomic rename that fails if another writer was first; readers see one version or another,
never a mixture, and old versions stay readable until ``expire``.

A run's size is the number of its text bytes plus a fixed charge a row.  The manifest
names runs, not rows or shards, so it stays small.  Runs that no version came to name, after a
lost commit or a lost driver, are deleted by their writer or by ``collect_orphans``.

Defined results: null texts have no bytes; an empty arrival makes no run; repeated rows
are kept as they are; any value can name an arrival, null among them, and the arrival column is
not stored; columns of the table keep their names and values, whatever they are called: names
that are added here give way.
"""

from __future__ import annotations

import json
import math
import time
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, new_scratch_path

TARGET_BYTES, FANOUT, BASE_BYTES, ROW_CHARGE = 64 << 20, 4, 1 << 16, 32


class CommitConflict(RuntimeError):
    """Another writer committed this version first."""


def _free(name: str, taken: list[str]) -> str:
    """``name`` with underscores in front until no column has it."""
    while name.lower() in {t.lower() for t in taken}:
        name = "_" + name
    return name


class ShardTable:
    def __init__(self, spark: SparkSession, root: str, *, target_bytes: int = TARGET_BYTES, fanout: int = FANOUT, base_bytes: int = BASE_BYTES, size_column: str = "text"):
        self.spark, self.root, self.size_column = spark, root.rstrip("/"), size_column
        self.target_bytes, self.fanout, self.base_bytes = target_bytes, fanout, base_bytes
        self.jvm, self.conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        self.fs = self._path(self.root).getFileSystem(self.conf)

    def _path(self, text: str):
        return self.jvm.org.apache.hadoop.fs.Path(text)

    # --- manifests ---------------------------------------------------------------------

    def versions(self) -> list[int]:
        folder = self._path(f"{self.root}/manifest")
        if not self.fs.exists(folder):
            return []
        names = [s.getPath().getName() for s in self.fs.listStatus(folder)]
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def manifest(self, version: int | None = None) -> dict:
        known = self.versions()
        version = version if version is not None else (known[-1] if known else 0)
        if version == 0:
            return {"version": 0, "schema": None, "runs": []}
        stream = self.fs.open(self._path(f"{self.root}/manifest/v{version:08d}.json"))
        try:
            return json.loads(self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def commit(self, base: dict, runs: list[dict], schema) -> dict:
        """Write the version after ``base``: a temporary file, then a rename that never overwrites."""
        made = {"version": base["version"] + 1, "schema": json.loads(schema.json()), "runs": runs}
        folder = f"{self.root}/manifest"
        self.fs.mkdirs(self._path(folder))
        draft = self._path(f"{folder}/.draft-{uuid.uuid4().hex}")
        out = self.fs.create(draft, False)
        try:
            out.write(bytearray(json.dumps(made).encode()))
        finally:
            out.close()
        none = self.spark.sparkContext._gateway.new_array(self.jvm.org.apache.hadoop.fs.Options.Rename, 0)
        context = self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(draft.toUri() if draft.toUri().getScheme() else self.fs.getUri(), self.conf)
        try:
            context.rename(draft, self._path(f"{folder}/v{made['version']:08d}.json"), none)
        except Exception as error:
            self.fs.delete(draft, False)
            if "FileAlreadyExists" in str(error):
                raise CommitConflict(f"version {made['version']} exists") from error
            raise
        return made

    # --- runs ----------------------------------------------------------------------------

    def _bytes(self):
        size = F.coalesce(F.octet_length(self.size_column), F.lit(0)) if self.size_column else F.lit(0)
        return F.sum(size.cast("bigint") + ROW_CHARGE)

    def append(self, rows: DataFrame, arrival: str | None = None) -> dict:
        """Add the rows as one run, or as one run for each value of the column ``arrival``."""
        base = self.manifest()
        name = f"data/append-{uuid.uuid4().hex[:12]}"
        run = _free("_run", rows.columns)
        # a digest in hexadecimal names the folder: no value needs escaping and none is taken for a number
        told = F.coalesce(F.concat(F.lit("v"), F.md5(F.col(arrival).cast("string"))), F.lit("null")) if arrival else F.lit("all")
        tagged = rows.withColumn(run, told)
        stored = rows.drop(arrival) if arrival else rows
        tagged.select(*stored.columns, run).write.option("compression", "zstd").partitionBy(run).parquet(f"{self.root}/{name}")
        new = [] if not self._written(name) else self._runs(name, stored.schema)
        return self._commit_or_clean(base, base["runs"] + new, stored.schema, [name])

    def _runs(self, name: str, schema) -> list[dict]:
        files = self.spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(f"{self.root}/{name}")
        place = F.regexp_extract(F.col("_metadata.file_path"), r"([^/]+)/[^/]+$", 1)
        sizes = files.groupBy(place.alias("place"), F.col("_metadata.file_path")).agg(F.count(F.lit(1)).alias("n"), self._bytes().alias("b")) \
            .groupBy("place").agg(F.sum("n").alias("rows"), F.sum("b").alias("bytes"), F.count(F.lit(1)).alias("shards")).collect()
        return [{"path": f"{name}/{r['place']}", "rows": r["rows"], "bytes": r["bytes"], "shards": r["shards"], "level": 0} for r in sorted(sizes, key=lambda r: r["place"])]

    def _commit_or_clean(self, base: dict, runs: list[dict], schema, made: list[str]) -> dict:
        """Commit; where another writer was first, delete what this one wrote."""
        try:
            return self.commit(base, runs, schema)
        except CommitConflict:
            for name in made:
                self.fs.delete(self._path(f"{self.root}/{name}"), True)
            raise

    def collect_orphans(self, grace_seconds: float = 86_400) -> int:
        """Delete data folders that no version names and nobody has written to for the grace period; their number."""
        folder = self._path(f"{self.root}/data")
        if not self.fs.exists(folder):
            return 0
        named = {r["path"].split("/")[1] for v in self.versions() for r in self.manifest(v)["runs"]}
        before = (time.time() - grace_seconds) * 1000
        lost = [s.getPath() for s in self.fs.listStatus(folder) if s.getPath().getName() not in named and s.getModificationTime() <= before]
        for path in lost:
            self.fs.delete(path, True)
        return len(lost)

    def _written(self, name: str) -> bool:
        return any(s.isDirectory() for s in self.fs.listStatus(self._path(f"{self.root}/{name}")))

    def tier(self, run: dict) -> int:
        return max(0, int(math.log(max(1, run["bytes"]) / self.base_bytes, self.fanout)) if run["bytes"] > self.base_bytes else 0)

    def settled(self, run: dict) -> bool:
        """A run of enough bytes whose files are near the target already."""
        return run["bytes"] >= self.target_bytes and run["bytes"] / run["shards"] >= self.target_bytes / 2

    def plan(self, runs: list[dict]) -> list[list[dict]]:
        """Groups of runs to merge: in every tier, ``fanout`` runs at a time; a run too large for its files alone."""
        tiers: dict[int, list[dict]] = {}
        for r in runs:
            if not self.settled(r):
                tiers.setdefault(self.tier(r), []).append(r)
        return [tier[i : i + self.fanout] for _, tier in sorted(tiers.items()) for i in range(0, len(tier) - self.fanout + 1, self.fanout)]

    def _merge(self, group: list[dict], schema) -> dict:
        size = sum(r["bytes"] for r in group)
        files = max(1, round(size / self.target_bytes))
        name = f"data/merge-{uuid.uuid4().hex[:12]}"
        self.spark.read.schema(schema).parquet(*[f"{self.root}/{r['path']}" for r in group]).coalesce(files).write.option("compression", "zstd").parquet(f"{self.root}/{name}")
        kept = sum(s.getPath().getName().startswith("part-") for s in self.fs.listStatus(self._path(f"{self.root}/{name}")))
        return {"path": name, "rows": sum(r["rows"] for r in group), "bytes": size, "shards": kept, "level": 1 + max(r["level"] for r in group)}

    def compact(self) -> dict:
        """Merge until no tier has enough runs; one commit a round."""
        from pyspark.sql.types import StructType

        now = self.manifest()
        while groups := self.plan(now["runs"]):
            schema = StructType.fromJson(now["schema"])
            gone = {r["path"] for g in groups for r in g}
            merged = [self._merge(g, schema) for g in groups]
            now = self._commit_or_clean(now, [r for r in now["runs"] if r["path"] not in gone] + merged, schema, [r["path"] for r in merged])
        return now

    def expire(self) -> int:
        """Delete the runs and manifests that only older versions name."""
        now = self.manifest()
        live, removed = {r["path"] for r in now["runs"]}, 0
        folders = {p.split("/")[1] for p in live}
        for v in self.versions()[:-1]:
            for r in self.manifest(v)["runs"]:
                if r["path"] not in live:
                    removed += bool(self.fs.delete(self._path(f"{self.root}/{r['path']}"), True))
                    if r["path"].split("/")[1] not in folders:
                        self.fs.delete(self._path(f"{self.root}/data/{r['path'].split('/')[1]}"), True)
            self.fs.delete(self._path(f"{self.root}/manifest/v{v:08d}.json"), False)
        return removed

    def read(self, version: int | None = None) -> DataFrame:
        """All rows of a version with ``shard_id``, the file that holds each, as the last column."""
        from pyspark.sql.types import StructType

        now = self.manifest(version)
        if now["schema"] is None:
            raise ValueError("the table has no version yet")
        schema = StructType.fromJson(now["schema"])
        shard_id = _free("shard_id", schema.names)
        if not now["runs"]:
            return self.spark.createDataFrame([], schema).withColumn(shard_id, F.lit(None).cast("string"))
        rows = self.spark.read.schema(schema).parquet(*[f"{self.root}/{r['path']}" for r in now["runs"]])
        place = F.regexp_extract(F.col("_metadata.file_path"), r"(?:merge|append)-[^/]+/(?:[^/]+/)?[^/]+$", 0)
        return rows.select("*", place.alias(shard_id))


def shard_report(docs: DataFrame, root: str, *, arrivals: int = 24, **options) -> DataFrame:
    """Deal the rows into uneven arrivals, append, compact, and report where each row lies."""
    table = ShardTable(docs.sparkSession, root, **options)
    # arrival a takes every 2**(a % 4 + 1)-th hash: runs of several sizes, none of them bound to a source
    dealt, batch = F.pmod(F.xxhash64("doc_id"), F.lit(arrivals * 4)), _free("_batch", docs.columns)
    table.append(docs.withColumn(batch, F.when(dealt < arrivals, dealt).otherwise(F.pmod(dealt, F.lit(arrivals // 2)))), batch)
    table.compact()
    table.expire()
    rows = table.read()
    at = rows.select("doc_id", F.col(rows.columns[-1]).alias("shard_id"), (F.coalesce(F.octet_length("text"), F.lit(0))).cast("bigint").alias("n_bytes"))
    return at.withColumn("version", F.lit(table.versions()[-1]))


def op6_sharding(spark, sf_dir):
    return shard_report(load(spark, sf_dir, "documents"), new_scratch_path(spark, "shards"))


QUERIES = {"op6_sharding": op6_sharding}
ORACLES: dict[str, str] = {}
