"""Sharding by size-tiered compaction under a versioned manifest.

An arrival is written as a run of small immutable shards. Runs of one tier, that is of similar
size, are merged once ``fanout`` of them have come together, into files of about the target size;
the tier of a run is how often its size can be divided by the fanout down to the base. A merge reads
whole shards and regroups them without a shuffle, so no key can be hot.

What a reader sees is the newest manifest: one JSON file for each version, with all live shards. It
is written under another name and renamed to its version, which fails if that version exists, so of
two writers one commits and the other starts again from the newer manifest. Files that no manifest
knows (of a writer or executor that was lost) are not read, and ``vacuum`` removes them.

Results: rows and columns come back as they were, nulls, repeated rows and any further columns
included; where arrivals have different columns, a row has nulls in those that its arrival lacked, and a
column that comes in another type is refused; shards hold rows in no stated order; an empty arrival commits a version without shards.
"""

from __future__ import annotations

import json
import math
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shared_dir, table

TARGET_BYTES, BASE_BYTES, FANOUT, ARRIVALS, FILES = 128 << 20, 1 << 20, 4, 8, 32


class Conflict(RuntimeError):
    """Another writer committed that version first."""


def merged(old: str | None, new: str | None) -> str | None:
    """The columns of two schemas (JSON): those of the old one, then those that only the new one has."""
    if old is None or new is None:
        return old or new
    fields, out = json.loads(new)["fields"], json.loads(old)
    known = {f["name"].lower(): f for f in out["fields"]}
    for f in fields:
        if f["name"].lower() not in known:
            out["fields"].append(f | {"nullable": True})
        elif known[f["name"].lower()]["type"] != f["type"]:
            raise ValueError(f"column {f['name']} comes as {f['type']}, it is {known[f['name'].lower()]['type']}")
    return json.dumps(out)


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target: int = TARGET_BYTES, base: int = BASE_BYTES, fanout: int = FANOUT):
        self.spark, self.root, self.target, self.base, self.fanout = spark, root.rstrip("/"), target, base, fanout
        self.jvm, self.conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        self.fs = self._path(self.root).getFileSystem(self.conf)
        self.fs.mkdirs(self._path(f"{self.root}/manifests"))

    def _path(self, at: str):
        return self.jvm.org.apache.hadoop.fs.Path(at)

    def _list(self, at: str) -> list[tuple[str, int, bool]]:
        path = self._path(at)
        return sorted((s.getPath().toString(), s.getLen(), s.isDirectory()) for s in self.fs.listStatus(path)) if self.fs.exists(path) else []

    def versions(self) -> list[int]:
        names = (p.rsplit("/", 1)[1] for p, _, _ in self._list(f"{self.root}/manifests"))
        return sorted(int(n[1:-5]) for n in names if n[:1] == "v" and n.endswith(".json"))

    def manifest(self, version: int | None = None) -> dict:
        found = self.versions()
        if not found:
            return {"version": 0, "schema": None, "shards": []}
        at = self._path(f"{self.root}/manifests/v{found[-1] if version is None else version:012d}.json")
        stream = self.fs.open(at)
        try:
            return json.loads(self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def commit(self, before: dict, shards: list[dict], schema: str | None) -> dict:
        after = {"version": before["version"] + 1, "schema": merged(before["schema"], schema), "shards": sorted(shards, key=lambda s: s["path"])}
        draft, final = (self._path(f"{self.root}/manifests/{n}") for n in (f"draft-{uuid.uuid4().hex}", f"v{after['version']:012d}.json"))
        stream = self.fs.create(draft, False)
        try:
            stream.write(bytearray(json.dumps(after).encode()))
        finally:
            stream.close()
        none = self.spark.sparkContext._gateway.new_array(self.jvm.org.apache.hadoop.fs.Options.Rename, 1)
        none[0] = self.jvm.org.apache.hadoop.fs.Options.Rename.NONE
        try:
            self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self.conf).rename(draft, final, none)
        except Exception as e:
            self.fs.delete(draft, False)
            if "FileAlreadyExists" in str(e):
                raise Conflict(f"version {after['version']} exists") from e
            raise
        return after

    def tier(self, size: int) -> int:
        return max(0, math.floor(math.log(max(1, size) / self.base, self.fanout) + 1e-9) + 1)

    def _write(self, df: DataFrame, run: str) -> list[dict]:
        at = f"{self.root}/data/{run}"
        df.write.option("compression", "zstd").parquet(at)
        return [{"path": f"data/{run}/{p.rsplit('/', 1)[1]}", "bytes": n, "run": run} for p, n, folder in self._list(at) if not folder and p.rsplit("/", 1)[1].startswith("part-")]

    def append(self, df: DataFrame, tries: int = 10) -> dict:
        """Adds the rows of df as a run of small shards."""
        merged(self.manifest()["schema"], df.schema.json())  # refuses before anything is written
        new = self._write(df, f"t0-{uuid.uuid4().hex}")
        for _ in range(tries):
            before = self.manifest()
            try:
                return self.commit(before, before["shards"] + new, df.schema.json())
            except Conflict:
                continue
        raise Conflict(f"gave up after {tries} tries")

    def due(self, shards: list[dict], finish: bool) -> list[dict]:
        """Shards of runs to merge next: the runs of the lowest tier that has ``fanout`` of them. To finish,
        all shards that are under half the target, if they can be fewer."""
        runs: dict[str, list[dict]] = {}
        for s in shards:
            if s["bytes"] < self.target / 2:
                runs.setdefault(s["run"], []).append(s)
        tiers: dict[int, list[list[dict]]] = {}
        for run in runs.values():
            tiers.setdefault(self.tier(sum(s["bytes"] for s in run)), []).append(run)
        for level in sorted(tiers):
            if len(tiers[level]) >= self.fanout:
                return [s for run in tiers[level] for s in run]
        left = [s for run in runs.values() for s in run]
        return left if finish and len(left) > max(1, math.ceil(sum(s["bytes"] for s in left) / self.target)) else []

    def compact(self, finish: bool = False) -> dict:
        """Merges until nothing is due. A merge that lost the race is dropped and planned anew."""
        while True:
            before = self.manifest()
            old = self.due(before["shards"], finish)
            if not old:
                return before
            size = sum(s["bytes"] for s in old)
            files = max(1, math.ceil(size / self.target))
            new = self._write(self._rows([s["path"] for s in old], before["schema"]).coalesce(files), f"t{self.tier(size)}-{uuid.uuid4().hex}")
            gone = {s["path"] for s in old}
            try:
                self.commit(before, [s for s in before["shards"] if s["path"] not in gone] + new, None)
            except Conflict:
                continue

    def _rows(self, paths: list[str], schema: str) -> DataFrame:
        from pyspark.sql.types import StructType

        kind = StructType.fromJson(json.loads(schema))
        return self.spark.read.schema(kind).parquet(*(f"{self.root}/{p}" for p in paths)) if paths else self.spark.createDataFrame([], kind)

    def read(self, version: int | None = None) -> DataFrame:
        m = self.manifest(version)
        if m["schema"] is None:
            raise ValueError("nothing has been committed")
        return self._rows([s["path"] for s in m["shards"]], m["schema"])

    def vacuum(self, keep: int = 1) -> None:
        """Deletes manifests but the newest ``keep``, and data that none of these knows. Not beside writers
        that have not committed yet."""
        found = self.versions()
        for v in found[: max(0, len(found) - keep)]:
            self.fs.delete(self._path(f"{self.root}/manifests/v{v:012d}.json"), False)
        live = {s["path"] for v in found[-keep:] for s in self.manifest(v)["shards"]}
        for run, _, _ in self._list(f"{self.root}/data"):
            paths = [p for p, _, _ in self._list(run)]
            known = [p for p in paths if "/".join(["data", *p.rsplit("/", 2)[1:]]) in live]
            if not known:
                self.fs.delete(self._path(run), True)


def arrivals(docs: DataFrame, n: int = ARRIVALS) -> list[DataFrame]:
    """The table as it might have come in: its files, at most ``FILES`` at once, so that their number grows with the
    table; one of few files comes in ``n`` parts by hash of its rows."""
    files = sorted(docs.inputFiles())
    if len(files) >= n:
        return [docs.sparkSession.read.schema(docs.schema).parquet(*files[i : i + FILES]) for i in range(0, len(files), FILES)]
    part = F.pmod(F.xxhash64("doc_id", F.length("text")), F.lit(n))
    return [docs.where(part == i) for i in range(n)]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    store = ShardStore(spark, f"{shared_dir(spark)}/shards-{uuid.uuid4().hex}")
    for part in arrivals(docs):
        store.append(part)
        store.compact()
        store.vacuum()
    store.compact(finish=True)
    store.vacuum()
    rows = store.read()
    if not store.manifest()["shards"]:
        return rows.select("doc_id", "n_chars", F.lit(0).alias("tier"), F.lit("").alias("shard"))
    name = F.element_at(F.split("_metadata.file_path", "/"), -2)
    return rows.select("doc_id", "n_chars", F.regexp_extract(name, r"^t(\d+)-", 1).cast("int").alias("tier"), F.concat_ws("/", name, "_metadata.file_name").alias("shard"))
