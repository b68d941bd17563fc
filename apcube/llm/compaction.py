"""An append-only shard store with size-tiered compaction and atomically committed, versioned manifests.

Arrivals are written as small immutable Parquet shards. ``compact`` takes the tiers (powers of ``fan_in`` of the size)
that hold at least ``fan_in`` shards and rewrites each as files of about the target size. Shards are never changed; a
version is a manifest (a Parquet table with one row per shard, made from the files' own metadata) and a numbered
version file that names it. Publishing that file is the commit: it appears whole and never in another's place, so of two
writers one wins, and the other must read the new version and try again. A writer that dies on its way leaves files that
no version names (``vacuum`` deletes them) and blocks nobody; a version file that can't be read is passed over. Readers
see one whole version. Only DataFrame operations and the file
system's own calls are used; merging reads and writes each shard once, without a shuffle.
"""

from __future__ import annotations

import json
import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from apcube.llm.storage import hadoop, publish


class CommitConflict(RuntimeError):
    """Another writer has committed the version first."""


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target_bytes: int = 128 << 20, fan_in: int = 4):
        self.spark, self.root, self.target, self.fan_in = spark, root.rstrip("/"), target_bytes, fan_in

    def _list(self, path: str, suffix: str) -> list[tuple[str, int]]:
        fs, p = hadoop(self.spark, path)
        if not fs.exists(p):
            return []
        files, out = fs.listFiles(p, True), []
        while files.hasNext():
            f = files.next()
            name = f.getPath().toString()
            if name.endswith(suffix) and f.getLen():
                out.append((name, f.getLen()))
        return sorted(out)

    def _numbers(self) -> list[int]:
        """The numbers of all version files, also of damaged ones."""
        fs, p = hadoop(self.spark, f"{self.root}/_versions")
        names = [f.getPath().getName() for f in fs.listStatus(p)] if fs.exists(p) else []
        return sorted(int(n.removesuffix(".json")) for n in names if n.endswith(".json") and n.removesuffix(".json").isdigit())

    def versions(self) -> list[int]:
        return [n for n in self._numbers() if self._version(n) is not None]

    def head(self) -> dict | None:
        """The newest version file's content."""
        return self._newest()[0]

    def _newest(self) -> tuple[dict | None, int]:
        """The newest readable version and the number that a commit upon it must create: past all that are there."""
        numbers = self._numbers()
        found = next((v for v in map(self._version, reversed(numbers)) if v is not None), None)
        return found, (numbers[-1] if numbers else 0) + 1

    def _version(self, number: int) -> dict | None:
        fs, p = hadoop(self.spark, f"{self.root}/_versions/{number:010d}.json")
        stream = fs.open(p)
        try:
            return json.loads(bytes(stream.readAllBytes()).decode())
        except ValueError:
            return None
        finally:
            stream.close()

    def _commit(self, number: int, manifest: DataFrame, schema: T.StructType, note: str) -> int:
        """Writes the manifest and publishes version ``number``; raises CommitConflict if that exists."""
        path = f"{self.root}/_manifests/{uuid.uuid4().hex}"
        manifest.coalesce(1).write.parquet(path)
        content = json.dumps({"version": number, "manifest": path, "schema": schema.json(), "note": note})
        if not publish(self.spark, f"{self.root}/_versions/{number:010d}.json", content.encode()):
            raise CommitConflict(f"version {number} exists")
        return number

    def _described(self, paths: list[str]) -> DataFrame:
        """path, bytes, rows of shards, from file metadata and footers."""
        meta = self.spark.read.parquet(*paths).select(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_size").alias("bytes"))
        return meta.groupBy("path").agg(F.max("bytes").alias("bytes"), F.count("*").alias("rows"))

    def manifest(self, number: int | None = None) -> DataFrame:
        """path, bytes, rows, tier of the live shards."""
        return self._manifest(self.head() if number is None else self._version(number))

    def _manifest(self, version: dict | None) -> DataFrame:
        if version is None:
            return self.spark.range(0).select(F.lit("").alias("path"), F.col("id").alias("bytes"), F.col("id").alias("rows"), F.lit(0).alias("tier"))
        return self.spark.read.parquet(version["manifest"]).select("path", "bytes", "rows", self._tier(F.col("bytes")).alias("tier"))

    def _tier(self, size: Column) -> Column:
        return F.floor(F.log(F.greatest(size, F.lit(1)).cast("double")) / math.log(self.fan_in)).cast("int")

    def read(self, number: int | None = None) -> DataFrame:
        """The rows of a version."""
        version = self.head() if number is None else self._version(number)
        if version is None:
            raise FileNotFoundError(f"{self.root} has no version")
        schema = T.StructType.fromJson(json.loads(version["schema"]))
        paths = [r["path"] for r in self._manifest(version).select("path").collect()]
        if not paths:
            return self.spark.range(0).select(*(F.lit(None).cast(f.dataType).alias(f.name) for f in schema))
        return self.spark.read.schema(schema).parquet(*paths)

    def append(self, df: DataFrame, note: str = "append") -> int:
        """Writes ``df`` as new shards and commits them; returns the version."""
        run = f"{self.root}/data/{uuid.uuid4().hex}"
        df.write.parquet(run)
        return self._add([p for p, _ in self._list(run, ".parquet")], df.schema, note)

    def append_batches(self, df: DataFrame, batch: Column) -> list[int]:
        """Writes ``df`` once, as arrivals told apart by ``batch``, and commits them one after another."""
        run = f"{self.root}/data/{uuid.uuid4().hex}"
        name = "__arrival"
        while name.lower() in (c.lower() for c in df.columns):
            name += "_"
        df.withColumn(name, batch).write.partitionBy(name).parquet(run)
        arrivals: dict[str, list[str]] = {}
        for path, _ in self._list(run, ".parquet"):
            arrivals.setdefault(path.rpartition("/")[0], []).append(path)
        if not arrivals:
            return [self._add([], df.schema, "empty")]
        return [self._add(arrivals[k], df.schema, k.rpartition("/")[2]) for k in sorted(arrivals)]

    def _add(self, paths: list[str], schema: T.StructType, note: str) -> int:
        new = self._described(paths) if paths else None
        while True:
            head, number = self._newest()
            old = self._manifest(head).select("path", "bytes", "rows")
            try:
                return self._commit(number, old.union(new) if new is not None else old, schema, note)
            except CommitConflict:
                continue  # an append goes with any other change; the next round sees the number that was taken

    def compact(self) -> list[int]:
        """Merges full tiers until none is left; returns the versions it committed. Files of at least half the target
        are never read again. A merge that would not lessen the number of files is not made."""
        done = []
        while True:
            head, number = self._newest()
            if head is None:
                return done
            small = self._manifest(head).where(F.col("bytes") < self.target // 2)
            tiers = small.groupBy("tier").agg(F.count("*").alias("n"), F.sum("bytes").alias("b"), F.sum("rows").alias("r")).where(F.col("n") >= self.fan_in).orderBy("tier").collect()
            tiers = [t for t in tiers if -(-t["b"] // self.target) < t["n"]]
            if not tiers:
                return done
            schema = T.StructType.fromJson(json.loads(head["schema"]))
            old, new, rows = [], [], 0
            for t in tiers:
                paths = [r["path"] for r in small.where(F.col("tier") == t["tier"]).orderBy("path").collect()]
                run = f"{self.root}/data/{uuid.uuid4().hex}"
                self.spark.read.schema(schema).parquet(*paths).coalesce(-(-t["b"] // self.target)).write.parquet(run)
                old += paths
                new += [p for p, _ in self._list(run, ".parquet")]
                rows += t["r"]
            merged = self._described(new)
            if merged.agg(F.sum("rows")).first()[0] != rows:
                raise RuntimeError("a merge changed the number of rows; nothing was committed")
            gone = self._manifest(head).where(F.col("path").isin(old)).select("path") if len(old) < 1000 else small.where(F.col("tier").isin([t["tier"] for t in tiers])).select("path")
            live = self._manifest(head).select("path", "bytes", "rows").join(gone, "path", "left_anti")
            try:
                done.append(self._commit(number, live.union(merged), schema, f"compact tiers {[t['tier'] for t in tiers]}"))
            except CommitConflict:
                for path in new:
                    fs, p = hadoop(self.spark, path)
                    fs.delete(p, False)

    def vacuum(self, keep: int = 1) -> int:
        """Deletes shards that none of the last ``keep`` versions names; returns their number. Writers must rest."""
        live: set[str] = set()
        for v in self.versions()[-keep:]:
            live |= {r["path"].removeprefix("file:").lstrip("/") for r in self.manifest(v).select("path").collect()}
        gone = [p for p, _ in self._list(f"{self.root}/data", ".parquet") if p.removeprefix("file:").lstrip("/") not in live]
        for path in gone:
            fs, p = hadoop(self.spark, path)
            fs.delete(p, False)
        return len(gone)


def compacted(rows: DataFrame, root: str, arrivals: int = 16, target_bytes: int = 128 << 20, fan_in: int = 4, id_col: str = "doc_id") -> ShardStore:
    """A store at ``root`` of all ``rows``, arrived in ``arrivals`` batches by a hash of the id, compacted and vacuumed.

    Every row is kept as it is, in any number of copies; nulls, empty and very long texts and further columns of any name
    are stored alike (a null id is in one batch with others). An empty table is a version without shards.
    """
    store = ShardStore(rows.sparkSession, root, target_bytes, fan_in)
    store.append_batches(rows, F.pmod(F.xxhash64(id_col), F.lit(arrivals)).cast("int"))
    store.compact()
    store.vacuum()
    return store
