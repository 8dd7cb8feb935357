"""Versions of a graph: immutable bucket files, a manifest for each version, one writer, any number of readers.

A version's manifest lists a folder for each bucket of vertices and each family of rows: chunks of out-neighbours (`out`),
of in-neighbours where the graph is directed (`in`), and vertices without edges (`alone`). A new version lists the
parent's folders for every bucket that its batch did not touch. Publishing creates the next manifest file, which fails if it exists, so a version appears whole
or not at all and two writers cannot both win. Readers hold a lease; folders that no manifest in use names are deleted.

The number of buckets comes from the first graph's size, so that a bucket is about BUCKET_CHUNKS chunk rows, and is kept;
inside a bucket the rows go to as many files as they need, so that a hub's chunks are no single task. Chunks are stored
in the store's codec.

Paths may be of any file system that Spark reads; manifests and leases are written through the same one.
"""

from __future__ import annotations

import json
import time
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.codec import COLUMNS, coded, opened
from ..functions.hashing import wide_hash
from ..operators import sets
from ..operators.graph import Graph

#: Chunk rows of a bucket, about, where the number of buckets is not given; the least number of buckets; rows of a file.
BUCKET_CHUNKS, LEAST_BUCKETS, FILE_CHUNKS = 1 << 20, 16, 1 << 18


class WriterConflict(RuntimeError):
    """Another writer has published this version first."""


@dataclass(frozen=True)
class Handle:
    version: int
    lease: str


class VersionStore:
    def __init__(self, spark: SparkSession, path: str, b: int = 256, seed: int = 0, buckets: int | None = None, codec: str = "plain"):
        self.spark, self.path, self.b, self.seed, self.buckets, self.codec = spark, path.rstrip("/"), b, seed, buckets, codec
        jvm = spark._jvm
        self._jvm, self._path = jvm, jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())

    # ------------------------------------------------------------------------------------------------- small files

    def _create(self, name: str, text: str) -> None:
        """Write a new small file; fails where it exists."""
        target = self._path(f"{self.path}/{name}")
        try:
            out = self._fs.create(target, False)
        except Exception as error:
            if self._fs.exists(target):
                raise WriterConflict(name) from error
            raise
        out.write(bytearray(text.encode()))
        out.close()

    def _read(self, name: str) -> str:
        stream = self._fs.open(self._path(f"{self.path}/{name}"))
        try:
            return bytes(self._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
        finally:
            stream.close()

    def _list(self, name: str) -> list[str]:
        folder = self._path(f"{self.path}/{name}")
        return sorted(s.getPath().getName() for s in self._fs.listStatus(folder)) if self._fs.exists(folder) else []

    # ------------------------------------------------------------------------------------------------------ versions

    def versions(self) -> list[int]:
        return sorted(int(n[1:-5]) for n in self._list("manifest") if n.startswith("v") and n.endswith(".json"))

    def manifest(self, version: int | None = None) -> dict:
        """Of a version, or of the newest; the reader's view of everything else."""
        version = self.versions()[-1] if version is None else version
        return json.loads(self._read(f"manifest/v{version:012d}.json"))

    def bucket(self, owner="owner", buckets: int | None = None):
        return F.pmod(wide_hash(F.col(owner), 7), F.lit(buckets or self.manifest()["buckets"])).cast("int")

    def _family(self, about: dict, files: list[dict], name: str) -> DataFrame:
        """The rows of a family, as a frame without the bucket."""
        schema = "vid long" if name == "alone" else _schema(about)
        paths = sorted(f"{self.path}/{f['path']}" for f in files if f["family"] == name)
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def _graph(self, about: dict, files: list[dict]) -> Graph:
        into = self._family(about, files, "in") if about["directed"] else None
        return Graph(self._family(about, files, "out"), about["b"], about["seed"], self._family(about, files, "alone"), into)

    def graph(self, version: int | None = None, owners: DataFrame | None = None) -> Graph:
        """The graph of a version; with owners, only the buckets that hold them are read."""
        about = self.manifest(version)
        files = about["files"]
        if owners is not None:
            wanted = {r["k"] for r in owners.select(self.bucket(buckets=about["buckets"]).alias("k")).distinct().collect()}  # at most `buckets` numbers
            files = [f for f in files if f["bucket"] in wanted]
        return self._graph(about, files)

    def as_of(self, version: int | None = None, timestamp: float | None = None) -> Graph:
        """The newest version at a point in time, or a version by number."""
        if timestamp is not None:
            version = max(v for v in self.versions() if self.manifest(v)["published_at"] <= timestamp)
        return self.graph(version)

    def history(self) -> DataFrame:
        """(version, parent, n, m, touched_buckets) of all versions."""
        rows = [(m["version"], m["parent"], m["n"], m["m"], m["touched"]) for m in map(self.manifest, self.versions())]
        return self.spark.createDataFrame(rows, "version long, parent long, n long, m long, touched_buckets int")

    def _write(self, g: Graph, parent: dict | None, touched: set[int] | None, batch_id: int | None, buckets: int) -> int:
        version = parent["version"] + 1 if parent else 0
        folder = f"data/{uuid.uuid4().hex}"
        about = {"b": g.b, "seed": g.seed, "codec": self.codec, "directed": g.into is not None, "value": dict(g.chunks.dtypes).get("head_val"), "sum": dict(g.chunks.dtypes).get("agg"), "buckets": buckets}
        made, seen = [], self.spark.createDataFrame([], "vid long")
        for family, rows in (("out", g.chunks), ("in", g.into), ("alone", g.isolated)):
            if rows is not None:
                new = self._write_family(about, f"{folder}/{family}", family, rows, seen)
                made += new
                if new:
                    seen = seen.unionByName(self._family(about, new, family).select(F.col("vid" if family == "alone" else "owner").alias("vid")))
        kept = [f for f in parent["files"] if touched is not None and f["bucket"] not in touched] if parent else []
        files = kept + made
        text = about | {"version": version, "parent": parent["version"] if parent else -1, "n": sum(f["n"] for f in files), "m": sum(f["m"] for f in files if f["family"] == "out"), "touched": len({f["bucket"] for f in made}) if touched is None else len(touched)}
        text |= {"batch_id": batch_id, "batch_ids": [*(parent["batch_ids"] if parent else []), *([] if batch_id is None else [batch_id])], "published_at": time.time(), "files": files}
        self._create(f"manifest/v{version:012d}.json", json.dumps(text))
        return version

    def _write_family(self, about: dict, folder: str, family: str, rows: DataFrame, seen: DataFrame) -> list[dict]:
        """What was written of a family: bucket, path, n (vertices that are not among those seen), m (elements)."""
        key = "vid" if family == "alone" else "owner"
        order = ["bucket", key] if family == "alone" else ["bucket", key, "head"]
        rows = rows if family == "alone" else coded(opened(rows), self.codec)
        dealt = rows.withColumn("bucket", self.bucket(key, about["buckets"]))
        dealt.repartitionByRange(*order).sortWithinPartitions(*order).write.option("maxRecordsPerFile", FILE_CHUNKS).partitionBy("bucket").parquet(f"{self.path}/{folder}")
        if not any(name.startswith("bucket=") for name in self._list(folder)):
            return []
        schema = "vid long" if family == "alone" else _schema(about)
        mine = self.spark.read.schema(f"{schema}, bucket int").parquet(f"{self.path}/{folder}")
        new = mine.select("bucket", F.col(key).alias("vid")).distinct().join(seen, "vid", "left_anti").groupBy("bucket").agg(F.count("*").alias("n"))
        stats = mine.groupBy("bucket").agg(F.sum(F.lit(0) if family == "alone" else sets.weight()).alias("m")).join(new, "bucket", "left")
        return [{"family": family, "bucket": r["bucket"], "path": f"{folder}/bucket={r['bucket']}", "n": r["n"] or 0, "m": r["m"]} for r in stats.orderBy("bucket").collect()]  # at most `buckets` rows

    def publish(self, g: Graph) -> int:
        """A whole graph as the next version, with its in-neighbours, values and vertices without edges."""
        parent = self.manifest() if self.versions() else None
        buckets = parent["buckets"] if parent else self.buckets or max(LEAST_BUCKETS, g.chunks.count() // BUCKET_CHUNKS + 1)
        return self._write(g, parent, None, None, buckets)

    def apply(self, updates: DataFrame, batch_id: int | None = None) -> int:
        """A batch of updates (seq, op, src, dst[, weight]) as the next version; only buckets of a vertex at either end are
        read and written. A batch id that the newest version's history has already is not applied again."""
        parent = self.manifest()
        if batch_id is not None and batch_id in parent["batch_ids"]:
            return parent["version"]
        updates = updates.where("src IS NOT NULL AND dst IS NOT NULL").persist()
        try:
            ends = updates.select(F.explode(F.array("src", "dst")).alias("owner"))
            touched = {r["k"] for r in ends.select(self.bucket(buckets=parent["buckets"]).alias("k")).distinct().collect()}  # at most `buckets` numbers
            if not touched:
                return parent["version"]
            base = self._graph(parent, [f for f in parent["files"] if f["bucket"] in touched])
            return self._write(base.apply(updates), parent, touched, batch_id, parent["buckets"])
        finally:
            updates.unpersist()

    # -------------------------------------------------------------------------------------------------------- leases

    def acquire(self) -> Handle:
        version = self.versions()[-1]
        lease = f"v{version:012d}-{uuid.uuid4().hex}"
        self._create(f"lease/{lease}", "")
        return Handle(version, lease)

    def release(self, handle: Handle) -> bool:
        """True when this was the last holder of an old version, whose files can now be collected."""
        self._fs.delete(self._path(f"{self.path}/lease/{handle.lease}"), False)
        prefix = f"v{handle.version:012d}-"
        return handle.version != self.versions()[-1] and not any(n.startswith(prefix) for n in self._list("lease"))

    def gc(self, keep: int = 1) -> list[str]:
        """Drop versions that are neither leased nor among the newest `keep`, and folders that no version left names."""
        versions, held = self.versions(), {int(n[1:13]) for n in self._list("lease")}
        stay = set(versions[-keep:]) | held
        named = {f["path"] for v in versions if v in stay for f in self.manifest(v)["files"]}
        for v in versions:
            if v not in stay:
                self._fs.delete(self._path(f"{self.path}/manifest/v{v:012d}.json"), False)
        gone = []
        for folder in [f"data/{x}/{family}" for x in self._list("data") for family in self._list(f"data/{x}")]:
            for bucket in [n for n in self._list(folder) if n.startswith("bucket=")]:
                if f"{folder}/{bucket}" not in named:
                    self._fs.delete(self._path(f"{self.path}/{folder}/{bucket}"), True)
                    gone.append(f"{folder}/{bucket}")
        return gone


def _schema(about: dict) -> str:
    """Of the chunk rows of a version, in the order that `Graph` has."""
    tail = f"{COLUMNS[about['codec']]} {'binary' if about['codec'] == 'bytecode' else 'array<bigint>'}"
    value, total = about["value"], about["sum"]
    return f"owner long, head long, lo long, hi long, cnt int, {tail}" + (f", vals array<{value}>, head_val {value}, agg {total}" if value else "")
