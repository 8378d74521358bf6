"""View store: a view is its base and an ordered log of signed deltas, mergeable because sums of payloads commute.

In memory the log is a list of DataFrames, folded into one written table now and then, so that neither the log nor the
plans grow with the number of updates.  On disk each append is a folder of Parquet files, split by a hash of the
leading key, and a version becomes visible when its manifest is renamed into place; the manifest also says which batch
of each stream came last, so a batch that is delivered again after a restart is passed over.
"""

from __future__ import annotations

import copy
import json
import uuid
from collections.abc import Iterable

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ringview.functions.rings import Ring
from ringview.operators.relation import AT, KeyedRelation, union, without_number
from ringview.sources.io import written

BUCKET = "__bucket"


class ViewStore:
    """In memory: each part of a view is kept as Spark's cached columns (spilled to disk, rebuilt if an executor is lost).
    After ``fold`` deltas a view is written to the shared folder and read again: its plan starts anew, old parts are freed."""

    def __init__(self, ring: Ring, cached: bool = True, fold: int = 8):
        self.ring, self.cached, self.fold = ring, cached, fold
        self.parts: dict[str, list[KeyedRelation]] = {}
        #: Rings of views that differ from the query's, and views that are read only as results.
        self.rings: dict[str, Ring] = {}
        self.only_read_last: set[str] = set()
        self.version = 0
        self.done: dict[str, int] = {}
        self._last: dict[str, KeyedRelation] = {}

    def create(self, name: str, rel: KeyedRelation) -> None:
        self.parts[name] = [self._keep(name, rel)]

    def latest(self, name: str) -> KeyedRelation:
        """The last change of a view, as it was kept: with the numbers of its batches, if it came with them."""
        return self._last[name]

    def append(self, name: str, delta: KeyedRelation) -> None:
        self._last[name] = self._keep(name, delta)
        self.parts.setdefault(name, []).append(without_number(self._last[name]))
        if len(self.parts[name]) > self.fold:
            old, whole = self.parts[name], self.read(name)
            self.parts[name] = [KeyedRelation(written(whole.df, "fold"), whole.keys, whole.ring)]
            for p in old:
                p.df.unpersist()

    def _keep(self, name: str, rel: KeyedRelation) -> KeyedRelation:
        return KeyedRelation(rel.df.persist(StorageLevel.MEMORY_AND_DISK), rel.keys, rel.ring) if self.cached and name not in self.only_read_last else rel

    def force(self) -> None:
        """Do the work of the latest changes now; from here on results are kept like other views."""
        self.only_read_last.clear()
        for name in self.names():
            self.parts[name][-1].df.count()

    def close(self) -> None:
        for parts in self.parts.values():
            for p in parts:
                p.df.unpersist()

    def as_now(self) -> ViewStore:
        """For reading only: the views as they are, whatever is appended later."""
        out = copy.copy(self)
        out.parts = {n: list(p) for n, p in self.parts.items()}
        return out

    def read(self, name: str) -> KeyedRelation:
        parts = self.parts[name]
        return parts[0] if len(parts) == 1 else union(*parts)

    def read_for(self, name: str, change: KeyedRelation) -> KeyedRelation:
        """What a change can meet in a view: all of it, or less where the layout allows."""
        return self.read(name)

    def names(self) -> list[str]:
        return list(self.parts)

    def has(self, stream: str, batch: int) -> bool:
        return batch <= self.done.get(stream, -1)

    def commit(self, stream: str | None = None, batch: int = 0) -> int:
        self.version += 1
        if stream is not None:
            self.done[stream] = batch
        return self.version

    def size(self, name: str) -> int:
        return self.read(name).size()


class ParquetStore(ViewStore):
    """On disk, for any Hadoop path.  Uncommitted appends are not visible after a restart; a batch id commits once.

    A view of over ``prune`` rows is read by bucket: only files that hold keys of a change are opened.
    """

    def __init__(self, spark: SparkSession, path: str, ring: Ring, buckets: int = 8, fold: int = 8, prune: int = 1_000_000):
        super().__init__(ring, fold=fold)
        self.spark, self.path, self.buckets, self.prune = spark, path.rstrip("/"), buckets, prune
        self.log: dict[str, list[str]] = {}
        self.schemas: dict[str, str] = {}
        self.keys: dict[str, tuple[str, ...]] = {}
        self.rows: dict[str, int] = {}
        self._load()

    def _hadoop(self):
        jvm = self.spark._jvm
        p = jvm.org.apache.hadoop.fs.Path(self.path)
        return jvm, p.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def _load(self) -> None:
        jvm, fs = self._hadoop()
        at = jvm.org.apache.hadoop.fs.Path(f"{self.path}/manifest")
        if not fs.exists(at):
            return
        found = sorted(int(s.getPath().getName()[1:-5]) for s in fs.listStatus(at) if s.getPath().getName().startswith("v"))
        if found:
            text = "\n".join(r.value for r in self.spark.read.text(f"{self.path}/manifest/v{found[-1]}.json").collect())
            m = json.loads(text)
            self.version, self.log, self.keys, self.done, self.schemas, self.rows = m["version"], m["log"], {k: tuple(v) for k, v in m["keys"].items()}, m["done"], m["schemas"], m["rows"]

    def _write(self, name: str, rel: KeyedRelation) -> None:
        part = f"{self.path}/{name}/{uuid.uuid4().hex}"
        keys = without_number(rel).keys
        lead = keys[:1]
        bucket = F.pmod(F.xxhash64(*lead), F.lit(self.buckets)).cast("int") if lead else F.lit(0)
        rel.df.withColumn(BUCKET, bucket).write.partitionBy(BUCKET).parquet(part)
        self.log.setdefault(name, []).append(part)
        self.keys[name], self.schemas[part] = keys, rel.df.schema.json()
        if name not in self.rows or len(self.log[name]) == 1:
            self.rows[name] = self._part(name, part, None).df.count()  # from the files' footers

    def create(self, name: str, rel: KeyedRelation) -> None:
        self.log[name] = []
        self._write(name, rel)

    def append(self, name: str, delta: KeyedRelation) -> None:
        self._write(name, delta)
        last = self._part(name, self.log[name][-1], None)
        self._last[name] = KeyedRelation(last.df, (*last.keys, AT), last.ring) if AT in delta.keys else last
        if len(self.log[name]) > self.fold:
            whole = self.read(name)
            self.log[name] = []
            self._write(name, whole)

    def as_now(self) -> ViewStore:
        out = super().as_now()
        out.log, out.rows = {n: list(p) for n, p in self.log.items()}, dict(self.rows)
        return out

    def _part(self, name: str, path: str, buckets: Iterable[int] | None) -> KeyedRelation:
        schema = T.StructType.fromJson(json.loads(self.schemas[path])).add(BUCKET, T.IntegerType())
        df = self.spark.read.schema(schema).parquet(path)
        df = (df if buckets is None else df.where(F.col(BUCKET).isin(list(buckets)))).drop(BUCKET)
        return KeyedRelation(df, self.keys[name], self.rings.get(name, self.ring))

    def force(self) -> None:
        """Appends are written at once."""

    def read_for(self, name: str, change: KeyedRelation) -> KeyedRelation:
        lead = self.keys[name][:1]
        if not lead or lead[0] not in change.keys or self.rows[name] <= self.prune:
            return self.read(name)
        return self.read(name, self.buckets_of(change.df, lead[0]))

    def read(self, name: str, buckets: Iterable[int] | None = None) -> KeyedRelation:
        """The view, or only some of its buckets: other files are not opened."""
        parts = [self._part(name, p, buckets) for p in self.log[name]]
        return parts[0] if len(parts) == 1 else union(*parts)

    def buckets_of(self, delta: DataFrame, key: str) -> list[int]:
        """Buckets that a delta's keys fall into: at most the number of buckets, whatever the delta's size."""
        return [r[0] for r in delta.select(F.pmod(F.xxhash64(key), F.lit(self.buckets)).cast("int").alias("b")).distinct().collect()]

    def names(self) -> list[str]:
        return list(self.log)

    def commit(self, stream: str | None = None, batch: int = 0) -> int:
        super().commit(stream, batch)
        live = {p for parts in self.log.values() for p in parts}
        self.schemas = {p: x for p, x in self.schemas.items() if p in live}
        jvm, fs = self._hadoop()
        path = jvm.org.apache.hadoop.fs.Path
        done, draft = path(f"{self.path}/manifest/v{self.version}.json"), path(f"{self.path}/manifest/_draft-{uuid.uuid4().hex}")
        out = fs.create(draft)
        out.write(bytearray(json.dumps({"version": self.version, "log": self.log, "keys": self.keys, "done": self.done, "schemas": self.schemas, "rows": self.rows}).encode()))
        out.close()
        if not fs.rename(draft, done):
            raise RuntimeError(f"version {self.version} exists: another writer committed it")
        return self.version

    def vacuum(self) -> int:
        """Delete manifests before the current one and parts that it does not name; for when nothing reads them any more."""
        jvm, fs = self._hadoop()
        path, gone = jvm.org.apache.hadoop.fs.Path, 0
        live = {p.rsplit("/", 1)[1] for parts in self.log.values() for p in parts} | {f"v{self.version}.json"}
        for name in ["manifest", *self.log]:
            for f in fs.listStatus(path(f"{self.path}/{name}")):
                if f.getPath().getName() not in live:
                    fs.delete(f.getPath(), True)
                    gone += 1
        return gone

    def bytes(self) -> int:
        """Size of the live files."""
        jvm, fs = self._hadoop()
        return sum(fs.getContentSummary(jvm.org.apache.hadoop.fs.Path(p)).getLength() for parts in self.log.values() for p in parts)
