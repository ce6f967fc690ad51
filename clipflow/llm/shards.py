"""Sharded storage with size-tiered compaction and a versioned manifest.

An append is a run: a folder of small immutable shards (parquet files). Compaction sorts runs into tiers of similar shard
size and merges those of a tier into a run of files of a target size, by scans whose splits are packed with whole
shards: there is no shuffle. Each change writes a manifest and commits it by one rename to the next version's name, which
fails if another writer was first. The manifest names runs, not files, so it grows with appends that await compaction.
Readers read the runs of one version; old ones go when no version that is kept names them.

All files are reached through Hadoop's file system, so the store may be anywhere that the session can write.
"""

from __future__ import annotations

import math
import uuid
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from clipflow.llm.common import CommitConflict, Manifest, remove

TARGET = 128 << 20


@dataclass(frozen=True)
class Run:
    path: str
    files: int
    size: int
    rows: int
    level: int  # merges that its rows have been through

    @property
    def shard(self) -> int:
        """Bytes of its shards, on average."""
        return self.size // max(self.files, 1)


class ShardStore:
    def __init__(self, spark: SparkSession, root: str, target: int = TARGET, fan_in: int = 4, similar: float = 4.0):
        self.spark, self.root, self.target, self.fan_in, self.similar = spark, root.rstrip("/"), target, fan_in, similar
        self.manifest = Manifest(spark, self.root)

    def versions(self) -> list[int]:
        return self.manifest.versions()

    def read_manifest(self, version: int | None = None) -> tuple[int, T.StructType | None, list[Run]]:
        """(version, schema, runs); version 0 is the empty store."""
        version, found = self.manifest.read(version)
        return (version, T.StructType.fromJson(found["schema"]), [Run(**r) for r in found["runs"]]) if found else (0, None, [])

    def commit(self, base: int, schema: T.StructType, runs: list[Run]) -> int:
        """Make ``runs`` version base + 1, or raise CommitConflict if that version exists."""
        return self.manifest.commit(base, {"schema": schema.jsonValue(), "runs": [asdict(r) for r in runs]})

    def _write(self, df: DataFrame, level: int, most_rows: int = 0) -> list[Run]:
        """The rows as one new run, or none if there are no rows."""
        path = f"{self.root}/data/{uuid.uuid4().hex}"
        df.write.option("maxRecordsPerFile", most_rows).parquet(path)
        folder = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        status = folder.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).listStatus(folder)
        sizes = [s.getLen() for s in status if s.getPath().getName().endswith(".parquet")]
        rows = self.spark.read.schema(df.schema).parquet(path).count()  # from the files' footers
        if rows:
            return [Run(path, len(sizes), sum(sizes), rows, level)]
        remove(self.spark, path)
        return []

    def append(self, arrivals: DataFrame, shard_rows: int = 2_000) -> int:
        """Store arrivals as shards of at most ``shard_rows`` rows and commit them. Returns the version.

        Columns keep their names and types, which must be the store's; nulls, empty texts and repeated rows are rows.
        """
        new = self._write(arrivals, 0, shard_rows)
        while True:  # an append goes with whatever others have committed
            base, schema, runs = self.read_manifest()
            if schema is not None and schema.fieldNames() != arrivals.schema.fieldNames():
                raise ValueError(f"columns {arrivals.columns} differ from the store's {schema.fieldNames()}")
            try:
                return self.commit(base, schema or arrivals.schema, runs + new)
            except CommitConflict:
                continue

    def tiers(self, runs: list[Run]) -> list[list[Run]]:
        """Runs of shards under half the target, by powers of ``similar``: shard sizes within a tier differ by that factor at most."""
        by: dict[int, list[Run]] = {}
        for r in runs:
            if r.shard < self.target / 2:
                by.setdefault(int(math.log(max(r.shard, 1), self.similar)), []).append(r)
        return [sorted(by[k], key=lambda r: (r.size, r.path)) for k in sorted(by)]

    def _due(self, runs: list[Run], all_tiers: bool) -> list[Run]:
        """The runs to merge: the tier of the smallest shards that has ``fan_in`` of them, if that makes fewer shards."""
        tiers = self.tiers(runs)
        found = [t for t in tiers if sum(r.files for r in t) >= self.fan_in] or ([sum(tiers, [])] if all_tiers and tiers else [])
        return next((t for t in found if sum(r.files for r in t) > max(1, -(-sum(r.size for r in t) // self.target))), [])

    def compact(self, all_tiers: bool = False) -> int:
        """Merge each tier of at least ``fan_in`` shards (with ``all_tiers``: any two small ones); returns the last version.

        What others commit meanwhile stays; if they took one of the merged runs away, the merge is dropped.
        """
        failed: set[frozenset] = set()
        while True:
            version, schema, runs = self.read_manifest()
            due = self._due(runs, all_tiers)
            paths = frozenset(r.path for r in due)
            if not due or paths in failed:
                return version
            new = self._merge(due, schema)
            if sum(r.files for r in new) >= sum(r.files for r in due):  # already as packed as splits allow
                failed.add(paths)
                self._drop(new)
                continue
            while True:
                version, schema, runs = self.read_manifest()
                if not paths <= {r.path for r in runs}:
                    self._drop(new)
                    break
                try:
                    self.commit(version, schema, [r for r in runs if r.path not in paths] + new)
                    break
                except CommitConflict:
                    continue
            self.expire()

    def _drop(self, runs: list[Run]) -> None:
        for r in runs:
            remove(self.spark, r.path)

    def _merge(self, runs: list[Run], schema: T.StructType) -> list[Run]:
        side = self.spark.newSession()  # its settings are its own
        for key, value in {"maxPartitionBytes": self.target, "openCostInBytes": 0, "minPartitionNum": 1}.items():
            side.conf.set(f"spark.sql.files.{key}", str(value))
        return self._write(side.read.schema(schema).parquet(*[r.path for r in runs]), max(r.level for r in runs) + 1)

    def expire(self, keep: int = 2) -> None:
        """Forget all but the last ``keep`` versions, and delete runs that none of these names and an older one did.

        Readers of the version before the last keep their files.
        """
        known = self.versions()
        old, live = known[:-keep], known[-keep:]
        named = {r.path for v in live for r in self.read_manifest(v)[2]}
        for v in old:
            self._drop([r for r in self.read_manifest(v)[2] if r.path not in named])
            self.manifest.forget(v)

    def read(self, version: int | None = None) -> DataFrame:
        """The rows of a version. An empty store without columns cannot be read."""
        _, schema, runs = self.read_manifest(version)
        if schema is None:
            raise ValueError("the store is empty")
        if not runs:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[r.path for r in runs])


def reshard(docs: DataFrame, root: str, target: int = TARGET, shard_rows: int = 2_000) -> DataFrame:
    """Append ``docs`` to the store at ``root``, compact it, and return the rows of the committed version.

    All columns and rows come back as they were, nulls, empty texts and repeated rows included, with ``_shard``, the name
    of the file that holds a row; an input column of that name is refused. An empty table gives no rows.
    """
    if "_shard" in docs.columns:
        raise ValueError("the input has a column _shard")
    store = ShardStore(docs.sparkSession, root, target)
    store.append(docs, shard_rows)
    store.compact(all_tiers=True)
    _, schema, runs = store.read_manifest()
    if not runs:
        return docs.sparkSession.createDataFrame([], T.StructType([*schema.fields, T.StructField("_shard", T.StringType())]))
    return store.read().withColumn("_shard", F.col("_metadata.file_name"))
