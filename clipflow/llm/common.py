"""What several operators of this subpackage share."""

from __future__ import annotations

import atexit
import ctypes
import json
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

try:
    _libc = ctypes.CDLL("libc.so.6")
except OSError:  # another C library
    _libc = None

_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; only Spark's readers touch the path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package when the session was started elsewhere."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    paths = env.get("PYTHONPATH", "").split(os.pathsep)
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *filter(None, paths)])


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share. Only a session in one machine may go without a named one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = os.path.join(tempfile.gettempdir(), "checkpoints")
    os.makedirs(own, exist_ok=True)
    return f"file://{own}"


_made: list[tuple[SparkSession, str, bool]] = []


def _forget() -> None:
    """Delete the folders and tables that this process has made for its queries, while its session is alive."""
    for spark, name, is_table in _made:
        try:
            if spark.sparkContext._jsc is not None:
                spark.sql(f"DROP TABLE IF EXISTS {name}") if is_table else remove(spark, name)
        except Exception:  # the session went first
            return


def for_now(spark: SparkSession, name: str, is_table: bool = False) -> str:
    """Have a folder or table deleted when the driver's process ends, as results may read it until then."""
    if not _made:
        atexit.register(_forget)
    _made.append((spark, name, is_table))
    return name


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder's path."""
    return for_now(spark, f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage with a written table in the shared folder; lost executors cost no rerun of what led to it."""
    path = scratch(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def fresh(name: str, taken: list[str]) -> str:
    """``name`` with as many underscores before it as make it new."""
    while name in taken:
        name = f"_{name}"
    return name


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder of ours through Hadoop's file system."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class CommitConflict(RuntimeError):
    """Another writer has committed the version that this one meant to."""


class Manifest:
    """Numbered JSON states in a folder. A state is committed by one rename, which fails if its number is taken."""

    def __init__(self, spark: SparkSession, root: str):
        self.folder = f"{root.rstrip('/')}/manifest"
        self._jvm, self._conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()

    def _path(self, name: str = ""):
        return self._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}" if name else self.folder)

    def _fs(self):
        return self._path().getFileSystem(self._conf)

    def versions(self) -> list[int]:
        if not self._fs().exists(self._path()):
            return []
        names = (s.getPath().getName() for s in self._fs().listStatus(self._path()))
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def read(self, version: int | None = None) -> tuple[int, dict | None]:
        """(version, state); version 0 is the state of nothing."""
        known = self.versions()
        version = (known[-1] if known else 0) if version is None else version
        if not version:
            return 0, None
        stream = self._fs().open(self._path(f"v{version:08d}.json"))
        try:
            return version, json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8"))
        finally:
            stream.close()

    def commit(self, base: int, state: dict) -> int:
        """Make ``state`` version base + 1, or raise CommitConflict if that version exists."""
        version = base + 1
        final, temporary = self._path(f"v{version:08d}.json"), self._path(f".{uuid.uuid4().hex}")
        stream = self._fs().create(temporary, False)
        stream.write(bytearray(json.dumps(state).encode()))
        stream.close()
        rename = self._jvm.org.apache.hadoop.fs.Options.Rename
        options = self._jvm.java.lang.reflect.Array.newInstance(rename.NONE.getClass(), 1)
        options[0] = rename.NONE
        try:
            self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self._conf).rename(temporary, final, options)
        except Exception as error:
            self._fs().delete(temporary, False)
            if self._fs().exists(final):
                raise CommitConflict(f"version {version} exists") from error
            raise
        return version

    def forget(self, version: int) -> None:
        self._fs().delete(self._path(f"v{version:08d}.json"), False)


def release() -> None:
    """Give a worker's freed memory back to the system: it stays a worker between tasks, beside the JVM's heap."""
    pa.default_memory_pool().release_unused()
    if _libc is not None:
        _libc.malloc_trim(0)


def utf8(column: str) -> Column:
    """Text as bytes, null as empty: Python workers then neither decode nor encode."""
    return F.coalesce(F.col(column).cast("binary"), F.lit(b""))


def lower_ascii(data: bytes) -> bytes:
    return data.translate(_LOWER)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of unsigned 64-bit values."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))
