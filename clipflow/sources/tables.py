"""Readers of the given tables and of other formats, always with the columns asked for."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table's rows, only ``columns`` if given, so that scans prune."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_any(spark: SparkSession, path: str, kind: str, schema: str | None = None, **options: str) -> DataFrame:
    """csv, json, text, orc, parquet or binaryFile; a schema spares the inference pass over the data."""
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_clips(df: DataFrame, path: str, partition: tuple[str, ...] = ("split",), kind: str = "parquet") -> None:
    """The mined corpus by split; readers of one split prune the others."""
    df.write.partitionBy(*partition).mode("overwrite").format(kind).save(path)


_made: list[tuple[SparkSession, str]] = []


def _forget() -> None:
    """Delete what ``written`` has made, when the driver's process ends: results may read it until then."""
    for spark, path in _made:
        try:
            if spark.sparkContext._jsc is not None:
                target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
                target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # the session went first
            return


def written(df: DataFrame, name: str, by: str | None = None, **options: int | str) -> DataFrame:
    """The rows from a table written once to the folder that driver and executors share: what reads them many times is
    planned apart, and a lost executor costs no rerun of what led to them. ``by``: a column whose values are read apart."""
    spark = df.sparkSession
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    path = f"{folder.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not _made:
        atexit.register(_forget)
    _made.append((spark, path))
    (df.write.partitionBy(by) if by else df.write).options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def dropped(df: DataFrame) -> None:
    """Delete the table that ``written`` made, of which no part is read any more."""
    files = df.inputFiles()[:1]
    spark = df.sparkSession
    for made, path in [x for x in _made if x[0] is spark and files and f"/{x[1].rpartition('/')[2]}/" in files[0]]:
        target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        _made.remove((made, path))
