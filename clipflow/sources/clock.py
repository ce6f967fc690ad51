"""A data source of frame clocks: the frame times of numbered clips, made where they are read, and a sink of clip folders.

``spark.read.format("frame_clock")`` with the options ``clips``, ``seconds`` and ``fps`` gives clip, t, sec, one partition
for each ``clips_per_task`` clips. Writing (clip, ...) rows in that format to a path makes one JSON-lines file a task; the
commit writes a list of them, and readers go by that list, so that what failed tasks left is never read.
"""

from __future__ import annotations

import json
import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage


@dataclass
class Range(InputPartition):
    first: int
    last: int


@dataclass
class Written(WriterCommitMessage):
    name: str
    rows: int


class FrameClock(DataSource):
    @classmethod
    def name(cls) -> str:
        return "frame_clock"

    def schema(self) -> str:
        return "clip long, t int, sec double"

    def reader(self, schema) -> DataSourceReader:
        return ClockReader(self.options)

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return FolderWriter(self.options)


class ClockReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.clips, self.step = int(options.get("clips", 1)), int(options.get("clips_per_task", 1000))
        self.seconds, self.fps = float(options.get("seconds", 1)), float(options.get("fps", 25))
        if not 0 < self.fps or self.step < 1:
            raise ValueError("fps and clips_per_task are positive")

    def partitions(self) -> list[Range]:
        return [Range(a, min(a + self.step, self.clips)) for a in range(0, self.clips, self.step)] or [Range(0, 0)]

    def read(self, part: Range) -> Iterator[pa.RecordBatch]:
        n = int(self.seconds * self.fps)
        for clip in range(part.first, part.last):
            yield pa.RecordBatch.from_arrays([pa.array([clip] * n, pa.int64()), pa.array(range(n), pa.int32()), pa.array([t / self.fps for t in range(n)], pa.float64())], names=["clip", "t", "sec"])


class FolderWriter(DataSourceWriter):
    """For a folder that driver and tasks share as a mounted path."""

    def __init__(self, options: dict[str, str]):
        self.path = options["path"].removeprefix("file://")

    def write(self, rows: Iterator) -> Written:
        os.makedirs(self.path, exist_ok=True)
        name, n = f"part-{uuid.uuid4().hex}.jsonl", 0
        with open(f"{self.path}/{name}", "w") as out:
            for r in rows:
                out.write(json.dumps(r.asDict(), default=str) + "\n")
                n += 1
        return Written(name, n)

    def commit(self, messages: list[Written | None]) -> None:
        with open(f"{self.path}/_list.json", "w") as out:
            json.dump([{"name": m.name, "rows": m.rows} for m in messages if m is not None], out)

    def abort(self, messages: list[Written | None]) -> None:
        for m in messages:
            if m is not None and os.path.exists(f"{self.path}/{m.name}"):
                os.remove(f"{self.path}/{m.name}")


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FrameClock)
