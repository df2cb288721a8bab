"""A data source for raw audit-log lines: ``time|actor|operation|object|microseconds``, batch and stream.

Register with ``spark.dataSource.register(AuditLogSource)`` and read with ``spark.read.format("audit_log").load(folder)``. A line that
does not parse is a row with the operation 'malformed' and itself as the object, so that it can be counted; traces have no edge for it.
"""

from __future__ import annotations

import os
from collections.abc import Iterator
from datetime import datetime

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

SCHEMA = "run_id long, seq long, ts timestamp_ntz, actor string, op string, object string, dur_us long"


class FilePart(InputPartition):
    def __init__(self, path: str, number: int):
        self.path, self.number = path, number


def parse(line: str, run: int, seq: int) -> tuple:
    line = line.rstrip("\n")
    parts = line.split("|")
    try:
        if len(parts) == 5:
            return (run, seq, datetime.fromisoformat(parts[0]), parts[1], parts[2], parts[3], int(parts[4] or 0))
    except ValueError:
        pass
    return (run, seq, None, None, "malformed", line, 0)


def _files(path: str) -> list[str]:
    path = path.removeprefix("file://")
    return sorted(os.path.join(path, f) for f in os.listdir(path) if f.endswith(".log")) if os.path.isdir(path) else [path]


class AuditLogReader(DataSourceReader):
    """One partition a file. The folder must be one that all executors see."""

    def __init__(self, options: dict):
        self.path, self.run = options["path"], int(options.get("run", 0))

    def partitions(self) -> list[InputPartition]:
        return [FilePart(p, i) for i, p in enumerate(_files(self.path))]

    def read(self, partition: FilePart) -> Iterator[tuple]:
        with open(partition.path, encoding="utf-8", errors="replace") as f:
            for k, line in enumerate(f):
                yield parse(line, self.run, partition.number << 32 | k)


class AuditLogStream(DataSourceStreamReader):
    """Files that are new by name, one partition each; the offset is the names seen, so a late file of an earlier name is read once."""

    def __init__(self, options: dict):
        self.reader = AuditLogReader(options)

    def initialOffset(self) -> dict:
        return {"files": []}

    def latestOffset(self) -> dict:
        return {"files": _files(self.reader.path)}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        seen = set(start["files"])
        return [FilePart(p, i) for i, p in enumerate(end["files"]) if p not in seen]

    def read(self, partition: FilePart) -> Iterator[tuple]:
        return self.reader.read(partition)

    def commit(self, end: dict) -> None:
        pass


class AuditLogSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "audit_log"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return AuditLogReader(self.options)

    def streamReader(self, schema) -> DataSourceStreamReader:
        return AuditLogStream(self.options)
