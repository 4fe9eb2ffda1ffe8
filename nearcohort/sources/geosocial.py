"""A Python data source ``geosocial``: edge lists and check-in logs, batch and stream.

Options: path (a text file or folder that each reader can open), kind ('edges' or 'checkins').
"""

from __future__ import annotations

import glob
import os
from datetime import datetime

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

_SCHEMAS = {"edges": "src bigint, dst bigint", "checkins": "user bigint, ts timestamp, y double, x double, place string"}


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _rows(path: str, kind: str):
    with open(path, encoding="utf-8") as f:
        for line in f:
            p = line.rstrip("\n").split("\t")
            try:
                if kind == "edges":
                    yield int(p[0]), int(p[1])
                else:
                    yield int(p[0]), datetime.fromisoformat(p[1].replace("Z", "+00:00")), float(p[2]), float(p[3]), p[4] if len(p) > 4 else None
            except (ValueError, IndexError):
                continue


def _files(path: str) -> list[str]:
    return sorted(glob.glob(os.path.join(path, "*.txt"))) if os.path.isdir(path) else [path]


class _Reader(DataSourceReader):
    def __init__(self, path: str, kind: str):
        self.path, self.kind = path, kind

    def partitions(self):
        return [_File(f) for f in _files(self.path)]

    def read(self, partition):
        yield from _rows(partition.path, self.kind)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, path: str, kind: str):
        self.path, self.kind = path, kind

    def initialOffset(self):
        return {"file": 0}

    def read(self, start):
        files = _files(self.path)[start["file"]:]
        rows = [r for f in files for r in _rows(f, self.kind)]
        return iter(rows), {"file": start["file"] + len(files)}

    def readBetweenOffsets(self, start, end):
        files = _files(self.path)[start["file"]:end["file"]]
        return iter([r for f in files for r in _rows(f, self.kind)])


class GeoSocialSource(DataSource):
    @classmethod
    def name(cls):
        return "geosocial"

    def schema(self):
        return _SCHEMAS[self.options.get("kind", "edges")]

    def reader(self, schema):
        return _Reader(self.options["path"], self.options.get("kind", "edges"))

    def simpleStreamReader(self, schema):
        return _Stream(self.options["path"], self.options.get("kind", "edges"))
