"""Update source ``gnn_updates``: replays JSON lines of updates in several partitions, batch or stream."""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

SCHEMA = "seq BIGINT, kind STRING, src BIGINT, dst BIGINT, w DOUBLE"


class Slice(InputPartition):
    def __init__(self, rows: list[str]):
        self.rows = rows


def parsed(lines: list[str]):
    for line in lines:
        r = json.loads(line)
        yield r["seq"], r["kind"], r["src"], r.get("dst"), r.get("w")


class UpdateReader(DataSourceReader):
    def __init__(self, lines: list[str], parts: int):
        self.lines, self.parts = lines, parts

    def partitions(self):
        return [Slice(self.lines[i :: self.parts]) for i in range(self.parts)]

    def read(self, partition):
        yield from parsed(partition.rows)


class UpdateStreamReader(DataSourceStreamReader):
    """Offsets count lines; ``batch`` lines per micro-batch."""

    def __init__(self, lines: list[str], batch: int):
        self.lines, self.batch, self.at = lines, batch, 0

    def initialOffset(self):
        return {"at": 0}

    def latestOffset(self):
        self.at = min(len(self.lines), self.at + self.batch)
        return {"at": self.at}

    def partitions(self, start, end):
        return [Slice(self.lines[start["at"] : end["at"]])]

    def read(self, partition):
        yield from parsed(partition.rows)


class UpdateSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "gnn_updates"

    def schema(self) -> str:
        return SCHEMA

    def _lines(self) -> list[str]:
        return [x for x in self.options.get("lines", "").split("\n") if x]

    def reader(self, schema):
        return UpdateReader(self._lines(), int(self.options.get("parts", "1")))

    def streamReader(self, schema):
        return UpdateStreamReader(self._lines(), int(self.options.get("batch", "100")))
