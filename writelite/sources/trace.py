"""A generated instruction trace (seq, op, addr) as a Python data source, for batches and streams."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "seq long, op string, addr long"


def record(seq: int, addresses: int, write_share: int) -> tuple[int, str, int]:
    """The access of a place in the trace: a multiplicative hash of it, so that any part can be made alone."""
    h = (seq + 1) * 0x9E3779B97F4A7C15 % 2**64 >> 20
    return seq, "W" if h % 100 < write_share else "R", (h // 100) % addresses


class TraceSource(DataSource):
    """Options: rows, addresses, writes (a share in percent), partitions."""

    @classmethod
    def name(cls) -> str:
        return "memory_trace"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)


def _settings(options) -> tuple[int, int, int, int]:
    return tuple(int(options.get(k, v)) for k, v in (("rows", 1000), ("addresses", 64), ("writes", 30), ("partitions", 4)))


class _Part(InputPartition):
    def __init__(self, start: int, end: int) -> None:
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, options) -> None:
        self.set = _settings(options)

    def partitions(self) -> list[_Part]:
        rows, _, _, n = self.set
        return [_Part(rows * i // n, rows * (i + 1) // n) for i in range(n)]

    def read(self, part: _Part) -> Iterator[tuple]:
        _, addresses, writes, _ = self.set
        yield from (record(i, addresses, writes) for i in range(part.start, part.end))


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options) -> None:
        self.set = _settings(options)

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        rows, addresses, writes, _ = self.set
        end = min(start["at"] + 500, rows)
        return iter([record(i, addresses, writes) for i in range(start["at"], end)]), {"at": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        _, addresses, writes, _ = self.set
        return iter([record(i, addresses, writes) for i in range(start["at"], end["at"])])
