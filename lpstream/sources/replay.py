"""A replayable update log as a custom data source, batch and stream, in Python."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def update(i: int, rows: int, cols: int, seed: int) -> tuple[int, int, float]:
    """The i-th update: a pure function of its number, so any part can be replayed."""
    x = (i * 6364136223846793005 + seed * 1442695040888963407 + 1) & ((1 << 64) - 1)
    x ^= x >> 33
    x = (x * 0xFF51AFD7ED558CCD) & ((1 << 64) - 1)
    x ^= x >> 29
    return x % rows, (x >> 20) % cols, float((x >> 32) % 2001 - 1000) / 10


class Span(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class ReplaySource(DataSource):
    """format('replay_updates'): options count, rows, cols, seed, partitions, batch."""

    @classmethod
    def name(cls) -> str:
        return "replay_updates"

    def schema(self) -> str:
        return "row_id bigint, col_id int, delta double"

    def _options(self) -> dict:
        return {k: int(self.options.get(k, v)) for k, v in {"count": 1000, "rows": 100, "cols": 7, "seed": 1, "partitions": 4, "batch": 250}.items()}

    def reader(self, schema):
        return BatchReader(self._options())

    def simpleStreamReader(self, schema):
        return StreamReader(self._options())


class BatchReader(DataSourceReader):
    def __init__(self, options: dict):
        self.o = options

    def partitions(self):
        n, p = self.o["count"], self.o["partitions"]
        return [Span(n * k // p, n * (k + 1) // p) for k in range(p)]

    def read(self, partition: Span):
        for i in range(partition.start, partition.stop):
            yield update(i, self.o["rows"], self.o["cols"], self.o["seed"])


class StreamReader(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.o = options

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict):
        stop = min(start["at"] + self.o["batch"], self.o["count"])
        return self._rows(start["at"], stop), {"at": stop}

    def readBetweenOffsets(self, start: dict, end: dict):
        return self._rows(start["at"], end["at"])

    def _rows(self, a: int, b: int):
        return iter([update(i, self.o["rows"], self.o["cols"], self.o["seed"]) for i in range(a, b)])


class NumberSource(DataSource):
    """format('replay_numbers'): the numbers (number) from start to stop in `partitions` spans, to replay a table by."""

    @classmethod
    def name(cls) -> str:
        return "replay_numbers"

    def schema(self) -> str:
        return "number bigint"

    def reader(self, schema):
        return NumberReader(*(int(self.options.get(k, v)) for k, v in (("start", 0), ("stop", 0), ("partitions", 4))))


class NumberReader(DataSourceReader):
    def __init__(self, start: int, stop: int, parts: int):
        self.start, self.stop, self.parts = start, stop, parts

    def partitions(self):
        n = max(0, self.stop - self.start)
        return [Span(self.start + n * k // self.parts, self.start + n * (k + 1) // self.parts) for k in range(self.parts)]

    def read(self, partition: Span):
        import numpy as np
        import pyarrow as pa

        for a in range(partition.start, partition.stop, 65536):
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(a, min(a + 65536, partition.stop)))], names=["number"])
