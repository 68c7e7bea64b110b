"""A Python data source of simulated votes, for batch and stream reads: ``spark.read.format("crowd_votes")``.

Options: records (records 0..n-1), groups (entity is id modulo groups), voters, err, seed, partitions;
a stream gives ``perBatch`` pairs at a time.
"""

from __future__ import annotations

import hashlib

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from crowdlink.schemas import VOTES


def _h(*parts) -> float:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16) / 4294967296.0


def _pair(index: int) -> tuple[int, int]:
    """The index-th pair in the order of the greater id."""
    w = int((1 + (1 + 8 * index) ** 0.5) / 2)
    while w * (w - 1) // 2 > index:
        w -= 1
    while (w + 1) * w // 2 <= index:
        w += 1
    return index - w * (w - 1) // 2, w


class _Options:
    def __init__(self, o: dict):
        self.n, self.groups, self.voters = int(o.get("records", 20)), int(o.get("groups", 5)), int(o.get("voters", 5))
        self.err, self.seed = float(o.get("err", 0.1)), int(o.get("seed", 42))
        self.parts, self.per = int(o.get("partitions", 4)), int(o.get("perBatch", 50))
        self.pairs = self.n * (self.n - 1) // 2

    def votes(self, start: int, end: int):
        for index in range(start, min(end, self.pairs)):
            u, w = _pair(index)
            for v in range(self.voters):
                yield u, w, v, ((u % self.groups == w % self.groups) != (_h(self.seed, u, w, v) < self.err))


class _Slice(InputPartition):
    def __init__(self, start: int, end: int):
        super().__init__((start, end))
        self.start, self.end = start, end


class _Reader(DataSourceReader):
    def __init__(self, o: _Options):
        self.o = o

    def partitions(self):
        step = -(-self.o.pairs // self.o.parts) or 1
        return [_Slice(a, a + step) for a in range(0, max(self.o.pairs, 1), step)]

    def read(self, partition):
        yield from self.o.votes(partition.start, partition.end)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, o: _Options):
        self.o = o

    def initialOffset(self):  # noqa: N802
        return {"pair": 0}

    def read(self, start):
        end = min(start["pair"] + self.o.per, self.o.pairs)
        return iter(list(self.o.votes(start["pair"], end))), {"pair": end}

    def readBetweenOffsets(self, start, end):  # noqa: N802
        return self.o.votes(start["pair"], end["pair"])

    def commit(self, end):
        pass


class CrowdVotes(DataSource):
    @classmethod
    def name(cls) -> str:
        return "crowd_votes"

    def schema(self) -> str:
        return VOTES

    def reader(self, schema) -> DataSourceReader:
        return _Reader(_Options(self.options))

    def simpleStreamReader(self, schema):  # noqa: N802
        return _Stream(_Options(self.options))
