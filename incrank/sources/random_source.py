"""A data source of random pairs, for batch and streaming reads: the same md5 draws as :mod:`incrank.sources.batches`."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def draw(seed: str, tag: str, i: int) -> int:
    return int(hashlib.md5(f"{seed}:{tag}:{i}".encode()).hexdigest()[:8], 16)


class Slice(InputPartition):
    def __init__(self, start: int, end: int) -> None:
        self.start, self.end = start, end


class RandomBatchSource(DataSource):
    """Options: pairs, vertices, seed, slices; places are from 1 to vertices. Streams add ``pairs`` pairs each micro-batch."""

    @classmethod
    def name(cls) -> str:
        return "random_pairs"

    def schema(self) -> str:
        return "id bigint, ps bigint, pd bigint"

    def _option(self, name: str, default: int) -> int:
        return int(self.options.get(name, default))

    def rows(self, start: int, end: int) -> Iterator[tuple[int, int, int]]:
        seed, n = self.options.get("seed", "42"), self._option("vertices", 1)
        for i in range(start, end):
            yield i, draw(seed, "s", i) % n + 1, draw(seed, "d", i) % n + 1

    def reader(self, schema) -> DataSourceReader:
        return RandomReader(self)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return RandomStream(self)


class RandomReader(DataSourceReader):
    def __init__(self, source: RandomBatchSource) -> None:
        self.source = source

    def partitions(self) -> list[Slice]:
        pairs, slices = self.source._option("pairs", 0), self.source._option("slices", 4)
        cuts = [pairs * k // slices for k in range(slices + 1)]
        return [Slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, part: Slice) -> Iterator[tuple[int, int, int]]:
        return self.source.rows(part.start, part.end)


class RandomStream(SimpleDataSourceStreamReader):
    def __init__(self, source: RandomBatchSource) -> None:
        self.source = source

    def initialOffset(self) -> dict:
        return {"next": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple[int, int, int]], dict]:
        end = start["next"] + self.source._option("pairs", 0)
        return self.source.rows(start["next"], end), {"next": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple[int, int, int]]:
        return self.source.rows(start["next"], end["next"])
