"""A Python data source of planted documents: spark.read.format("planted").option("docs", n).load(), batch and stream."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition
from pyspark.sql.types import StructType


def _mix(x: int, salt: int) -> int:
    return ((x * 48271 + salt) % 2147483647) * 16807 % 2147483647


class _Rows:
    def __init__(self, options: dict) -> None:
        self.docs = int(options.get("docs", 1000))
        self.parts = int(options.get("parts", 4))
        self.communities = int(options.get("communities", 4))

    def rows(self, start: int, stop: int) -> Iterator[tuple]:
        for i in range(start, stop):
            yield i, _mix(i, 1) % 100, _mix(i, 2) // 64 % self.communities, f"w{_mix(i, 3) // 64 % 50:02d} w{_mix(i, 4) // 64 % 50:02d}"


class PlantedReader(DataSourceReader, _Rows):
    def __init__(self, options: dict) -> None:
        _Rows.__init__(self, options)

    def partitions(self) -> list[InputPartition]:
        step = -(-self.docs // self.parts)
        return [InputPartition((a, min(self.docs, a + step))) for a in range(0, self.docs, step)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        return self.rows(*partition.value)


class PlantedStream(DataSourceStreamReader, _Rows):
    def __init__(self, options: dict) -> None:
        _Rows.__init__(self, options)
        self.at = 0
        self.step = int(options.get("per_batch", 100))

    def initialOffset(self) -> dict:  # noqa: N802
        return {"at": 0}

    def latestOffset(self) -> dict:  # noqa: N802
        self.at = min(self.docs, self.at + self.step)
        return {"at": self.at}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        return [InputPartition((start["at"], end["at"]))]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        return self.rows(*partition.value)

    def commit(self, end: dict) -> None:
        pass


class PlantedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "doc_id bigint, user_id int, c int, text string"

    def reader(self, schema: StructType) -> DataSourceReader:
        return PlantedReader(self.options)

    def streamReader(self, schema: StructType) -> DataSourceStreamReader:  # noqa: N802
        return PlantedStream(self.options)
