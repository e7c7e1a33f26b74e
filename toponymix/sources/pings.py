"""A Python data source of made-up pings: repeatable load for tests of scale, split over any number of tasks."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "user_id bigint, city int, lat_u bigint, lon_u bigint"


class PingSource(DataSource):
    """format("pings") with options users, pings (of each user), partitions. A user's pings gather around a home."""

    @classmethod
    def name(cls) -> str:
        return "pings"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("users", 100)), int(self.options.get("pings", 10)), int(self.options.get("partitions", 4)))


class _Reader(DataSourceReader):
    def __init__(self, users: int, pings: int, parts: int):
        self.users, self.pings, self.parts = users, pings, parts

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for user in range(partition.value, self.users, self.parts):
            for k in range(self.pings):
                yield user, 0, 30_000_000 + user * 7919 % 300_000 + k * 31 % 100, 120_000_000 + user * 10457 % 300_000 + k * 17 % 100
