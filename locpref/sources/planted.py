"""A data source of planted preference matrices, as a table and as a stream.

``spark.dataSource.register(PlantedSource)`` makes the format ``planted_preferences``
known; options are ``users``, ``items``, ``rank``, ``density``, ``seed`` and, for the
stream, ``users_per_batch``. A cell's values depend on its key alone.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "user_id long, item_id long, rating double, truth int"


class Users(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


def rows(first: int, last: int, options: dict) -> Iterator[tuple]:
    """Cells of users first to last (exclusive)."""
    import numpy as np

    items, rank = int(options.get("items", 20)), int(options.get("rank", 3))
    density, seed, flip = float(options.get("density", 0.5)), int(options.get("seed", 42)), float(options.get("flip", 0.05))
    z = np.random.default_rng([seed, 1]).normal(size=(items, rank))
    for user in range(first, last):
        rng = np.random.default_rng([seed, 2, user])
        truth = (z @ rng.normal(size=rank) + 0.3 > 0).astype(int)
        seen, wrong = rng.random(items) < density, rng.random(items) < flip
        for item in np.flatnonzero(seen).tolist():
            t = int(truth[item])
            yield user, item, float(1 - t if wrong[item] else t), t


class PlantedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def partitions(self) -> list[Users]:
        n, each = int(self.options.get("users", 100)), int(self.options.get("users_per_task", 10_000))
        return [Users(k, min(n, k + each)) for k in range(0, n, each)]

    def read(self, partition: Users) -> Iterator[tuple]:
        return rows(partition.first, partition.last, self.options)


class PlantedStream(SimpleDataSourceStreamReader):
    def __init__(self, options: dict):
        self.options = options

    def initialOffset(self) -> dict:
        return {"user": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(int(self.options.get("users", 100)), start["user"] + int(self.options.get("users_per_batch", 10)))
        return iter(list(rows(start["user"], end, self.options))), {"user": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(list(rows(start["user"], end["user"], self.options)))

    def commit(self, end: dict) -> None:
        pass


class PlantedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted_preferences"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> PlantedReader:
        return PlantedReader(dict(self.options))

    def simpleStreamReader(self, schema) -> PlantedStream:
        return PlantedStream(dict(self.options))
