"""Streams of edge changes: a rate for soak tests, and a table of events played again in order, as a data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader
from pyspark.sql.types import StructType

SCHEMA = "src long, dst long, op string, ts timestamp, seq long"


def rate_changes(spark: SparkSession, nodes: int, rows_per_second: int = 100, delete_every: int = 10) -> DataFrame:
    """Changes between random nodes at a rate; each `delete_every`-th takes the edge of its hash away."""
    ticks = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return changes_of_numbers(ticks, nodes, delete_every)


def changes_of_numbers(ticks: DataFrame, nodes: int, delete_every: int = 10) -> DataFrame:
    """The same for any table of timestamp and value, so a stream can be checked against a batch."""
    end = lambda salt: F.pmod(F.xxhash64("value", F.lit(salt)), F.lit(nodes))
    op = F.when(F.col("value") % delete_every == delete_every - 1, "delete").otherwise("insert")
    return ticks.select(end(1).alias("src"), end(2).alias("dst"), op.alias("op"), F.col("timestamp").alias("ts"), F.col("value").alias("seq")).where("src <> dst")


class ReplayReader(DataSourceReader):
    def __init__(self, rows: int, nodes: int, parts: int):
        self.rows, self.nodes, self.parts = rows, nodes, parts

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from replayed(range(partition.value, self.rows, self.parts), self.nodes)


class ReplayStream(SimpleDataSourceStreamReader):
    """`step` rows a micro-batch, up to `rows`."""

    def __init__(self, rows: int, nodes: int, step: int):
        self.rows, self.nodes, self.step = rows, nodes, step

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = min(self.rows, start["at"] + self.step)
        # a list's iterator can be copied, which a reader that keeps its rows does
        return iter(list(replayed(range(start["at"], end), self.nodes))), {"at": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(list(replayed(range(start["at"], end["at"]), self.nodes)))


def replayed(numbers: range, nodes: int) -> Iterator[tuple]:
    """Changes that follow from their number alone, so they can be read again after a restart."""
    import datetime

    begun = datetime.datetime(2024, 1, 1, tzinfo=datetime.UTC)
    for k in numbers:
        a, b = (k * 7919) % nodes, (k * 104729 + 1) % nodes
        if a != b:
            yield a, b, "delete" if k % 10 == 9 else "insert", begun + datetime.timedelta(seconds=k), k


class EdgeReplay(DataSource):
    """spark.dataSource.register(EdgeReplay); spark.read or readStream .format("edge_replay"). Options: rows, nodes, parts, step."""

    @classmethod
    def name(cls) -> str:
        return "edge_replay"

    def schema(self) -> str:
        return SCHEMA

    def _option(self, name: str, default: int) -> int:
        return int(self.options.get(name, default))

    def reader(self, schema: StructType) -> DataSourceReader:
        return ReplayReader(self._option("rows", 1000), self._option("nodes", 100), self._option("parts", 4))

    def simpleStreamReader(self, schema: StructType) -> SimpleDataSourceStreamReader:
        return ReplayStream(self._option("rows", 1000), self._option("nodes", 100), self._option("step", 250))
