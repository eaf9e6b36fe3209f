"""A data source of portable scenarios: spark.read.format("scenario_loads").option("ids", 6).load()."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.scenarios import portable_rows

SCHEMA = "scenario_id bigint, step int, slice_id int, work bigint"


class ScenarioSource(DataSource):
    """Options ids, steps and m; one partition for each scenario."""

    @classmethod
    def name(cls) -> str:
        return "scenario_loads"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return ScenarioReader(*(int(self.options.get(k, d)) for k, d in (("ids", "6"), ("steps", "100"), ("m", "64"))))


class ScenarioReader(DataSourceReader):
    def __init__(self, ids: int, steps: int, m: int) -> None:
        self.ids, self.steps, self.m = ids, steps, m

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.ids)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield from portable_rows(partition.value, self.steps, self.m)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ScenarioSource)
