"""A Python data source of simulated sensors: carrier waves with optional faults, batch and stream."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


def reading(t: int, i: int, fault: tuple[int, int, int] | None) -> float:
    v = 0.5 + 0.35 * math.sin(2 * math.pi * (t - i // 5) / (12 + 4 * (i % 5)))
    return 1 - v if fault and fault[0] == i and fault[1] <= t <= fault[2] else v


class Span(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class SimulatedSensors(DataSource):
    """Options: ticks, sensors, partitions, and fault = sensor:first:last (sign flip)."""

    @classmethod
    def name(cls) -> str:
        return "simulated_sensors"

    def schema(self) -> str:
        return "tick bigint, sensor_id int, value double"

    def _set(self) -> tuple[int, int, tuple[int, int, int] | None]:
        f = self.options.get("fault")
        return int(self.options.get("ticks", 1000)), int(self.options.get("sensors", 10)), tuple(map(int, f.split(":"))) if f else None

    def reader(self, schema) -> DataSourceReader:
        ticks, sensors, fault = self._set()
        return Reader(ticks, sensors, fault, int(self.options.get("partitions", 4)))

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        ticks, sensors, fault = self._set()
        return Stream(sensors, fault, int(self.options.get("ticks_per_batch", 50)))


class Reader(DataSourceReader):
    def __init__(self, ticks: int, sensors: int, fault, parts: int):
        self.ticks, self.sensors, self.fault, self.parts = ticks, sensors, fault, parts

    def partitions(self):
        step = -(-self.ticks // self.parts)
        return [Span(a, min(self.ticks, a + step)) for a in range(0, self.ticks, step)]

    def read(self, partition: Span) -> Iterator[tuple]:
        for t in range(partition.lo, partition.hi):
            for i in range(self.sensors):
                yield t, i, reading(t, i, self.fault)


class Stream(SimpleDataSourceStreamReader):
    def __init__(self, sensors: int, fault, step: int):
        self.sensors, self.fault, self.step = sensors, fault, step

    def initialOffset(self) -> dict:
        return {"tick": 0}

    def read(self, start: dict):
        end = start["tick"] + self.step
        return self.readBetweenOffsets(start, {"tick": end}), {"tick": end}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter([(t, i, reading(t, i, self.fault)) for t in range(start["tick"], end["tick"]) for i in range(self.sensors)])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SimulatedSensors)
