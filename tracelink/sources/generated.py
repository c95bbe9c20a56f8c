"""A Python data source of generated events, for scale tests without files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
#: First second of the events, and their span.
BEGIN, SPAN = 1704067200, 2592000
BATCH = 50_000


def made(i: np.ndarray, objects: int) -> pa.RecordBatch:
    """The events with these numbers."""
    k = i * 31 % 100
    columns = [
        pa.array(i), pa.array((BEGIN + i * 7907 % SPAN) * 1_000_000).cast(pa.timestamp("us")), pa.array(i % objects), pa.array(["view"] * len(i)),
        pa.array((i * 37 % 1000) / 10.0), pa.array([f'{{"k": {x}}}' for x in k.tolist()]),
    ]
    return pa.RecordBatch.from_arrays(columns, names=["event_id", "ts", "user_id", "event_type", "value", "props"])


def from_events(events: DataFrame, objects: int) -> DataFrame:
    """Generated events of the numbers that a table's events have, in its tasks."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield made(b.column(0).to_numpy(zero_copy_only=False).astype(np.int64), objects)

    return events.where("event_id is not null").select("event_id").mapInArrow(each, SCHEMA)


class Part(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class GeneratedReader(DataSourceReader):
    def __init__(self, objects: int, points: int, parts: int):
        self.objects, self.rows, self.parts = objects, objects * points, parts

    def partitions(self) -> list[Part]:
        edges = [self.rows * i // self.parts for i in range(self.parts + 1)]
        return [Part(a, b) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition: Part) -> Iterator[pa.RecordBatch]:
        for a in range(partition.start, partition.stop, BATCH):
            yield made(np.arange(a, min(a + BATCH, partition.stop), dtype=np.int64), self.objects)


class GeneratedEvents(DataSource):
    """``spark.read.format("tracegen").option("objects", n).option("points", p).load()``: n objects of p points each, in ``parts`` partitions."""

    @classmethod
    def name(cls) -> str:
        return "tracegen"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> GeneratedReader:
        o = self.options
        return GeneratedReader(int(o.get("objects", 100)), int(o.get("points", 66)), int(o.get("parts", 8)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(GeneratedEvents)
