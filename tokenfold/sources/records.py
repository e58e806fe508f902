"""A Python data source of prompts that repeat a record, for stress runs of any size without stored input."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

#: Rows of one Arrow batch.
BATCH = 4096


@dataclass
class Ids(InputPartition):
    low: int
    high: int


class RepeatedRecords(DataSource):
    """Rows (seq_id, text) for the ids from 0 to `rows`, in `parts` ranges; prompt i repeats its record 1 + i % 5 times."""

    @classmethod
    def name(cls) -> str:
        return "repeated_records"

    def schema(self) -> str:
        return "seq_id long, text string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("rows", 1000)), int(self.options.get("parts", 8)))


class _Reader(DataSourceReader):
    def __init__(self, rows: int, parts: int):
        if rows < 0 or parts < 1:
            raise ValueError("rows must not be negative, and parts at least 1")
        self.rows, self.parts = rows, parts

    def partitions(self) -> list[InputPartition]:
        return [Ids(self.rows * p // self.parts, self.rows * (p + 1) // self.parts) for p in range(self.parts)]

    def read(self, partition: Ids) -> Iterator[pa.RecordBatch]:
        for low in range(partition.low, partition.high, BATCH):
            ids = range(low, min(low + BATCH, partition.high))
            made = [" ".join([f"record {i} field {i % 7} ;"] * (1 + i % 5)) for i in ids]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(made, pa.string())], names=["seq_id", "text"])
