"""A Python data source: spark.read.format("zipf").option("n", ..).option("columns", ..).load()."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from rowloom.sources.synth import M1, M2, PRIME, S1, S2, zipf_steps

ROWS = 65_536


class ZipfSource(DataSource):
    """id and Zipfian columns, cut in partitions of ROWS rows; the same rows as `zipf_table`."""

    @classmethod
    def name(cls) -> str:
        return "zipf"

    def schema(self) -> str:
        return "id bigint, " + ", ".join(f"c{j + 1} int" for j in range(int(self.options.get("columns", 4))))

    def reader(self, schema) -> ZipfReader:  # noqa: ANN001
        return ZipfReader(int(self.options.get("n", 8192)), int(self.options.get("columns", 4)), int(self.options.get("seed", 42)))


class ZipfReader(DataSourceReader):
    def __init__(self, n: int, columns: int, seed: int):
        self.n, self.columns, self.seed = n, columns, seed

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((at, min(self.n, at + ROWS))) for at in range(0, self.n, ROWS)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        ids = np.arange(*partition.value, dtype="int64")
        steps = zipf_steps(self.n)
        arrays = [pa.array(ids)]
        for j in range(self.columns):
            salt = self.seed + j
            x = ((ids + 1) * M1 + salt * S1) % PRIME
            y = (x * x + salt * S2 + 1) % PRIME
            z = (y * M2 + x) % PRIME
            h = z * 2_147_483_648 + (z * z + y) % PRIME
            arrays.append(pa.array((np.searchsorted(steps, h % steps[-1], "right") + 1).astype("int32")))
        yield pa.RecordBatch.from_arrays(arrays, names=["id", *(f"c{j + 1}" for j in range(self.columns))])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ZipfSource)
