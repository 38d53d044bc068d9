"""The kernel matrix of a list of points as a data source with one input partition for each block of rows."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from rankgrid.sources.matrices import DIAGONAL, kernel_value


class KernelSource(DataSource):
    """Options: points (JSON list of [x, y, z]), kind, rows (per partition)."""

    @classmethod
    def name(cls) -> str:
        return "kernel_matrix"

    def schema(self) -> str:
        return "i long, j long, v double"

    def reader(self, schema) -> DataSourceReader:
        return KernelReader(np.array(json.loads(self.options["points"]), dtype=np.float64).reshape(-1, 3), self.options.get("kind", "decay"), int(self.options.get("rows", 32)))


class KernelReader(DataSourceReader):
    def __init__(self, points: np.ndarray, kind: str, rows: int):
        self.points, self.kind, self.rows = points, kind, rows

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(s) for s in range(0, len(self.points), self.rows)]

    def read(self, partition: InputPartition):
        s = partition.value
        for i in range(s, min(s + self.rows, len(self.points))):
            d2 = ((self.points[i] - self.points) ** 2).sum(-1)
            row = kernel_value(self.kind, d2)
            row[i] += DIAGONAL
            for j, v in enumerate(row.tolist()):
                yield (i, j, v)
