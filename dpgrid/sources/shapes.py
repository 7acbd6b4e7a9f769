"""Python data source of synthetic shapes, for tests: ``spark.read.format("dpgrid_shapes").option("shape", "ring")``."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ShapeSource(DataSource):
    """Options: ``shape`` (ring, disc, line, two), ``rows``, ``parts``. Points are placed by rule, not drawn."""

    @classmethod
    def name(cls) -> str:
        return "dpgrid_shapes"

    def schema(self) -> str:
        return "point_id bigint, x0 double, x1 double, truth int"

    def reader(self, schema) -> DataSourceReader:
        return ShapeReader(dict(self.options))


class ShapeReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.shape, self.rows, self.parts = options.get("shape", "ring"), int(options.get("rows", 1000)), int(options.get("parts", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for i in range(partition.value, self.rows, self.parts):
            t, j = (i + 0.5) / self.rows, i * 0.6180339887498949 % 1.0
            if self.shape == "ring":
                r, a, c, k = 0.3 + 0.06 * (j - 0.5), 2 * math.pi * t, (0.5, 0.5), 0
            elif self.shape == "disc":
                r, a, c, k = 0.3 * math.sqrt(j), 2 * math.pi * t, (0.5, 0.5), 0
            elif self.shape == "two":
                k = i % 2
                r, a, c = 0.12 * math.sqrt(j), 2 * math.pi * t, (0.25 + 0.5 * k, 0.5)
            elif self.shape == "line":
                yield i, 0.1 + 0.8 * t, 0.5 + 0.02 * (j - 0.5), 0
                continue
            else:
                raise ValueError(f"shape {self.shape!r}")
            yield i, c[0] + r * math.cos(a), c[1] + r * math.sin(a), k
