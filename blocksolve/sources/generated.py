"""A Python data source of scan rays: partitions are ranges of views, and filters on the view cut them before any ray is made."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition


class FanRays(DataSource):
    @classmethod
    def name(cls) -> str:
        return "fan_rays"

    def schema(self) -> str:
        return "row_id bigint, view int, det int, sx double, sy double, dx double, dy double"

    def reader(self, schema) -> FanReader:
        return FanReader(self.options)


class FanReader(DataSourceReader):
    def __init__(self, options) -> None:
        self.n, self.dets = int(options.get("views", 360)), int(options.get("dets", 187))
        self.radius, self.pitch, self.phase = float(options.get("radius", 115)), float(options.get("pitch", 1)), float(options.get("phase", 1e-3))
        self.views = list(range(self.n))

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("view",):
                self.views = [v for v in self.views if v == f.value]
            elif isinstance(f, In) and f.attribute == ("view",):
                self.views = [v for v in self.views if v in f.value]
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(self.views[i : i + 16]) for i in range(0, len(self.views), 16)] or [InputPartition([])]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for v in partition.value:
            phi = 2 * math.pi * v / self.n + self.phase
            c, s = math.cos(phi), math.sin(phi)
            for k in range(self.dets):
                u = (k - (self.dets - 1) / 2) * self.pitch
                yield v * self.dets + k, v, k, self.radius * c, self.radius * s, -self.radius * c - u * s, -self.radius * s + u * c
