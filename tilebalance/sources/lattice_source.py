"""A Python data source that generates a lattice in blocks of rows, one block a task."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class LatticeSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tile_lattice"

    def schema(self) -> str:
        return "tile_id bigint, tx int, ty int"

    def reader(self, schema) -> DataSourceReader:
        return LatticeReader(int(self.options["nx"]), int(self.options["ny"]), int(self.options.get("rows", 64)))


class LatticeReader(DataSourceReader):
    def __init__(self, nx: int, ny: int, rows: int):
        self.nx, self.ny, self.rows = nx, ny, rows

    def partitions(self):
        return [InputPartition((a, min(self.ny, a + self.rows))) for a in range(0, self.ny, self.rows)]

    def read(self, partition):
        for y in range(*partition.value):
            for x in range(self.nx):
                yield x + y * self.nx, x, y
