"""``spark.read.format("voxelgrid")``: all voxels of a grid, in as many partitions as asked for.

Options: ``gx``, ``gy``, ``gt`` and ``partitions`` (8). Rows are ``(vx, vy, vt)``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Slab(InputPartition):
    def __init__(self, low: int, high: int):
        super().__init__((low, high))
        self.low, self.high = low, high


class VoxelReader(DataSourceReader):
    def __init__(self, gx: int, gy: int, gt: int, parts: int):
        self.gx, self.gy, self.gt, self.parts = gx, gy, gt, parts

    def partitions(self):
        edges = [self.gx * i // self.parts for i in range(self.parts + 1)]
        return [Slab(a, b) for a, b in zip(edges, edges[1:]) if a < b]

    def read(self, partition):
        for vx in range(partition.low, partition.high):
            vy, vt = np.divmod(np.arange(self.gy * self.gt, dtype=np.int32), np.int32(self.gt))
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(vy), vx, np.int32)), pa.array(vy), pa.array(vt)], names=["vx", "vy", "vt"])


class VoxelGrid(DataSource):
    @classmethod
    def name(cls):
        return "voxelgrid"

    def schema(self):
        return "vx int, vy int, vt int"

    def reader(self, schema):
        gx, gy, gt = (int(self.options[k]) for k in ("gx", "gy", "gt"))
        return VoxelReader(gx, gy, gt, int(self.options.get("partitions", "8")))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(VoxelGrid)
