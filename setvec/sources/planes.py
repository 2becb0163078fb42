"""A data source of parameter tables: planes and signs are made from the seed when they are read, and never stored."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from setvec.functions import seeds


class _Rep(InputPartition):
    def __init__(self, rep: int):
        super().__init__(rep)
        self.rep = rep


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.table = options.get("table", "planes")
        self.seed, self.reps = int(options.get("seed", 42)), int(options.get("reps", 1))
        self.rows, self.dim = int(options.get("rows", 1)), int(options.get("dim", 64))
        if self.table not in ("planes", "inner"):
            raise ValueError("table is planes or inner")

    def partitions(self) -> list[InputPartition]:
        return [_Rep(r) for r in range(self.reps)]

    def read(self, partition: _Rep) -> Iterator[tuple]:
        of = (lambda *at: seeds.int12("plane", self.seed, *at)) if self.table == "planes" else (lambda *at: seeds.sign("inner", self.seed, *at))
        for i in range(self.rows):
            for d in range(self.dim):
                yield partition.rep, i, d, of(partition.rep, i, d)


class PlaneSource(DataSource):
    """``spark.read.format("setvec_planes")`` with options table, seed, reps, rows (bits or projected numbers) and dim."""

    @classmethod
    def name(cls) -> str:
        return "setvec_planes"

    def schema(self) -> str:
        return "rep int, i int, dim int, g bigint"

    def reader(self, schema: object) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlaneSource)
