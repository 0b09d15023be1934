"""``format("splitcount_pairs")``: seeded (id, j, r) pairs, j uniform over m and r geometric."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from splitcount.schema import MAX_RANK, registers_of


class _Slice(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class _Reader(DataSourceReader):
    def __init__(self, n: int, p: int, seed: int, slices: int):
        self.n, self.m, self.seed, self.slices = n, registers_of(p), seed, slices

    def partitions(self):
        cuts = [self.n * k // self.slices for k in range(self.slices + 1)]
        return [_Slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Slice):
        step = 1 << 16
        for at in range(partition.start, partition.stop, step):
            n = min(step, partition.stop - at)
            # The generator is keyed by the block's place, so a block read again is the same.
            rng = np.random.Generator(np.random.Philox(key=self.seed, counter=at))
            j = rng.integers(0, self.m, n)
            r = np.minimum(rng.geometric(0.5, n), MAX_RANK)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(at, at + n)), pa.array(j), pa.array(r)], ["id", "j", "r"])


class PairsSource(DataSource):
    """Options: n (rows), p (index bits), seed, slices (partitions)."""

    @classmethod
    def name(cls) -> str:
        return "splitcount_pairs"

    def schema(self) -> str:
        return "id long, j long, r long"

    def reader(self, schema):
        o = self.options
        return _Reader(int(o.get("n", 1000)), int(o.get("p", 10)), int(o.get("seed", 0)), int(o.get("slices", 4)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PairsSource)
