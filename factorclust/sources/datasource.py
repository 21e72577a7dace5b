"""A Python data source: ``spark.read.format("planted_mixture")`` with options n, d, k, gamma, seed, partitions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Stretch(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class PlantedMixtureReader(DataSourceReader):
    def __init__(self, options: dict):
        get = lambda k, default: options.get(k, default)
        self.n, self.d, self.k = int(get("n", "1000")), int(get("d", "8")), int(get("k", "4"))
        self.gamma, self.seed, self.parts = float(get("gamma", "1.0")), int(get("seed", "0")), int(get("partitions", "4"))

    def partitions(self) -> list[Stretch]:
        step = -(-self.n // self.parts)
        return [Stretch(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)]

    def read(self, partition: Stretch) -> Iterator:
        import numpy as np
        import pyarrow as pa

        from factorclust.sources.points import mixture_rows

        for at in range(partition.lo, partition.hi, 8192):
            ids = np.arange(at, min(partition.hi, at + 8192))
            x, truth = mixture_rows(ids, self.n, self.d, self.k, self.gamma, self.seed)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1) * self.d, pa.int32()), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(ids), lists, pa.array(truth.astype(np.int32))], names=["id", "x", "truth"])


class PlantedMixtureSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted_mixture"

    def schema(self) -> str:
        return "id bigint, x array<double>, truth int"

    def reader(self, schema) -> PlantedMixtureReader:
        return PlantedMixtureReader(self.options)
