"""A Python data source that generates skew design rows, ``spark.read.format("tallquant_skew")``.

Options: rows, d, q, seed, partitions.  A row depends on its number and the seed
alone, so partitions can be read again after a failure.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class SkewSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tallquant_skew"

    def schema(self) -> str:
        return "row_id string, j int, b double"

    def reader(self, schema) -> DataSourceReader:
        return SkewReader(self.options)


class SkewReader(DataSourceReader):
    def __init__(self, options):
        self.rows, self.d, self.q = int(options.get("rows", "1000")), int(options.get("d", "5")), float(options.get("q", "2.0"))
        self.seed, self.n = int(options.get("seed", "3")), int(options.get("partitions", "4"))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.rows // self.n)
        return [InputPartition((a, min(self.rows, a + step))) for a in range(0, self.rows, step)]

    def _unit(self, stream: str, key: str) -> float:
        return (int(hashlib.md5(f"{self.seed}|{stream}|{key}".encode()).hexdigest()[:13], 16) + 0.5) / float(1 << 52)

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from tallquant.sources.design import skew_noise_scale, skew_truth

        truth = skew_truth(self.d, self.seed)
        scale = skew_noise_scale(self.d, self.q, truth)
        for i in range(*partition.value):
            k = str(i)
            j = min(self.d - 1, int(math.log(1 + self._unit("column", k) * (self.q**self.d - 1)) / math.log(self.q)))
            v = self._unit("noise", k) - 0.5
            e = -scale * math.copysign(1, v) * math.log(1 - 2 * abs(v))
            yield k, j, 500 * e if self._unit("outlier", k) < 0.001 else truth[j] + e


def register(spark) -> None:
    spark.dataSource.register(SkewSource)
