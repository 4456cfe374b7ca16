"""A Python data source: the grid of settings that an audit is repeated over."""

from __future__ import annotations

import json
from collections.abc import Iterator
from itertools import product

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class AuditGrid(DataSource):
    """``spark.read.format("audit_grid").option("exposure", "[1, 4]").option("layer", "[0, 1]").load()``: one row a combination.

    Options are JSON lists; those not given have one value, the default. A combination is a partition of its own.
    """

    DEFAULTS = {"exposure": 1, "layer": 1, "min_df": 3}

    @classmethod
    def name(cls) -> str:
        return "audit_grid"

    def schema(self) -> str:
        return "name string, exposure int, layer int, min_df int"

    def reader(self, schema) -> DataSourceReader:
        return _GridReader({k: json.loads(self.options.get(k, f"[{v}]")) for k, v in self.DEFAULTS.items()})


class _GridReader(DataSourceReader):
    def __init__(self, axes: dict[str, list[int]]):
        self.axes = axes

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(values) for values in product(*self.axes.values())]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        yield ("/".join(f"{k}={v}" for k, v in zip(self.axes, partition.value, strict=True)), *partition.value)
