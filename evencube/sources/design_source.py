"""``spark.read.format("cube_design")``: strata as a data source whose box filters skip whole subtrees.

Options: count, dims, avoid_odd (true), mode (fixed), seed (0), parts (8).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual

from ..operators.strata import _frontier_nodes, expand_np


class Subtree(InputPartition):
    def __init__(self, off: int, cnt: int, lo: list[float], hi: list[float]) -> None:
        self.off, self.cnt, self.lo, self.hi = off, cnt, lo, hi


class CubeDesign(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cube_design"

    def schema(self) -> str:
        n = int(self.options.get("dims", "2"))
        return "stratum_id long, " + ", ".join(f"lo{d} double, hi{d} double" for d in range(1, n + 1))

    def reader(self, schema) -> "CubeDesignReader":
        return CubeDesignReader(dict(self.options))


class CubeDesignReader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.count, self.n = int(options.get("count", "1")), int(options.get("dims", "2"))
        self.avoid_odd, self.mode = options.get("avoid_odd", "true") == "true", options.get("mode", "fixed")
        self.seed, self.parts = int(options.get("seed", "0")), int(options.get("parts", "8"))
        self.low, self.high = [0.0] * self.n, [1.0] * self.n

    def pushFilters(self, filters: list) -> Iterator:
        """Bounds on lo/hi columns prune subtrees; every filter is still applied to the rows by Spark."""
        for f in filters:
            name = f.attribute[0] if len(getattr(f, "attribute", ())) == 1 else ""
            if name[2:].isdigit() and name[:2] in ("lo", "hi"):
                d = int(name[2:]) - 1
                if isinstance(f, (GreaterThan, GreaterThanOrEqual)):
                    self.low[d] = max(self.low[d], float(f.value))  # hi > lo >= v
                elif isinstance(f, (LessThan, LessThanOrEqual)):
                    self.high[d] = min(self.high[d], float(f.value))  # lo < hi <= v
            yield f

    def partitions(self) -> list[Subtree]:
        nodes = _frontier_nodes(self.count, [0.0] * self.n, [1.0] * self.n, self.parts, self.avoid_odd, self.mode, self.seed)
        near = [n for n in nodes if all(h >= a and low <= b for low, h, a, b in zip(n[2], n[3], self.low, self.high))]
        return [Subtree(*n) for n in near] or [Subtree(0, 0, [], [])]

    def read(self, part: Subtree) -> Iterator[pa.RecordBatch]:
        if not part.cnt:
            return
        ids, lo, hi = expand_np(np.array([part.cnt]), np.array([part.off]), np.array([part.lo]), np.array([part.hi]), self.avoid_odd, self.mode, self.seed)
        sides = [pa.array(np.ascontiguousarray(s[:, d])) for d in range(self.n) for s in (lo, hi)]
        yield pa.RecordBatch.from_arrays([pa.array(ids), *sides], names=["stratum_id", *(f"{s}{d}" for d in range(1, self.n + 1) for s in ("lo", "hi"))])


def register(spark: SparkSession) -> None:
    """Registers the source and lets filters reach it (a setting that may change at run time)."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(CubeDesign)
