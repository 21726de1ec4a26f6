"""A Python data source of graphs with planted compatibilities in expectation: ``spark.read.format("planted")``.

Options: nodes, degree, strength, classes (3), seed, partitions.  Node i has class i % classes; each partition draws the arcs
of its own range of nodes, so a graph of any size is read in parallel and never held.  Exact counts need ``planted_graph``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.compat import strength_compat


class NodeRange(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


class PlantedReader(DataSourceReader):
    BATCH = 50_000

    def __init__(self, options: dict):
        self.n, self.degree = int(options.get("nodes", 1_000)), float(options.get("degree", 10))
        self.h, self.seed = float(options.get("strength", 8)), int(options.get("seed", 1))
        self.parts = max(1, int(options.get("partitions", 8)))
        if int(options.get("classes", 3)) != 3:
            raise ValueError("strengths are defined for 3 classes")

    def partitions(self) -> list[NodeRange]:
        cuts = [self.n * i // self.parts for i in range(self.parts + 1)]
        return [NodeRange(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: NodeRange) -> Iterator[pa.RecordBatch]:
        odds, each = np.cumsum(strength_compat(self.h), 1), max(1, round(self.degree / 2))
        for first in range(partition.first, partition.last, self.BATCH):
            nodes = np.arange(first, min(first + self.BATCH, partition.last))
            rng = np.random.default_rng([self.seed, first])
            src = np.repeat(nodes, each)
            cls = (rng.random(len(src))[:, None] > odds[src % 3]).sum(1).clip(0, 2)
            size = (self.n - cls + 2) // 3  # nodes of that class
            dst = np.floor(rng.random(len(src)) * size).astype(np.int64) * 3 + cls
            ok = (src != dst) & (size > 0)
            yield pa.RecordBatch.from_pydict({"src": src[ok].astype(np.int64), "dst": dst[ok]})


class PlantedSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> PlantedReader:
        return PlantedReader(dict(self.options))


def register(spark) -> None:
    spark.dataSource.register(PlantedSource)
