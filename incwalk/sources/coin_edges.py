"""A Python data source: ``spark.read.format("coin_edges")`` draws a uniform random graph out of coins.

Options: ``nodes``, ``edges``, ``seed`` and ``partitions``. A partition draws its own range of edge
numbers, so nothing but the range travels to it and a retried one draws the same edges.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from incwalk.functions.coins import python_coin, sql_a, sql_b, sql_digest

#: Rows of a record batch.
BATCH = 10_000
_ARROW = pa.schema([("src", pa.int64()), ("dst", pa.int64()), ("ord", pa.int64())])


class Range(InputPartition):
    def __init__(self, first: int, end: int):
        super().__init__(first)
        self.first, self.end = first, end


class _Reader(DataSourceReader):
    def __init__(self, nodes: int, edges: int, seed: int, parts: int):
        self.nodes, self.edges, self.seed, self.parts = nodes, edges, seed, parts

    def partitions(self):
        cuts = [self.edges * i // self.parts for i in range(self.parts + 1)]
        return [Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition):
        for first in range(partition.first, partition.end, BATCH):
            ids = np.arange(first, min(first + BATCH, partition.end))
            ends = np.array([[c * self.nodes >> 32 for c in python_coin(self.seed, "uniform", i, 0, 0)] for i in ids.tolist()], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(ends[:, 0]), pa.array(ends[:, 1]), pa.array(ids)], schema=_ARROW)


class CoinEdges(DataSource):
    @classmethod
    def name(cls):
        return "coin_edges"

    def schema(self):
        return "src long, dst long, ord long"

    def reader(self, schema):
        number = lambda key, otherwise: int(self.options.get(key, otherwise))
        nodes, edges, parts = number("nodes", 1000), number("edges", 10_000), number("partitions", 8)
        if nodes < 1 or edges < 0 or parts < 1:
            raise ValueError("nodes and partitions must be positive, edges not negative")
        return _Reader(nodes, edges, number("seed", 1), parts)


def coin_edges_sql(nodes: int, edges: int, seed: int) -> str:
    return f"SELECT ({sql_a('h')} * {nodes}) >> 32 AS src, ({sql_b('h')} * {nodes}) >> 32 AS dst, id AS ord FROM (SELECT id, {sql_digest(seed, 'uniform', 'id', '0', '0')} AS h FROM range({edges}) t(id))"
