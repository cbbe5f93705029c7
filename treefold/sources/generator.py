"""Synthetic trees of any size, from spark.range or as a data source named tree_gen."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

PARENTS = {
    "chain": "id - 1",
    "heap": "(id + 1) div 2 - 1",
    "random": "((id * 2654435761) % 4294967296) % id",
    "star": "0L",
    "caterpillar": "CASE WHEN id % 2 = 0 THEN id - 2 ELSE id - 1 END",
}


def generate(spark: SparkSession, kind: str, n: int, modulus: int = 1000) -> DataFrame:
    """Tree 0 of n vertices with weights id * 7919 mod modulus + 1."""
    weight = f"(id * 7919) % {modulus} + 1"
    rule = PARENTS[kind].replace("% id", "% greatest(id, 1)") if kind == "random" else PARENTS[kind]
    return spark.range(n).selectExpr("0L AS tree_id", "id AS node_id", f"CASE WHEN id > 0 THEN {rule} END AS parent_id", "0 AS child_ord", f"{weight} AS node_w", f"CASE WHEN id > 0 THEN {weight} END AS edge_w")


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__((first, last))
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, kind: str, n: int, parts: int):
        self.kind, self.n, self.parts = kind, n, parts

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Range(a, min(self.n, a + step)) for a in range(0, self.n, step)]

    def read(self, partition):
        import numpy as np
        import pyarrow as pa

        for first in range(partition.first, partition.last, 100_000):
            ids = np.arange(first, min(partition.last, first + 100_000), dtype=np.int64)
            safe = np.maximum(ids, 1)
            parent = {
                "chain": ids - 1,
                "heap": (ids + 1) // 2 - 1,
                "random": ((ids.astype(np.uint64) * np.uint64(2654435761)) % np.uint64(1 << 32)).astype(np.int64) % safe,
                "star": ids * 0,
                "caterpillar": np.where(ids % 2 == 0, ids - 2, ids - 1),
            }[self.kind]
            root, w = ids == 0, ids * 7919 % 1000 + 1
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids * 0), pa.array(ids), pa.array(parent, mask=root), pa.array((ids * 0).astype(np.int32)), pa.array(w), pa.array(w, mask=root)],
                ["tree_id", "node_id", "parent_id", "child_ord", "node_w", "edge_w"],
            )


class TreeGenerator(DataSource):
    """spark.read.format("tree_gen").options(kind=..., n=..., partitions=...).load()"""

    @classmethod
    def name(cls):
        return "tree_gen"

    def schema(self):
        return "tree_id long, node_id long, parent_id long, child_ord int, node_w long, edge_w long"

    def reader(self, schema):
        return _Reader(self.options.get("kind", "chain"), int(self.options.get("n", "1000")), int(self.options.get("partitions", "4")))


def register_generator(spark: SparkSession) -> None:
    spark.dataSource.register(TreeGenerator)
