"""A Python Data Source over saved index lists, with pruning by cell."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition


class _Cells(InputPartition):
    def __init__(self, group: str, cells: tuple[int, ...] | None):
        self.group, self.cells = group, cells


class IndexSource(DataSource):
    """format("nearcopy_index"), option path: a saved index in a file system that pyarrow opens. One partition a
    group of cells.

    option pruning true: filters on the cell choose the groups; the session must then have
    spark.sql.python.filterPushdown.enabled."""

    @classmethod
    def name(cls) -> str:
        return "nearcopy_index"

    def schema(self) -> str:
        return "id long, cell int, codes binary, self_dist double"

    def reader(self, schema) -> DataSourceReader:
        return (_PruningReader if self.options.get("pruning") == "true" else _Reader)(self.options["path"])


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.cells = path.removeprefix("file://"), None

    def partitions(self):
        import pyarrow.dataset as ds

        found = ds.dataset(f"{self.path}/lists", partitioning="hive").files
        groups = sorted({p.rpartition("/")[0] for p in found})
        if self.cells is not None and groups:
            n = saved_groups(ds.dataset(f"{self.path}/manifest").to_table().column("manifest")[0].as_py())
            wanted = {f"cell_group={c % n}" for c in self.cells}
            groups = [g for g in groups if g.rpartition("/")[2] in wanted]
        return [_Cells(g, self.cells) for g in groups] or [_Cells("", None)]

    def read(self, partition):
        import pyarrow.dataset as ds

        if not partition.group:
            return
        rows = ds.dataset(partition.group)
        keep = ds.field("cell").isin(list(partition.cells)) if partition.cells is not None else None
        yield from rows.to_batches(columns=["id", "cell", "codes", "self_dist"], filter=keep)


class _PruningReader(_Reader):
    def pushFilters(self, filters):
        """Several filters on the cell are met by their common values."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("cell",):
                wanted = (f.value,)
            elif isinstance(f, In) and f.attribute == ("cell",):
                wanted = tuple(f.value)
            else:
                yield f
                continue
            self.cells = wanted if self.cells is None else tuple(c for c in self.cells if c in wanted)


def saved_groups(manifest: str) -> int:
    """The number of groups of cells that a saved index was written with."""
    return int(json.loads(manifest)["groups"])


def read_lists(spark: SparkSession, path: str, cells: list[int] | None = None) -> DataFrame:
    """The lists by Spark's own reader, which any store serves: cells prune the partition folders and row groups."""
    lists = spark.read.parquet(f"{path}/lists")
    if cells is None:
        return lists.drop("cell_group")
    groups = saved_groups(spark.read.parquet(f"{path}/manifest").first()[0])
    return lists.where(
        F.col("cell_group").isin(sorted({c % groups for c in cells})) & F.col("cell").isin(cells)
    ).drop("cell_group")
