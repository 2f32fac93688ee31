"""Python data source ``ladder``: block rows of a store by block range, pruned by the Parquet statistics.

``spark.dataSource.register(LadderSource)``, then ``spark.read.format("ladder").option("low", 10).load(folder)``; the
options ``low`` and ``high`` (both inclusive) bound ``blk``.  They are options and not pushed filters: with a
``pushFilters`` reader under Spark 4.1.2, a later count of the same DataFrame still had the bounds of the query before it.
The folder may be any that pyarrow opens; elsewhere read the store's Parquet with Spark itself.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "blk long, n_sym int, settled boolean, body string"


def save_blocks(blocks: DataFrame, folder: str) -> None:
    """Write ``(blk, n_sym, settled, body)`` so that ranges of blocks lie together."""
    blocks.select("blk", "n_sym", "settled", "body").repartitionByRange("blk").sortWithinPartitions("blk").write.parquet(folder)


class _Reader(DataSourceReader):
    def __init__(self, folder: str, low: str | None, high: str | None):
        self.folder = folder
        self.low, self.high = (None if x is None else int(x) for x in (low, high))

    def _dataset(self, *files: str):
        import pyarrow.dataset as ds
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(self.folder) if "://" in self.folder or self.folder.startswith("file:") else (fs.LocalFileSystem(), self.folder)
        return ds.dataset(list(files) or path, format="parquet", filesystem=store)

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(f) for f in self._dataset().files]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow.compute as pc

        wanted = None
        for bound in (self.low is not None and pc.field("blk") >= self.low, self.high is not None and pc.field("blk") <= self.high):
            if bound is not False:
                wanted = bound if wanted is None else wanted & bound
        yield from self._dataset(partition.value).to_batches(columns=["blk", "n_sym", "settled", "body"], filter=wanted)


class LadderSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ladder"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> _Reader:
        return _Reader(self.options["path"], self.options.get("low"), self.options.get("high"))
